"""The stages on small tables, one after the other, and each against brute force."""

from collections import Counter

import corpus_pipeline
import numpy as np
from pyspark.sql import functions as F
from test_operators import brute_fingerprint

from stkfun.functions.shared import settle
from stkfun.llm import ftrl_quality, simhash_pivots, slot_sharding, source_mix, tiling_decontam

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = first = spark.read.parquet(f"{SF}/documents.parquet")
    sizes = [docs.count()]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = settle(stage(spark, docs, SF), "stage")
        sizes.append(docs.count())
        if k < len(corpus_pipeline.STAGES) - 1:
            assert docs.columns == first.columns, name
        if name == "simhash near-dedup":
            again = simhash_pivots.near_duplicates(docs, 5)
            assert again.select("root").distinct().count() == docs.count()
    assert sizes[0] > sizes[1] >= sizes[2] >= sizes[3] and sizes[-1] == sizes[-2]
    assert docs.columns == [*first.columns, "slot", "shard"]
    text = docs.select("doc_id", "text").distinct().join(first.select("doc_id", F.col("text").alias("was")), "doc_id")
    assert text.where("text <> was").count() == 0


def test_stages_take_empty_and_odd_tables(spark, edge_docs, empty_docs):
    for table in (empty_docs, edge_docs):
        docs = table
        for _, stage in corpus_pipeline.STAGES:
            docs = settle(stage(spark, docs, SF), "stage")
        assert docs.count() == 0 if table is empty_docs else docs.count() > 0


def test_each_stage_by_brute_force(spark):
    """Every stage's rows from its own input: scores, all pairs, all items, times, slots."""
    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    ids = lambda df: sorted(r.doc_id for r in df.select("doc_id").collect())

    model = ftrl_quality.fit(docs, spark.read.parquet(f"{SF}/labels.parquet"), training=ftrl_quality.in_training(F.col("doc_id")))
    good = [r.doc_id for r in ftrl_quality.score(docs, model).collect() if r.score >= 0.5]
    docs = settle(stages["quality classifier"](spark, docs, SF), "stage")
    assert ids(docs) == sorted(good)

    def shingles(text):
        w = (text or "").lower().split()
        return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}

    sets, fps, root = {i: shingles(rows[i].text) for i in good}, {i: brute_fingerprint(rows[i].text, 5) for i in good}, {i: i for i in good}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in good:
        for b in good:
            both = len(sets[a] & sets[b])
            if a < b and ((fps[a] ^ fps[b]).bit_count() <= 3 or 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both)):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    docs = settle(stages["simhash near-dedup"](spark, docs, SF), "stage")
    left = sorted(i for i in good if find(i) == i)
    assert ids(docs) == left and len(left) < len(good)

    items = [tiling_decontam.hashed_words(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    words = {i: tiling_decontam.hashed_words(rows[i].text) for i in left}
    leaks = lambda i: any(len(p) >= 3 and len(np.intersect1d(p, words[i])) >= 0.3 * len(np.unique(p)) and tiling_decontam.tile(p, words[i], 3) >= 0.5 * len(p) for p in items)
    clean = [i for i in left if not leaks(i)]
    docs = settle(stages["benchmark decontamination"](spark, docs, SF), "stage")
    assert ids(docs) == clean

    times = Counter({r.doc_id: r.times for r in source_mix.mixture(docs).collect()})
    docs = settle(stages["mixing to target weights"](spark, docs, SF), "stage")
    assert Counter(ids(docs)) == +times

    owner = slot_sharding.fill_slots([f"shard-{k}" for k in range(32)])
    for r in stages["sharding"](spark, docs, SF).collect():
        assert owner[r.slot] == int(str(r.shard).rsplit("-", 1)[-1])
