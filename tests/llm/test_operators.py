"""Every operator against brute force on a small table with all edge cases."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from stkfun.llm import divergence_rules, ftrl_quality, hpy_lm, license_scan, phrase_dedup, pii_sanitize, simhash_pivots, slot_sharding, source_mix, tiling_decontam
from stkfun.llm.batches import text_bytes, word_codes, word_hashes


def words(text, lower=False):
    b = (text or "").encode()
    return (b.lower() if lower else b).split()


def brute_fingerprint(text, n=3):
    w = words(text, True)
    if not w:
        return 0
    parts = [b" ".join(w[k : k + n]) for k in range(len(w) - n + 1)] or [b" ".join(w)]
    h = [xxhash.xxh64_intdigest(p, 42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum((x >> b) & 1 for x in h) > len(h))


def brute_components(fps, bits=3):
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(fps)):
        for b in range(a):
            if (fps[a] ^ fps[b]).bit_count() <= bits:
                root[find(a)] = find(b)
    return [find(x) for x in range(len(fps))]


def test_simhash(edge_docs, empty_docs, edge_rows):
    got = simhash_pivots.near_duplicates(edge_docs).select("doc_id", "fp", "component_id").collect()
    fps = [brute_fingerprint(r[1]) for r in edge_rows]
    comp = brute_components(fps)
    low = defaultdict(list)
    for r, c in zip(edge_rows, comp):
        low[c] += [r[0]] if r[0] is not None else []
    want = sorted(((r[0] if r[0] is not None else -1, f if f < 1 << 63 else f - (1 << 64), min(low[c], default=None)) for r, f, c in zip(edge_rows, fps, comp)), key=str)
    assert sorted(((r.doc_id if r.doc_id is not None else -1, r.fp, r.component_id) for r in got), key=str) == want
    assert simhash_pivots.near_duplicates(empty_docs).count() == 0
    kept = simhash_pivots.keep_one(edge_docs, shingle=3, similarity=None)
    assert kept.columns == edge_docs.columns
    assert kept.count() == len(set(comp))


def test_similar_texts_are_linked(spark):
    rng = np.random.default_rng(7)
    vocab = [f"v{i}" for i in range(500)]
    rows, groups = [], {}
    for g in range(60):
        base = list(rng.choice(vocab, 200))
        for c in range(3):
            text = list(base)
            if c:
                for at in rng.choice(200, 3, replace=False):
                    text[at] = f"edit{g}{c}{at}"
            rows.append((len(rows), " ".join(text)))
            groups[len(rows) - 1] = g
    half = rows[0][1].split()[:100] + list(rng.choice(vocab, 100))
    rows.append((len(rows), " ".join(half)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = {r.doc_id for r in simhash_pivots.keep_one(docs).collect()}
    assert kept == {3 * g for g in range(60)} | {len(rows) - 1}


def test_forest_of_a_dense_group():
    rng = np.random.default_rng(0)
    centre = np.uint64(rng.integers(0, 1 << 63))
    fps = {int(centre)}
    while len(fps) < 3000:
        x = int(centre)
        for b in rng.choice(64, rng.integers(1, 6), replace=False):
            x ^= 1 << int(b)
        fps.add(x)
    fps = np.array(sorted(fps | {int(v) for v in rng.integers(0, 1 << 62, 300)}), np.uint64)
    got = simhash_pivots.forest(fps, simhash_pivots.pivot_values(), 3)
    root = np.arange(len(fps))
    changed = True
    near = [np.flatnonzero(np.bitwise_count(fps ^ f) <= 3) for f in fps]
    while changed:
        new = np.array([root[n].min() for n in near])
        new = new[new]
        changed = (new != root).any()
        root = new
    assert (got == root).all()


def test_phrase_dedup(spark, edge_docs, empty_docs, edge_rows, monkeypatch):
    seen = Counter()
    for r in edge_rows:
        w = words(r[1])
        seen.update(tuple(w[k : k + 35]) for k in range(len(w) - 34))
    want = []
    for r in edge_rows:
        w = words(r[1])
        gone = [False] * len(w)
        for k in range(len(w) - 34):
            if seen[tuple(w[k : k + 35])] > 1:
                gone[k : k + 35] = [True] * 35
        want.append((r[0], len(w), sum(gone), hashlib.sha256(b" ".join(x for x, g in zip(w, gone) if not g)).hexdigest()))
    for size in (phrase_dedup.BLOCK_BYTES, 2000):
        monkeypatch.setattr(phrase_dedup, "BLOCK_BYTES", size)
        got = [tuple(r) for r in phrase_dedup.deduplicated(edge_docs).collect()]
        assert sorted(got, key=str) == sorted(want, key=str)
    assert phrase_dedup.deduplicated(empty_docs).count() == 0


def test_source_mix(spark, edge_docs, empty_docs):
    got = source_mix.mixture(edge_docs).toPandas()
    assert len(got) == edge_docs.count() and (got.taken == got.times * got["size"]).all() and (got.times <= 3).all()
    by = got.groupby(got.source.fillna("~")).agg(total=("size", "sum"), target=("target", "first"), taken=("taken", "sum"), most=("size", "max"))
    assert by.target.sum() == pytest.approx(by.total.sum())
    assert (by.target <= 3 * by.total + 1e-6).all() and ((by.taken - by.target).abs() <= by.most).all()
    again = source_mix.mixture(edge_docs.repartition(5)).toPandas()
    assert sorted(got.taken) == sorted(again.taken)
    assert source_mix.mixture(empty_docs).count() == 0
    rows = source_mix.mixed(edge_docs)
    assert rows.columns == edge_docs.columns and rows.count() == got.times.sum()


def test_source_targets_level_by_repeated_sharing(spark):
    sizes = [("a", 10), ("b", 1000), ("c", 5), ("d", 300), (None, 40)]
    df = spark.createDataFrame(sizes, "source string, source_size long")
    got = {r.source: r.target for r in source_mix.source_targets(df).collect()}
    w = {"a": 1, "b": 2, "c": 3, "d": 1, None: 2}
    target, open_, left = {}, {s for s, _ in sizes}, sum(n for _, n in sizes)
    while True:
        share = {s: left * w[s] / sum(w[x] for x in open_) for s in open_}
        over = {s for s in open_ if share[s] > 3 * dict(sizes)[s]}
        if not over:
            break
        for s in over:
            target[s] = 3 * dict(sizes)[s]
            left -= target[s]
        open_ -= over
    target |= share
    assert got == pytest.approx(target)


def test_pii(spark, edge_docs, empty_docs):
    rows = [(1, "write a@b.c_d@e.f or +1 (988) 555-2485\nthen 1.2.3.4.5.6.7.8 and 999.1.1.1"), (2, "4111 1111-1111 1111 é 👍 q@w.e"), (3, None), (4, "1" * 4000 + " x@" + "b." * 2000 + "c"), (None, "reveal zorgon a@b.cd now"), (5, "reveal zorgon a@b.cd too"), (6, "now and too")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in pii_sanitize.personal_spans(docs).select("doc_id", pii_sanitize.span_list(F.col("found")).alias("base"), pii_sanitize.span_list(pii_sanitize.all_spans(F.col("found"), F.col("terms"))).alias("spans")).collect()}
    for i, text in rows:
        spans = []
        for k, (kind, p) in enumerate((("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([ -]?[0-9])+"), ("phone", r"\+[0-9][ ().0-9-]+[0-9]"))):
            for m in re.finditer(p, text or ""):
                digits = re.sub("[^0-9]", "", m.group())
                luhn = sum(int(c) if j % 2 == 0 else (2 * int(c) - 9 * (int(c) > 4)) for j, c in enumerate(reversed(digits))) % 10 == 0
                ok = {"email": True, "ip": all(int(x) <= 255 for x in m.group().split(".")) if kind == "ip" else 0, "card": 12 <= len(digits) <= 19 and luhn, "phone": 9 <= len(digits) <= 15}[kind]
                if ok:
                    spans.append((m.start(), k, kind, m.end()))
        assert got[i].base == ",".join(f"{k}:{a}:{b}" for a, _, k, b in sorted(spans)), i
    assert "term:7:13" in got[5].spans and "term:0:6" in got[None].spans and got[6].spans == ""
    text = docs.where("doc_id = 2").select(pii_sanitize.sanitised(F.col("text"), pii_sanitize.entities(F.col("text"))).alias("s")).first().s
    assert text == "[CARD] é 👍 [EMAIL]"
    assert pii_sanitize.personal_spans(edge_docs).count() == edge_docs.count()
    assert pii_sanitize.personal_spans(empty_docs).count() == 0


def test_language_model(edge_docs, empty_docs, edge_rows):
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 10 == 0
    count = Counter()
    for r in edge_rows:
        if not held(r[0]):
            count.update(words(r[1], True) + [b""])
    n, v = sum(count.values()), len(count)
    want = sorted((str(r[0]), len(words(r[1])) + 1, sum(count[w] > 0 for w in words(r[1], True) + [b""]), round(sum(math.log10((count[w] + 0.1) / (n + 0.1 * (v + 1))) for w in words(r[1], True) + [b""]), 6)) for r in edge_rows)
    got = hpy_lm.scored(edge_docs).collect()
    assert sorted((str(r.doc_id), r.n_tokens, r.n_known, round(r.base_score, 6)) for r in got) == want
    assert all(r.train_tokens == n and r.held_out == held(r.doc_id) and r.score < 0 for r in got)
    again = hpy_lm.scored(edge_docs.repartition(2)).collect()
    assert sorted(round(r.score, 6) for r in again) == sorted(round(r.score, 6) for r in got)
    assert hpy_lm.scored(empty_docs).count() == 0


def test_spelling_is_a_distribution():
    spelling = hpy_lm.byte_restaurants(np.array([97 * 1, 97 * 256 + 98, (97 * 256 + 98) * 256]), np.array([5, 3, 2]), 1)
    for ctx in (0, 97, 97 * 256 + 98):
        p = spelling.back[ctx] * spelling.lower[ctx & 255]
        for c, q in zip(spelling.cells, spelling.chance):
            if c >> 8 == ctx:
                p[c & 255] = q
        assert p.sum() == pytest.approx(1, abs=1e-6)


def test_language_model_hears_the_order_of_words(spark):
    rng = np.random.default_rng(4)
    follow = rng.permutation(40)
    rows = []
    for i in range(400):
        w = [int(rng.integers(40))]
        while len(w) < 30:
            w.append(int(follow[w[-1]]) if rng.random() < 0.8 else int(rng.integers(40)))
        rows.append((i, " ".join(f"v{x}" for x in w)))
    rows += [(1000 + k, " ".join(reversed(rows[k][1].split()))) for k in range(20)] + [(2000, "v1 neverseen v2"), (2001, "v1 neverseenatall v2")]
    got = {r.doc_id: r for r in hpy_lm.scored(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    held = [k for k in range(400) if got[k].held_out]
    assert sum(got[k].score for k in held) > sum(got[k].base_score for k in held)
    assert sum(got[k].score for k in range(400) if not got[k].held_out) > sum(got[k].base_score for k in range(400) if not got[k].held_out)
    assert sum(got[k].score - got[1000 + k].score for k in range(20)) > 20 * 5
    assert got[2000].score > got[2001].score  # unseen words are spelled, longer ones are less likely


def test_pairs_of_rare_words_have_restaurants(spark, monkeypatch):
    """Four dishes and eight words in memory: the order of all other words is heard no less."""
    rng = np.random.default_rng(4)
    follow = rng.permutation(40)
    rows = []
    for i in range(400):
        w = [int(rng.integers(40))]
        while len(w) < 30:
            w.append(int(follow[w[-1]]) if rng.random() < 0.8 else int(rng.integers(40)))
        rows.append((i, " ".join(f"v{x}" for x in w)))
    rows += [(1000 + k, " ".join(reversed(rows[k][1].split()))) for k in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(hpy_lm, "DISHES", 4)
    many = {r.doc_id: r.score for r in hpy_lm.scored(docs).collect()}
    monkeypatch.setattr(hpy_lm, "HOT_WORDS", 8)
    few = {r.doc_id: r.score for r in hpy_lm.scored(docs).collect()}
    assert few == pytest.approx(many, rel=1e-9)
    assert sum(few[k] - few[1000 + k] for k in range(20)) > 20 * 10


def test_pair_restaurants_by_brute_force(spark, monkeypatch):
    """Pairs of one training token leave nothing to chance; buckets and tiers of words do not matter."""
    monkeypatch.setattr(hpy_lm, "HOT_WORDS", 6)
    monkeypatch.setattr(hpy_lm, "DISHES", 3)
    rows = [(k, " ".join(f"w{(k + 1) * j % 31}" for j in range(1, 9))) for k in range(14)]
    seen, kept = set(), []
    for i, text in rows:
        w = ["^", *text.split(), ""]
        pairs = set(zip(w, w[1:]))
        if zlib.crc32(str(i).encode()) % 10 == 0 or not pairs & seen:
            kept.append((i, text))
            seen |= pairs if zlib.crc32(str(i).encode()) % 10 else set()
    held = lambda i: zlib.crc32(str(i).encode()) % 10 == 0
    if not any(held(i) for i, _ in kept):
        kept.append((next(i for i in range(100, 200) if held(i)), rows[0][1] + " w1 unseen"))
    src = spark.createDataFrame([(i, held(i), t) for i, t in kept], "doc_id long, held boolean, text string")
    words_, n, v = hpy_lm.lexicon(src, 1)
    hot = hpy_lm.hot_words(words_)
    state = hpy_lm.pair_buckets(src, words_, hot, n)
    _, slots, few = hpy_lm.summed(state, hot, lambda b: [np.minimum(b.c, 1), b.c], 2, False)
    count, ctx = Counter(), Counter()
    for i, t in kept:
        if not held(i):
            w = ["^", *t.split(), ""]
            count.update(zip(w, w[1:]))
            ctx.update(w[:-1])
    assert max(count.values()) == 1 and few.tolist() == [len(count), 0]
    d = hpy_lm.rate(*few)
    chance = type("Chance", (), {"value": np.full((hpy_lm._CONTEXTS, hot.dishes + 1), np.log10(1 / (hot.dishes + 1)))})()
    s = hpy_lm.Seating(hot, d, slots[:, 1], (slots[:, 0],) * 4, chance)
    got = Counter()
    for batch in hpy_lm._scorer(s, 2, n, v)(iter(state.toArrow().to_batches())):
        for r in (r for r in batch.to_pylist() if r["lp"] is not None):
            for uid, lp in zip(hpy_lm._unpacked(r["uid"], np.int64), hpy_lm._unpacked(r["lp"], np.float64)):
                got[int(uid)] += lp
    lexicon = {r.wh: r.lp for r in words_.collect()}
    top = {int(h) for h, k in zip(hot.ids.view(np.int64), hot.rank) if k < hot.dishes}
    want = []
    for _, t in kept:
        w = ["^", *t.split(), ""]
        total = 0.0
        for a, b in zip(w, w[1:]):
            raw = np.frombuffer(b.encode(), np.uint8)
            h = int(hpy_lm.word_hashes(raw, np.zeros(1, np.int64), np.full(1, len(raw)))[:1].view(np.int64)[0])
            parent = 1 / (hot.dishes + 1) * (1 if h in top else 10 ** lexicon[h] / hot.base()[-1])
            total += math.log10((count[a, b] * (1 - d) + (1 + d * ctx[a]) * parent) / (1 + ctx[a]))
        want.append(total)
    assert sorted(got.values()) == pytest.approx(sorted(want), rel=1e-6)


def test_context_restaurants_by_brute_force(spark):
    """Customers seated alone leave nothing to chance: the three levels by their formulas."""
    width = 6
    cells = {0: {0: 1, 1: 1, 5: 1}, 3: {1: 1, 2: 1}, hpy_lm._CONTEXTS - 1: {4: 1}}
    table = spark.createDataFrame([(c, list(d), list(d.values())) for c, d in cells.items()], "context int, w array<int>, c array<long>")
    base = np.array([0.3, 0.2, 0.2, 0.1, 0.1, 0.1])
    got = 10.0 ** hpy_lm.context_model(table, base).astype(float)
    assert got.sum(1) == pytest.approx(np.ones(len(got)), abs=1e-4)
    k = np.zeros(width)
    for d in cells.values():
        for w in d:
            k[w] += 1
    discount = hpy_lm.rate(6, 0)
    mean = np.zeros((2, width))
    for tables in (1, 2):  # dish 1 has two customers: one or two tables
        s = np.where(k == 2, tables, np.minimum(k, 1))
        d0 = hpy_lm.rate((k == 1).sum(), (k == 2).sum())
        root = (k - d0 * s + (1 + d0 * s.sum()) * base) / (1 + k.sum())
        p = (1 + discount * 3) * root
        p[[0, 1, 5]] += 1 - discount
        mean[tables - 1] = p / (1 + 3)
    low, high = mean.min(0) - 1e-4, mean.max(0) + 1e-4
    assert ((got[0] >= low) & (got[0] <= high)).all()


def test_quality_rules(edge_docs, empty_docs, edge_rows):
    want = []
    for r in edge_rows:
        w = words(r[1])
        t = r[1] or ""
        grams = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        c = Counter(grams)
        hit = set().union(*[{k, k + 1, k + 2} for k, g in enumerate(grams) if c[g] > 1] or [set()])
        lines = [x for x in t.split("\n") if x.encode().split()]
        want.append((r[0], len(w), sum(len(x.decode()) for x in w), sum(x in "#*$%&|<>" for x in t), len(lines) - len(set(lines)), len(hit), len(w) < 50 or 100 * len(hit) > 50 * len(w)))
    got = divergence_rules.judged(edge_docs).collect()
    assert sorted(((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in got), key=str) == sorted(want, key=str)
    assert not any(r.kept and r.base_failed for r in got)
    assert divergence_rules.judged(empty_docs).count() == 0


def test_distance_bounds(spark):
    df = spark.createDataFrame([([1, 0], [5, 0]), ([1, 0], [0, 2]), ([0, 0], [1, 1])], "a array<long>, b array<long>")
    got = [r[0] for r in df.select(divergence_rules.distance(F.col("a"), F.col("b"))).collect()]
    assert got[0] == pytest.approx(0) and got[1] == pytest.approx(1) and got[2] is None


def test_quality_classifier(spark, edge_docs, empty_docs):
    rng = np.random.default_rng(2)
    good = [" ".join(rng.choice(["the", "cat", "sat", "mat", "on"], 40)) for _ in range(200)]
    bad = [" ".join(w + "###" for w in rng.choice(["the", "cat", "sat", "mat", "on"], 40)) for _ in range(200)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(good + bad)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 200)) for i in range(400)] + [(0, 1), (999, 1), (5, None)], "doc_id long, quality int")
    model = ftrl_quality.fit(docs, labels, training=ftrl_quality.in_training(F.col("doc_id")))
    got = ftrl_quality.score(docs, model).collect()
    assert all((r.score >= 0.7) == (r.doc_id < 200) for r in got)
    assert ftrl_quality.score(edge_docs, model).count() == edge_docs.count()
    assert ftrl_quality.score(empty_docs, model).count() == 0
    assert ftrl_quality.keep_good(edge_docs, model).columns == edge_docs.columns
    none = ftrl_quality.fit(docs, labels.limit(0))
    assert {r.score for r in ftrl_quality.score(docs, none).collect()} == {0.5}


def test_tiling(spark, edge_docs, empty_docs):
    w = tiling_decontam.hashed_words
    assert tiling_decontam.tile(w("a b c d e f g h i j"), w("f g h i j x a b c d e"), 3) == 10
    assert tiling_decontam.tile(w("a b c d e f"), w("a b c x d e f a b c d"), 3) == 4
    assert tiling_decontam.tile(w("a b"), w("a b"), 3) == 0
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lamda mu"
    bench = spark.createDataFrame([(1, item), (2, "too short"), (3, None), (1, item)], "item_id long, text string")
    moved = "noise " + " ".join(item.upper().split()[6:]) + " filler words " + " ".join(item.split()[:6])
    docs = spark.createDataFrame([(1, moved), (2, "alpha beta gamma and nothing else of it"), (3, None), (4, item[:40])], "doc_id long, text string")
    for block in (10**6, 1):
        got = {r.doc_id: r for r in tiling_decontam.contamination(docs, bench, block_words=block).collect()}
        assert got[1].coverage == 1.0 and got[1].n_items == 2 and got[1].best_item == 1 and got[2].n_items == 0 and got[3].n_items == 0
    assert sorted(r.doc_id for r in tiling_decontam.keep_clean(docs, bench).collect()) == [2, 3]
    assert tiling_decontam.contamination(edge_docs, bench.limit(0)).where("n_items > 0").count() == 0
    assert tiling_decontam.contamination(empty_docs, bench).count() == 0


def test_sharding(spark, edge_docs, empty_docs):
    owner = slot_sharding.fill_slots([f"shard-{i}" for i in range(32)])
    sizes = Counter(owner)
    assert len(owner) == slot_sharding.SLOTS and max(sizes.values()) - min(sizes.values()) <= 1
    fewer = slot_sharding.fill_slots([f"shard-{i}" for i in range(31)])
    moved = sum(a != b for a, b in zip(owner, fewer) if a != 31)
    assert moved < 0.25 * slot_sharding.SLOTS
    got = slot_sharding.sharded(edge_docs)
    assert got.count() == edge_docs.count() and got.columns == [*edge_docs.columns, "slot", "shard"]
    assert got.groupBy("doc_id").agg(F.countDistinct("shard").alias("n")).where("n > 1").count() == 0
    assert slot_sharding.sharded(empty_docs).count() == 0
    with pytest.raises(ValueError):
        slot_sharding.fill_slots(["a"], 10)


def test_licences(spark, edge_docs, empty_docs):
    rows = [(1, "a/LICENSE", "Released under the MIT License."), (2, "a/b/c/x.py", "code"), (3, "a/b/COPYING", "Licensed under CC BY-NC 4.0."), (4, "a/y.py", "Licensed under the Apache License, Version 2.0.\n" + "foo bar " * 30), (5, "z/q.py", "nothing"), (6, None, "x"), (7, "a/b/w.py", None), (None, "top.py", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, path string, text string")
    got = {r.doc_id: (r.own, r.licence, r.origin) for r in license_scan.licences(docs).collect()}
    assert got[1] == ("MIT", "MIT", "own") and got[2] == (None, "CC-BY-NC-4.0", "a/b") and got[4] == ("Apache-2.0", "Apache-2.0", "own")
    assert got[7] == (None, "CC-BY-NC-4.0", "a/b") and got[5] == got[6] == got[None] == (None, None, None)
    pathed = edge_docs.withColumn("path", license_scan.document_path())
    assert license_scan.licences(pathed).count() == edge_docs.count()
    assert license_scan.licences(empty_docs.withColumn("path", F.lit("a"))).count() == 0


def test_varied_copies_of_one_text_are_all_linked(spark):
    """Copies are similar to the original only, and share its bands in large buckets."""
    rng = np.random.default_rng(11)
    base = [f"b{i}" for i in range(300)]
    rows = [(1000, " ".join(base))]
    for c in range(400):
        text = list(base)
        for at in rng.choice(58, 5, replace=False) * 5 + 5:
            text[at] = f"edit{c}x{at}"
        rows.append((c + 1001, " ".join(text)))
    sets = [{tuple(t.split()[k : k + 5]) for k in range(296)} for _, t in rows]
    jaccard = lambda a, b: len(a & b) / len(a | b)
    assert min(jaccard(sets[0], s) for s in sets[1:]) > 0.8 and np.mean([jaccard(sets[k], sets[k + 1]) for k in range(1, 400)]) < 0.75
    kept = simhash_pivots.keep_one(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()
    assert [r.doc_id for r in kept] == [1000]


def test_similarity_bound_is_exact(spark):
    """Pairs of a text and a copy with its tail changed: 0.8 similar exactly, or just below."""
    rows, want = [], set()
    for g in range(300):
        base = [f"p{g}w{i}" for i in range(94)]
        for kind, tail in ((0, 10), (1, 11)):
            at, name = len(rows), f"{g}k{kind}"
            rows += [(at, " ".join(name + w for w in base)), (at + 1, " ".join([name + w for w in base[: 94 - tail]] + [f"{name}t{i}" for i in range(tail)]))]
            a, b = ({tuple(t.split()[k : k + 5]) for k in range(90)} for _, t in rows[-2:])
            similar = 5 * len(a & b) >= 4 * len(a | b)
            assert similar == (kind == 0) and (kind or 5 * len(a & b) == 4 * len(a | b))
            want |= {at} if similar else {at, at + 1}
    fps = [brute_fingerprint(t, 5) for _, t in rows]
    want -= {k + 1 for k in range(0, len(rows), 2) if (fps[k] ^ fps[k + 1]).bit_count() <= 3}
    kept = {r.doc_id for r in simhash_pivots.keep_one(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    assert kept == want


def test_repeated_ids_keep_different_texts(spark):
    rng = np.random.default_rng(3)
    a, b, c = (" ".join(rng.choice([f"r{i}" for i in range(300)], 80)) for _ in range(3))
    docs = spark.createDataFrame([(3, a), (5, a), (5, b), (None, c), (None, c), (None, a)], "doc_id long, text string")
    for similarity in (None, 0.8):
        kept = sorted(((r.doc_id or 0, r.text) for r in simhash_pivots.keep_one(docs, similarity=similarity).collect()))
        assert kept == sorted([(3, a), (5, b), (0, c)])


def test_tiling_keeps_rows_over_many_blocks(spark):
    items = [(k, " ".join(f"i{k}w{j}" for j in range(12))) for k in range(4)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    texts = [items[0][1], "clean text of no item", items[3][1] + " " + items[1][1], None, "also clean", items[2][1][:12]]
    docs = spark.createDataFrame(list(zip([None, None, 7, 7, 8, 8], texts)), "doc_id long, text string")
    want = sorted([(None, 1, 0), (None, 0, None), (7, 2, 1), (7, 0, None), (8, 0, None), (8, 0, None)], key=str)
    for block in (10**6, 1):
        got = tiling_decontam.contamination(docs, bench, block_words=block).collect()
        assert sorted([(r.doc_id, r.n_items, r.best_item) for r in got], key=str) == want
        assert tiling_decontam.keep_clean(docs, bench, block_words=block).count() == 4


def brute_tile(a, b, n):
    """Greedy tiling by the definition: the longest unmarked common run first."""
    pa_, pb, total = [False] * len(a), [False] * len(b), 0
    while True:
        best = (0, 0, 0)
        for i in range(len(a)):
            for j in range(len(b)):
                k = 0
                while i + k < len(a) and j + k < len(b) and a[i + k] == b[j + k] and not pa_[i + k] and not pb[j + k]:
                    k += 1
                best = max(best, (k, -i, -j))
        if best[0] < n:
            return total
        k, i, j = best[0], -best[1], -best[2]
        pa_[i : i + k] = pb[j : j + k] = [True] * k
        total += k


def test_tiling_covers_as_much_as_brute_force():
    rng = np.random.default_rng(9)
    for _ in range(60):
        a = [f"t{x}" for x in rng.integers(0, 6, rng.integers(3, 25))]
        cut = sorted(rng.integers(0, len(a), 2))
        b = a[cut[1] :] + [f"t{x}" for x in rng.integers(0, 6, 4)] + a[: cut[1]]
        got = tiling_decontam.tile(tiling_decontam.hashed_words(" ".join(a)), tiling_decontam.hashed_words(" ".join(b)), 3)
        want = brute_tile(a, b, 3)
        # Ties of equally long runs may be taken in another order.
        assert abs(got - want) <= 3 and (got > 0) == (want > 0)


def test_equal_keys_take_no_more_than_fits(spark):
    text = "w " * 100
    rows = [(None, text, "a") for _ in range(50)] + [(k, "v " * 30, "b") for k in range(100)] + [(k, "z " * 9, None) for k in range(5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    got = source_mix.mixture(docs).toPandas()
    by = got.groupby(got.source.fillna("~")).agg(target=("target", "first"), taken=("taken", "sum"))
    assert ((by.taken - by.target).abs() <= 100).all()
    assert source_mix.mixed(docs).count() == got.times.sum()


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    got = ftrl_quality.op9_query(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out and quality is not null")
    one = got.agg(F.avg((F.col("predicted") == F.col("quality")).cast("int")).alias("a"), F.count("*").alias("n")).first()
    assert one.n > 20 and one.a > 0.95


def test_automaton_decides_what_goes():
    """Passages and windows are held against the words where a phrase is located, and nowhere else."""
    words = [f"w{k}".encode() for k in range(60)]
    raw = np.frombuffer(b" ".join(words), np.uint8)
    starts, ends, _ = phrase_dedup.word_spans(raw, np.array([0, len(raw)]))
    h = phrase_dedup.word_hashes(raw, starts, ends)
    phrase = " ".join(f"w{k}" for k in range(20, 28))
    none, key = np.zeros(0, np.int64), np.array([5], np.int64)
    covered = lambda shard, text: np.flatnonzero(shard.confirmed(text)).tolist()
    one = phrase_dedup.span_hashes(h, np.array([2]), np.array([35])).view(np.int64)
    loose = phrase_dedup.Shard((key, one), (none,) * 4, [(5, phrase)], 35, 8)
    assert covered(loose, words) == list(range(2, 37)) and covered(loose, [b"x"] * 3 + words) == list(range(5, 40))
    assert covered(loose, words[:21] + [b"other"] + words[21:]) == []
    at, many, off = np.array([10]), np.array([4]), np.array([10])
    d = phrase_dedup.passage_hashes(h, at, many, off, 35).view(np.int64)
    whole = phrase_dedup.Shard((none, none), (key, d, off, many), [(5, phrase)], 35, 8)
    assert covered(whole, words) == list(range(10, 48)) and covered(whole, words[:40]) == []
    assert covered(phrase_dedup.Shard((key, one), (key, d, off, many), [], 35, 8), words) == []


def test_revealing_terms_by_brute_force(spark):
    rng = np.random.default_rng(12)
    vocab = [f"t{i}" for i in range(30)]
    mails = [f"p{i}@x.org" for i in range(4)]
    rows = []
    for i in range(120):
        w = list(rng.choice(vocab, int(rng.integers(5, 60))))
        for m in range(4):
            if rng.random() < 0.15:
                at = int(rng.integers(len(w)))
                w[at:at] = [f"near{m}", mails[m], str(rng.choice(vocab))]
        rows.append((i, "".join(x + str(rng.choice([" ", " ", " ", "\n"])) for x in w)))
    reach = 30
    near = set()
    count = Counter(x for _, t in rows for x in t.split())
    n = sum(count.values())
    for i, t in rows:
        spots = [(m.start(), m.end(), m.group()) for m in re.finditer(r"\S+", t)]
        hits = [s for s in spots if "@" in s[2]]
        for a, b, e in hits:
            for x, y, term in spots:
                inside = a - reach <= x and y <= a or x >= b and y <= b + reach
                if inside and "\n" not in t[min(x, a) : max(y, b)] and not any(x < q and p < y for p, q, _ in hits):
                    near.add((i, e, term, x, y))
    both, n_rows, n_e = Counter(), defaultdict(set), Counter()
    for i, e, term, _, _ in near:
        both[e, term] += 1
        n_rows[e, term].add(i)
        n_e[e] += 1
    told = {k for k, v in both.items() if len(n_rows[k]) >= 2 and math.log2(v * n / (count[k[1]] * n_e[k[0]])) >= 0.8 * math.log2(n / n_e[k[0]])}
    want = {(i, x, y) for i, e, term, x, y in near if (e, term) in told}
    got = pii_sanitize.personal_spans(spark.createDataFrame(rows, "doc_id long, text string"), reach=reach).select("doc_id", F.explode("terms").alias("t")).collect()
    assert len(want) > 10 and {(r.doc_id, r.t.start, r.t.end) for r in got} == want


def test_a_long_line_of_entities_is_scanned_once(spark):
    rng = np.random.default_rng(1)
    line = " ".join(f"w{rng.integers(900)}" if k % 20 else f"u{k}@h{k}.org" for k in range(20_000))
    got = pii_sanitize.personal_spans(spark.createDataFrame([(1, line), (2, line)], "doc_id long, text string")).select(F.size("found").alias("n")).collect()
    assert [r.n for r in got] == [1000, 1000]


def brute_notice(text):
    """Best (score, name) over all blocks of a text, by the definitions."""
    term = re.compile(license_scan._TERM)
    rows = [(n, term.findall(t)) for n, ts in license_scan.TEMPLATES.items() for t in ts]
    idf = lambda t: round(1000 * (1 + math.log((1 + len(rows)) / (1 + sum(t in b for _, b in rows)))))
    vec = lambda ts: {t: ts.count(t) * idf(t) for t in set(ts)}
    norm = lambda v: math.sqrt(sum(x * x for x in v.values()))
    lines = text.split("\n")
    blocks = [text] if re.search(license_scan._CUE, text) else []
    for i, x in enumerate(lines):
        if re.search(license_scan._CUE, x):
            blocks += [" ".join(lines[max(i + a, 0) :][:n]) for a, n in ((0, 1), (-1, 2), (0, 2), (-1, 3), (-2, 5))]
    best = (0.0, None)
    for b in blocks:
        v = vec(term.findall(b.lower()))
        for n, ts in rows:
            w = vec(ts)
            dot = sum(v.get(t, 0) * w[t] for t in w)
            if dot and dot / norm(v) / norm(w) > best[0] + 1e-12:
                best = (dot / norm(v) / norm(w), n)
    return best


def test_licence_blocks_by_brute_force(spark):
    texts = [
        "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0. If a copy of it was not given, ask.", "// SPDX-License-Identifier: MIT\nint main() {}",
        "# SPDX-License-Identifier: Apache-2.0", "GNU GENERAL PUBLIC LICENSE\nVersion 3, 29 June 2007\n\n" + "Everyone may copy this text. " * 30,
        "This work is free; it is licensed under the terms of the GNU General\nPublic License\nversion 3 of it", "All rights reserved.", "no cue here", "license " * 400 + "x",
        "some prose about a driving license " + "and other words " * 50, "Permission is hereby granted, free of charge,\nto any person obtaining a copy\nof this software and associated\ndocumentation files",
    ]
    docs = spark.createDataFrame([(i, "a/b.txt", t) for i, t in enumerate(texts)], "doc_id long, path string, text string")
    got = {r.doc_id: r for r in license_scan.scan(docs).collect()}
    for i, t in enumerate(texts):
        score, name = brute_notice(t)
        assert got[i].score == pytest.approx(score, abs=1e-9) and got[i].own == (name if score >= license_scan.THRESHOLD else None), t
    assert [got[i].own for i in (0, 1, 2, 3, 6, 9)] == ["MPL-2.0", "MIT", "Apache-2.0", "GPL-3.0", None, "MIT"]


def test_periodic_texts_lose_all_words(spark):
    """Every window of them recurs, at each of very many located phrases."""
    rows = [(1, "a " * 60_000), (2, "a " * 50), (3, "b c " * 20_000), (4, "d " * 35), (5, "e " * 36)]
    got = {r.doc_id: (r.n_words, r.n_removed) for r in phrase_dedup.deduplicated(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: (60_000, 60_000), 2: (50, 50), 3: (40_000, 40_000), 4: (35, 0), 5: (36, 36)}


def test_words_are_looked_up_once_a_batch(monkeypatch):
    texts = [" b\x0bA  a\tb  \x1cb ", "", None, "\n", "Äa a", "a b " * 2000]
    batch = pa.RecordBatch.from_pydict({"uid": list(range(6)), "doc_id": list(range(6)), "held": [False] * 6, "text": texts})
    code, words, counts = word_codes(batch.column("text"))
    want = [(t or "").encode().lower().split() for t in texts]
    assert [words[c].as_py().encode() for c in code.tolist()] == [w for t in want for w in t] and counts.tolist() == [len(t) for t in want]
    raw, off = text_bytes(words)
    ids = np.unique(np.append(word_hashes(raw, off[:-1], off[1:]), np.uint64(0)))
    hot = hpy_lm.HotWords(ids[:3], np.ones(3, np.int64), np.zeros(3), np.arange(3), 3)
    asked, look_up = [], hpy_lm.HotWords.look_up
    monkeypatch.setattr(hpy_lm.HotWords, "look_up", lambda self, h: asked.append(len(h)) or look_up(self, h))
    blocks = list(hpy_lm._blocks(hot, 5)(iter([batch])))
    list(hpy_lm._rare_words(hot, 5)(iter([batch])))
    assert sum(asked) <= 2 * (len(words) + 1)
    pairs = Counter((i, u, w) for i, t in enumerate(want) for u, w in zip([None, *t], [*t, b""]))
    got = [hpy_lm._unpacked(x, np.uint32) for b in blocks for x in b.column("times").to_pylist()]
    assert sorted(np.concatenate(got).tolist()) == sorted(pairs.values())
