"""Licence scans, in DataFrame functions only.

Texts that hold a cue word are scored in blocks: the whole text, every line with a
cue, and the runs of two to five adjacent lines around it, so that notices wrapped
over lines and whole licence files count as well as single lines. A block's terms
(runs of letters, digits and dots, lower-cased) are weighed against each template
by the cosine of sparse TF-IDF vectors, the inverse document frequency being that
of the templates; a file takes the template of its best block at or above
``threshold``. Files whose notices make up most of the text, or that carry a
licence file's name, speak for their directory: a file without a notice of its
own inherits from the nearest ancestor directory that has one, found by joining
its ancestors' paths.

Weights are fixed-point integers, so sums do not depend on their order.

Defined cases: null and wordless texts have no notice; null paths neither
inherit nor speak for a directory; ties of score take the smallest licence name,
ties between licence files of a directory the best score, then name, then path;
rows are kept one to one, repeated rows and null ids included; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stkfun.functions.shared import settle
from stkfun.llm.divergence_rules import let

THRESHOLD = 0.5
SCALE = 1000
FILE_NAMES = r"(?i)^(licen[sc]e|copying|unlicense|notice)([-.].*)?$"

#: Short public notices by licence name.
TEMPLATES = {
    "Apache-2.0": ["licensed under the apache license version 2.0", "apache license version 2.0 january 2004", "spdx license identifier apache 2.0"],
    "BSD-2-Clause": ["bsd 2 clause license", "spdx license identifier bsd 2 clause"],
    "BSD-3-Clause": ["redistribution and use in source and binary forms with or without modification are permitted bsd license", "bsd 3 clause license", "spdx license identifier bsd 3 clause"],
    "CC-BY-4.0": ["this work is licensed under a creative commons attribution 4.0 international license cc by 4.0", "licensed under cc by 4.0"],
    "CC-BY-NC-4.0": ["licensed under cc by nc 4.0", "creative commons attribution noncommercial 4.0 international license"],
    "CC-BY-SA-4.0": ["licensed under cc by sa 4.0", "creative commons attribution sharealike 4.0 international license"],
    "CC0-1.0": ["cc0 1.0 universal public domain dedication"],
    "GPL-2.0": ["this program is free software licensed under the gnu general public license version 2", "gnu general public license version 2 june 1991", "spdx license identifier gpl 2.0"],
    "GPL-3.0": ["this work is licensed under the gnu general public license version 3", "gnu general public license version 3 29 june 2007", "gnu general public license", "spdx license identifier gpl 3.0"],
    "ISC": ["permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "spdx license identifier isc"],
    "LGPL-3.0": ["licensed under the gnu lesser general public license version 3", "gnu lesser general public license version 3 29 june 2007", "spdx license identifier lgpl 3.0"],
    "MIT": ["released under the mit license", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "licensed under the mit license", "spdx license identifier mit"],
    "MPL-2.0": ["this source code form is subject to the terms of the mozilla public license v. 2.0", "mozilla public license version 2.0", "spdx license identifier mpl 2.0"],
    "Proprietary": ["copyright all rights reserved", "copyright c all rights reserved proprietary and confidential"],
    "Unlicense": ["this is free and unencumbered software released into the public domain", "spdx license identifier unlicense"],
}
_CUE = r"(?i)licen[sc]e|copyright|rights reserved|released (?:under|into)|redistribution|permission|mozilla public|creative commons|public domain|spdx"
_TERM = r"[a-z0-9]+(?:\.[0-9]+)*"


def template_weights(templates: dict[str, list[str]] | None = None) -> tuple[list[str], dict[str, list[int]], list[float]]:
    """The name of each template, term -> its idf and its weight in each template (integers), template norms."""
    templates = templates or TEMPLATES
    rows = [(n, re.findall(_TERM, t)) for n in sorted(templates) for t in templates[n]]
    bags = [{t: terms.count(t) for t in terms} for _, terms in rows]
    df = {t: sum(t in b for b in bags) for b in bags for t in b}
    idf = {t: round(SCALE * (1 + math.log((1 + len(rows)) / (1 + n)))) for t, n in df.items()}
    weights = {t: [idf[t], *(b.get(t, 0) * idf[t] for b in bags)] for t in idf}
    norms = [math.sqrt(sum(w[i + 1] ** 2 for w in weights.values())) for i in range(len(rows))]
    return [n for n, _ in rows], weights, norms


def unseen_weight(n_templates: int) -> int:
    """The weight of a term that no template has."""
    return round(SCALE * (1 + math.log(1 + n_templates)))


def notice_scores(block: Column, templates: dict[str, list[str]] | None = None) -> Column:
    """Best (score, name) of one block, as struct(minus, name)."""
    names, weights, norms = template_weights(templates)
    terms = sorted(weights)
    # Constants that the optimizer folds; products hold one run of weights for each term.
    known = F.split(F.lit(" ".join(terms)), " ")
    numbers = lambda values: F.split(F.lit(" ".join(map(str, values))), " ").cast("array<long>")
    idf = numbers(weights[t][0] for t in terms)
    products = numbers(weights[t][0] * w for t in terms for w in weights[t][1:])
    long = lambda v: F.lit(v).cast("long")

    def squared(run: Column, at: Column) -> Column:
        part = run * F.when(at > 0, F.get(idf, at - 1)).otherwise(long(unseen_weight(len(names))))
        return part * part

    def rate(words: Column) -> Column:
        # Equal terms are neighbours: their number is known when the next term begins.
        def step(acc: Column, w: Column) -> Column:
            same = w["term"] == acc["term"]
            return F.struct(w["term"].alias("term"), w["at"].alias("at"), F.when(same, acc["run"] + 1).otherwise(long(1)).alias("run"), F.when(same, acc["sq"]).otherwise(acc["sq"] + squared(acc["run"], acc["at"])).alias("sq"))

        start = F.struct(F.lit("").alias("term"), F.lit(0).alias("at"), long(0).alias("run"), long(0).alias("sq"))
        norm = F.aggregate(words, start, step, lambda acc: F.sqrt((acc["sq"] + squared(acc["run"], acc["at"])).cast("double")))
        dots = F.aggregate(F.filter(words, lambda w: w["at"] > 0), F.array_repeat(long(0), len(names)), lambda acc, w: F.zip_with(acc, F.slice(products, (w["at"] - 1) * len(names) + 1, F.lit(len(names))), lambda a, b: a + b))
        both = F.struct(norm.alias("norm"), dots.alias("dots"))
        return let(both, lambda v: F.array_min(F.array(*[F.struct((-F.get(v["dots"], F.lit(i)).cast("double") / (v["norm"] * norms[i])).alias("minus"), F.lit(n).alias("name")) for i, n in enumerate(names)])))

    words = F.transform(F.array_sort(F.regexp_extract_all(F.lower(block), F.lit(_TERM), F.lit(0))), lambda w: F.struct(w.alias("term"), F.array_position(known, w).cast("int").alias("at")))
    return let(words, rate)


def blocks_of(text: Column, lines: Column) -> Column:
    """The text and, around each line with a cue, the runs of one to five lines."""

    def around(i: Column) -> Column:
        run = lambda a, n: F.array_join(F.slice(lines, F.greatest(i + a, F.lit(0)) + 1, F.lit(n)), " ")
        return F.array(run(0, 1), run(-1, 2), run(0, 2), run(-1, 3), run(-2, 5))

    cued = F.filter(F.sequence(F.lit(0), F.size(lines) - 1), lambda i: F.rlike(F.get(lines, i), F.lit(_CUE)))
    return F.array_distinct(F.concat(F.array(text), F.flatten(F.transform(cued, around))))


def scan(files: DataFrame, threshold: float = THRESHOLD, path_col: str = "path", text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """doc_id, path, own, score, share (of words in notices) of every row."""
    src = files.select(F.col(id_col).alias("doc_id"), F.col(path_col).cast("string").alias("path"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t"))
    cued = F.rlike("t", F.lit(_CUE))
    blocks = F.when(cued, let(F.split("t", "\n", -1), lambda lines: blocks_of(F.col("t"), lines))).otherwise(F.array().cast("array<string>"))
    notices = F.when(cued, F.filter(F.split("t", "\n", -1), lambda x: F.rlike(x, F.lit(_CUE)))).otherwise(F.array().cast("array<string>"))
    cut = src.select("doc_id", "path", F.regexp_count("t", F.lit(r"[^\x20\x09-\x0D]+")).alias("words"), blocks.alias("blocks"), notices.alias("notices"))
    rated = cut.select("doc_id", "path", "words", "notices", F.when(F.size("blocks") > 0, F.array_min(F.transform("blocks", lambda x: notice_scores(x)))).alias("best"))
    found = -F.col("best.minus") >= threshold
    spoken = F.aggregate(F.array_distinct("notices"), F.lit(0), lambda a, x: a + F.regexp_count(x, F.lit(r"[^\x20\x09-\x0D]+")))
    return rated.select("doc_id", "path", F.when(found, F.col("best.name")).alias("own"), F.coalesce(-F.col("best.minus"), F.lit(0.0)).alias("score"), (spoken / F.greatest("words", F.lit(1))).alias("share"))


def folder(path: Column) -> Column:
    """The directory of a path, '' for the top."""
    return F.regexp_replace(path, r"/?[^/]*$", "")


def ancestors(path: Column) -> Column:
    """All directories above a path, nearest first, as struct(depth, dir)."""
    parts = F.split(path, "/", -1)
    return let(parts, lambda p: F.transform(F.sequence(F.lit(1), F.size(p)), lambda k: F.struct(k.alias("up"), F.array_join(F.slice(p, F.lit(1), F.size(p) - k), "/").alias("dir"))))


def licences(files: DataFrame, threshold: float = THRESHOLD, file_share: float = 0.5, **cols: str) -> DataFrame:
    """doc_id, path, own, score, licence, origin ('own', the directory, or null)."""
    seen = settle(scan(files, threshold, **cols), "notices")
    name = F.regexp_extract("path", r"[^/]*$", 0)
    speaks = F.col("own").isNotNull() & F.col("path").isNotNull() & (name.rlike(FILE_NAMES) | (F.col("share") >= file_share))
    per_dir = seen.where(speaks).groupBy(folder(F.col("path")).alias("dir")).agg(F.min(F.struct((-F.col("score")).alias("minus"), F.col("own"), F.col("path"))).alias("b")).select("dir", F.col("b.own").alias("given"))
    homes = seen.where(F.col("own").isNull() & F.col("path").isNotNull()).select(folder(F.col("path")).alias("home")).distinct()
    above = homes.select("home", F.explode(ancestors(F.concat("home", F.lit("/x")))).alias("a")).select("home", "a.up", "a.dir")
    near = above.join(per_dir, "dir").groupBy("home").agg(F.min(F.struct("up", "dir", "given")).alias("n")).select("home", F.col("n.dir").alias("from"), F.col("n.given").alias("given"))
    out = seen.withColumn("home", folder(F.col("path"))).join(near, "home", "left")
    return out.select("doc_id", "path", "own", "score", F.coalesce("own", "given").alias("licence"), F.when(F.col("own").isNotNull(), "own").otherwise(F.col("from")).alias("origin"))


def document_path() -> Column:
    """Documents as files: source/language/hundreds/name; the name of a text that
    begins with a notice marks it as its folder's licence file."""
    head = F.substring_index(F.coalesce("text", F.lit("")), "\n", 1)
    name = F.concat(F.when(head.rlike(_CUE) & (F.length(head) < 120), F.lit("LICENSE-")).otherwise(F.lit("doc-")), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.lit(".txt"))
    return F.concat_ws("/", F.coalesce("source", F.lit("none")), F.coalesce("lang", F.lit("none")), F.coalesce(F.floor(F.col("doc_id") / 100).cast("string"), F.lit("none")), name)


def op2_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = licences(docs.select("doc_id", document_path().alias("path"), "text"))
    return got.select("doc_id", "path", "own", F.round("score", 6).alias("score"), "licence", "origin")
