"""Quality rules by distribution divergence, in DataFrame functions only.

Counts of each whole text (words, symbols, repeated lines, repeated 3-word
windows) give base rules; histograms of character classes and of common words
are held against references of the document's language, the sums over all its
documents, by Jensen-Shannon distance (base 2, 0 to 1). A minimum length guards
each histogram: shorter documents are judged by the base rules alone.

Defined cases: null and wordless texts have zero counts and fail the base rules;
null is a language of its own; a language whose documents are all below the
guard has no reference and rejects nothing; rows are kept one to one, repeated
rows and null ids included; an empty table gives an empty result; only the id,
text and language columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.functions.shared import settle

MIN_WORDS = 50
GUARD_WORDS = 100
MAX_CHAR_DISTANCE = 0.25
MAX_WORD_DISTANCE = 0.45
MAX_LANGUAGES = 10_000

#: Frequent words of English, German, French and Spanish.
COMMON = (
    "the of and to in a is that it for on was "
    "der die das und zu den mit von ist nicht "
    "le la les des et est que pour un une dans "
    "el los las de en y por con del se"
).split()
_CODES = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
_SPACE = r"[\x20\x09-\x0D]"
_CLASSES = {"upper": r"\p{Lu}", "digit": "[0-9]", "symbol": r"[#*$%&|<>]", "mark": r"[.,;:!?'\x22()\-]"}


def let(value: Column, body) -> Column:
    """``body`` of ``value``, computed once for each row."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, f"{_SPACE}+", -1), lambda w: w != "")


def repeated_words(words: Column) -> Column:
    """Words inside 3-word windows that occur twice or more."""

    def spread(starts: Column) -> Column:
        return F.aggregate(F.transform(starts, lambda s, i: F.coalesce(F.least(F.lit(3), F.get(starts, i + 1) - s), F.lit(3))), F.lit(0), lambda a, b: a + b)

    def twice(grams: Column) -> Column:
        pairs = F.array_sort(F.transform(grams, lambda g, i: F.struct(g.alias("g"), i.alias("i"))))

        def pick(p: Column) -> Column:
            near = F.filter(p, lambda e, i: (F.get(p, i + 1)["g"] == e["g"]) | (F.when(i > 0, F.get(p, i - 1)["g"]) == e["g"]))
            return let(F.sort_array(F.transform(near, lambda e: e["i"])), spread)

        return F.when(F.size(F.array_distinct(grams)) == F.size(grams), F.lit(0)).otherwise(let(pairs, pick))

    grams = let(words, lambda w: F.transform(F.slice(w, 1, F.greatest(F.size(w) - 2, F.lit(0))), lambda x, i: F.xxhash64(x, F.get(w, i + 1), F.get(w, i + 2))))
    return let(grams, twice)


def repeated_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.rlike(x, F.lit(r"[^\x20\x09-\x0D]")))
    return let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x)))


def common_codes(words: Column) -> Column:
    """One character for each word: its place in ``COMMON``, or a dot."""
    known = F.array(*[F.lit(w) for w in COMMON])
    return F.array_join(F.transform(words, lambda w: F.substring(F.lit("." + _CODES), F.array_position(known, F.lower(w)).cast("int") + 1, F.lit(1))), "")


def text_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """doc_id, lang, the base counts, and the two histograms of every row."""
    t = F.col("t")
    src = docs.select(F.col(id_col).alias("doc_id"), F.col(lang_col).cast("string").alias("lang"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t"))
    parts = let(words_of(t), lambda w: F.struct(F.size(w).alias("n"), repeated_words(w).alias("r"), common_codes(w).alias("c")))
    found = {k: F.regexp_count(t, F.lit(p)).alias(k) for k, p in _CLASSES.items()}
    one = src.select("doc_id", "lang", F.length(t).alias("chars"), F.regexp_count(t, F.lit(_SPACE)).alias("space"), *found.values(), repeated_lines(t).alias("lines"), parts.alias("p"))
    bins = [F.length("p.c") - F.length(F.replace(F.col("p.c"), F.lit(_CODES[i]), F.lit(""))) for i in range(len(COMMON))]
    rest = F.col("chars") - F.col("space") - F.col("upper") - F.col("digit") - F.col("symbol") - F.col("mark")
    two = one.select(
        "doc_id", "lang", F.col("p.n").cast("long").alias("n_words"), (F.col("chars") - F.col("space")).cast("long").alias("word_chars"),
        F.col("symbol").cast("long").alias("n_symbols"), F.col("lines").cast("long").alias("n_dup_lines"), F.col("p.r").cast("long").alias("n_repeat_words"),
        F.array(*[c.cast("long") for c in (rest, F.col("space"), F.col("upper"), F.col("digit"), F.col("symbol"), F.col("mark"))]).alias("char_bins"),
        F.array(*[b.cast("long") for b in bins]).alias("some"),
    )
    other = F.col("n_words") - F.aggregate("some", F.lit(0).cast("long"), lambda a, b: a + b)
    return two.withColumn("word_bins", F.concat("some", F.array(other))).drop("some")


def references(counts: DataFrame, guard_words: int = GUARD_WORDS) -> DataFrame:
    """lang and the summed histograms of its documents of guarded length."""
    sums = [F.sum(F.get("char_bins", F.lit(i))).alias(f"c{i}") for i in range(len(_CLASSES) + 2)]
    sums += [F.sum(F.get("word_bins", F.lit(i))).alias(f"w{i}") for i in range(len(COMMON) + 1)]
    got = counts.where(F.col("n_words") >= guard_words).groupBy("lang").agg(*sums)
    return got.select(F.col("lang").alias("ref_lang"), F.array(*[f"c{i}" for i in range(len(_CLASSES) + 2)]).alias("char_ref"), F.array(*[f"w{i}" for i in range(len(COMMON) + 1)]).alias("word_ref"))


def distance(a: Column, b: Column) -> Column:
    """Jensen-Shannon distance (base 2) of two histograms; null if one is empty."""

    def total(x: Column) -> Column:
        return F.aggregate(x, F.lit(0.0), lambda s, v: s + v.cast("double"))

    def half(p: Column, q: Column) -> Column:
        return F.when(p > 0, p * F.log2(2 * p / (p + q))).otherwise(0.0)

    def diverge(n: Column) -> Column:
        each = F.zip_with(a, b, lambda x, y: let(F.struct((x / n["a"]).alias("p"), (y / n["b"]).alias("q")), lambda s: half(s["p"], s["q"]) + half(s["q"], s["p"])))
        return F.sqrt(F.greatest(F.lit(0.0), total(each) / 2))

    sums = F.struct(total(a).alias("a"), total(b).alias("b"))
    return let(sums, lambda n: F.when((n["a"] > 0) & (n["b"] > 0), diverge(n)))


def judged(docs: DataFrame, min_words: int = MIN_WORDS, guard_words: int = GUARD_WORDS, max_char: float = MAX_CHAR_DISTANCE, max_word: float = MAX_WORD_DISTANCE, **cols: str) -> DataFrame:
    """Counts, distances, base_failed and kept of every row."""
    counts = settle(text_counts(docs, **cols), "textcounts")
    refs = settle(references(counts, guard_words), "textrefs")
    refs = F.broadcast(refs) if refs.limit(MAX_LANGUAGES + 1).count() <= MAX_LANGUAGES else refs
    both = counts.join(refs, F.col("lang").eqNullSafe(F.col("ref_lang")), "left")
    long = F.col("n_words") >= guard_words
    both = both.withColumn("char_distance", F.when(long, distance(F.col("char_bins"), F.col("char_ref")))).withColumn("word_distance", F.when(long, distance(F.col("word_bins"), F.col("word_ref"))))
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    verdict = (F.coalesce("char_distance", F.lit(0.0)) <= max_char) & (F.coalesce("word_distance", F.lit(0.0)) <= max_word)
    return both.select("doc_id", "lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "char_distance", "word_distance", failed.alias("base_failed"), (~failed & verdict).alias("kept"))


def op8_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return judged(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


_WORDS_SQL = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"


def _sql() -> str:
    known = ", ".join(f"'{w}'" for w in COMMON)
    classes = ", ".join(f"CAST(len(regexp_extract_all(t, '{p}')) AS BIGINT) AS k_{k}" for k, p in {**_CLASSES, "mark": r"[.,;:!?''\x22()\-]", "space": _SPACE}.items())
    words = ", ".join(f"CAST(len(list_filter(lw, lambda w: w = '{c}')) AS BIGINT)" for c in COMMON)
    sums = lambda c, n: ", ".join(f"sum({c}[{i + 1}])" for i in range(n))
    js = lambda a, b: f"sqrt(greatest(0.0::DOUBLE, list_sum(list_transform(list_zip({a}, {b}), lambda z: (CASE WHEN z[1] > 0 THEN (z[1] / list_sum({a})::DOUBLE) * log2(2 * (z[1] / list_sum({a})::DOUBLE) / (z[1] / list_sum({a})::DOUBLE + z[2] / list_sum({b})::DOUBLE)) ELSE 0.0 END) + (CASE WHEN z[2] > 0 THEN (z[2] / list_sum({b})::DOUBLE) * log2(2 * (z[2] / list_sum({b})::DOUBLE) / (z[1] / list_sum({a})::DOUBLE + z[2] / list_sum({b})::DOUBLE)) ELSE 0.0 END))) / 2))"
    return rf"""
WITH d AS (SELECT doc_id, lang, coalesce(text, '') AS t, {_WORDS_SQL} AS ws FROM documents),
b AS (
  SELECT doc_id, lang, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(t) AS BIGINT) AS chars, {classes},
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ln,
    list_transform(ws, lambda w: lower(w)) AS lw, ws,
    list_transform(range(CAST(greatest(len(ws) - 2, 0) AS BIGINT)), lambda i: ws[i + 1] || chr(10) || ws[i + 2] || chr(10) || ws[i + 3]) AS grams
  FROM d),
g AS (SELECT row_number() OVER () AS r, * FROM b),
win AS (SELECT r, unnest(grams) AS gram, generate_subscripts(grams, 1) AS i FROM g),
again AS (SELECT r, i FROM win QUALIFY count(*) OVER (PARTITION BY r, gram) > 1),
covered AS (SELECT r, count(DISTINCT i + k) AS n FROM again, range(3) q(k) GROUP BY r),
f AS (
  SELECT g.doc_id, g.lang, n_words, chars - k_space AS word_chars, k_symbol AS n_symbols,
    CAST(len(ln) - len(list_distinct(ln)) AS BIGINT) AS n_dup_lines, CAST(coalesce(covered.n, 0) AS BIGINT) AS n_repeat_words,
    [chars - k_space - k_upper - k_digit - k_symbol - k_mark, k_space, k_upper, k_digit, k_symbol, k_mark] AS cb,
    [{words}, CAST(len(list_filter(lw, lambda w: NOT list_contains([{known}], w))) AS BIGINT)] AS wb
  FROM g LEFT JOIN covered USING (r)),
refs AS (SELECT lang AS rl, [{sums("cb", len(_CLASSES) + 2)}]::BIGINT[] AS cr, [{sums("wb", len(COMMON) + 1)}]::BIGINT[] AS wr FROM f WHERE n_words >= {GUARD_WORDS} GROUP BY lang),
j AS (
  SELECT f.*, n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words AS base_failed,
    CASE WHEN n_words >= {GUARD_WORDS} THEN {js("cb", "cr")} END AS cd, CASE WHEN n_words >= {GUARD_WORDS} THEN {js("wb", "wr")} END AS wd
  FROM f LEFT JOIN refs ON lang IS NOT DISTINCT FROM rl)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND coalesce(cd, 0) <= {MAX_CHAR_DISTANCE} AND coalesce(wd, 0) <= {MAX_WORD_DISTANCE} AS kept
FROM j
"""


OP8_SQL = _sql()
