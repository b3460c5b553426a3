"""Mixing sources to target weights with weighted sampling by exponential keys.

Each source gets a target number of words: shares by weight, stopped at
``max_epochs`` times the source's size, the excess dealt again by weight. A
source takes all its documents for each complete epoch, then a fraction in the
order of the keys u ** (1 / quality) (u a hash of the id and text, quality a
weight of the document), descending, until the remaining budget is met; the
document at the boundary is taken if more than half of it fits.

The order is never materialised per source: keys fall into fixed ranges,
their sizes are prefix-summed, and only the range that holds the boundary is
sorted. What reaches the documents is one row for each source.

Defined cases: null texts have size 0; null is a source of its own, after all
others; documents without words are never taken in the fraction; a source
without words has target 0; repeated rows have equal keys and are ordered by a
row number that is written once, so that no more of them are taken than fit; an
empty table gives an empty result; the id may be null; extra columns are carried
by ``mixed``, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stkfun.functions.shared import settle

WORD = r"[^\x20\x09-\x0D]+"
RANGES = 4096
MAX_SOURCES = 100_000


def words_of(text: Column) -> Column:
    """Number of words, null texts 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def quality_of(text: Column, size: Column) -> Column:
    """A document weight in [0.2, 1]: long enough and made of letters rather than marks."""
    chars = F.length(F.coalesce(text, F.lit("")))
    marks = chars - F.length(F.translate(F.coalesce(text, F.lit("")), "#*$%&|<>!", ""))
    clean = F.lit(1.0) - F.least(F.lit(1.0), marks.cast("double") * 10 / F.greatest(chars, F.lit(1)))
    return F.lit(0.2) + F.lit(0.8) * clean * F.least(F.lit(1.0), size.cast("double") / 50)


def uniform_of(doc_id: Column, text: Column) -> Column:
    """A fixed number in (0, 1) for each id and text."""
    head = F.substring(F.md5(F.concat(F.lit("mix:"), F.coalesce(doc_id.cast("string"), F.lit("null")), F.lit(":"), F.coalesce(text, F.lit("")))), 1, 12)
    return (F.conv(head, 16, 10).cast("double") + 0.5) / 281474976710656.0


def source_targets(sizes: DataFrame, max_epochs: int = 3, weights: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """source, source_size, target from (source, source_size): one row a source.

    Sources by code point, nulls last, weigh ``weights`` in turn. Levelled in
    one pass: sources in order of cap over weight are capped while the level
    that the others would reach lies above."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    pick = F.element_at(F.array(*[F.lit(w) for w in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    w = sizes.withColumn("weight", pick).withColumn("cap", F.col("source_size") * max_epochs)
    line = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before = line.rowsBetween(Window.unboundedPreceding, -1)
    everyone = Window.partitionBy()
    stepped = w.withColumns({
        "ratio": F.col("cap") / F.col("weight"),
        "capped": F.coalesce(F.sum("cap").over(before), F.lit(0)),
        "open": F.sum("weight").over(everyone) - F.coalesce(F.sum("weight").over(before), F.lit(0)),
        "total": F.sum("source_size").over(everyone),
    })
    level = (F.col("total") - F.col("capped")).cast("double") / F.col("open")
    first = F.min(F.when(level <= F.col("ratio"), F.struct("ratio", (-level).alias("minus")))).over(everyone)
    stepped = stepped.withColumn("level", -first["minus"])
    return stepped.select("source", "source_size", F.least(F.col("cap").cast("double"), F.col("level") * F.col("weight")).alias("target"))


def mix_plan(docs: DataFrame, max_epochs: int = 3, weights: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """source, source_size, target, epochs, cut_key, cut_uid for (uid, size, source, key) rows.

    A document is taken ``epochs`` times, once more if its key is above the cut's
    or equal to it with a row number up to the cut's."""
    sizes = docs.groupBy("source").agg(F.sum("size").alias("source_size"))
    plan = source_targets(sizes, max_epochs, weights)
    plan = plan.withColumn("epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    plan = settle(plan.withColumn("rest", F.col("target") - F.col("epochs") * F.col("source_size")), "mixplan")
    with_words = docs.where("size > 0").withColumn("slot", F.least(F.lit(RANGES - 1), F.floor((1 - F.col("key")) * RANGES).cast("int")))
    line = Window.partitionBy("source").orderBy("slot").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ranges = with_words.groupBy("source", "slot").agg(F.sum("size").alias("held")).withColumn("upto", F.sum("held").over(line))
    small = _bounded(plan.withColumnRenamed("source", "of"))
    edge = ranges.join(small, F.col("source").eqNullSafe(F.col("of"))).select("source", "slot", "rest", (F.col("upto") - F.col("held")).alias("before"), "upto")
    edge = edge.where("before < rest and rest <= upto").select(F.col("source").alias("s"), F.col("slot").alias("k"), "rest", "before")
    edge = _bounded(settle(edge, "mixedge"))
    inside = with_words.join(edge, F.col("source").eqNullSafe(F.col("s")) & (F.col("slot") == F.col("k")))
    within = Window.partitionBy("source").orderBy(F.desc("key"), "uid").rowsBetween(Window.unboundedPreceding, -1)
    ahead = inside.withColumn("ahead", F.col("before") + F.coalesce(F.sum("size").over(within), F.lit(0)))
    last = ahead.where(F.col("ahead") + F.col("size") / 2.0 < F.col("rest")).groupBy("source").agg(F.max(F.struct((-F.col("key")).alias("minus"), "uid")).alias("cut"))
    last = last.withColumnRenamed("source", "of")
    # Without a document in the range, everything before it is taken.
    edged = edge.join(last, F.col("s").eqNullSafe(F.col("of")), "left").select("s", F.coalesce(-F.col("cut.minus"), 1 - F.col("k") / F.lit(float(RANGES))).alias("cut_key"), F.coalesce("cut.uid", F.lit(-1).cast("long")).alias("cut_uid"))
    out = plan.join(_bounded(edged), F.col("source").eqNullSafe(F.col("s")), "left")
    nothing = F.when(F.col("rest") > 0, F.col("cut_key")).otherwise(F.lit(2.0))
    return out.select("source", "source_size", "target", "epochs", F.coalesce(nothing, F.lit(2.0)).alias("cut_key"), F.coalesce("cut_uid", F.lit(-1).cast("long")).alias("cut_uid"))


def _bounded(plan: DataFrame) -> DataFrame:
    """A table of one row a source: broadcast up to ``MAX_SOURCES`` rows, joined otherwise."""
    return F.broadcast(plan) if plan.limit(MAX_SOURCES + 1).count() <= MAX_SOURCES else plan


def _size_and_key(doc_id: Column, text: Column) -> list[Column]:
    size = words_of(text)
    return [size.alias("size"), F.pow(uniform_of(doc_id, text), 1 / quality_of(text, size)).alias("key")]


def taken_times(row: Column, plan: Column) -> Column:
    """How often a row with uid, size and key is taken under its source's plan."""
    more = (row["key"] > plan["cut_key"]) | ((row["key"] == plan["cut_key"]) & (row["uid"] <= plan["cut_uid"]))
    return plan["epochs"] + F.when((row["size"] > 0) & more, 1).otherwise(0)


def mixture(docs: DataFrame, max_epochs: int = 3, weights: tuple[int, ...] = (1, 2, 3), id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, source, size, source_size, target, times, taken for every row."""
    text = F.col(text_col).cast("string")
    rows = docs.select(F.monotonically_increasing_id().alias("uid"), F.col(id_col).alias("doc_id"), F.col(source_col).cast("string").alias("source"), *_size_and_key(F.col(id_col), text))
    rows = settle(rows, "mixkeys")
    plan = _bounded(settle(mix_plan(rows, max_epochs, weights), "mixplan"))
    out = rows.select(F.struct("*").alias("r")).join(plan.select(F.struct("*").alias("p")), F.col("r.source").eqNullSafe(F.col("p.source")))
    out = out.select("r", "p", taken_times(F.col("r"), F.col("p")).alias("times"))
    return out.select("r.doc_id", "r.source", "r.size", "p.source_size", "p.target", "times", (F.col("times") * F.col("r.size")).alias("taken"))


def mixed(docs: DataFrame, max_epochs: int = 3, weights: tuple[int, ...] = (1, 2, 3), id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The rows of ``docs`` as often as the mixture takes them."""
    text = F.col(text_col).cast("string")
    own = F.struct(F.monotonically_increasing_id().alias("uid"), F.col(source_col).cast("string").alias("source"), *_size_and_key(F.col(id_col), text))
    rows = settle(docs.select(own.alias("mix"), F.struct(*docs.columns).alias("doc")), "mixrows")
    plan = _bounded(settle(mix_plan(rows.select("mix.*"), max_epochs, weights), "mixplan")).select(F.struct("*").alias("plan"))
    out = rows.join(plan, F.col("mix.source").eqNullSafe(F.col("plan.source")))
    times = taken_times(F.col("mix"), F.col("plan"))
    return out.select("doc", F.explode(F.array_repeat(F.lit(1), times.cast("int")))).select("doc.*")


def op5_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mixture(docs).select("doc_id", "size", "source_size", "target", "taken")


OP5_SQL = r"""
WITH d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         length(coalesce(text, '')) AS chars,
         length(coalesce(text, '')) - length(translate(coalesce(text, ''), '#*$%&|<>!', '')) AS marks,
         (CAST(('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), 'null') || ':' || coalesce(text, '')), 1, 12)) AS BIGINT) + 0.5) / 281474976710656.0::DOUBLE AS u
  FROM documents),
k AS (
  SELECT *, pow(u, 1 / (0.2::DOUBLE + 0.8::DOUBLE * (1.0::DOUBLE - least(1.0::DOUBLE, marks::DOUBLE * 10 / greatest(chars, 1))) * least(1.0::DOUBLE, size::DOUBLE / 50))) AS key FROM d),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, 1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS weight, source_size * 3 AS cap FROM s),
t AS (
  SELECT *, cap::DOUBLE / weight AS ratio,
    coalesce(sum(cap) OVER (ORDER BY cap::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS capped,
    sum(weight) OVER () - coalesce(sum(weight) OVER (ORDER BY cap::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS open,
    sum(source_size) OVER () AS total FROM w),
v AS (SELECT *, (total - capped)::DOUBLE / open::DOUBLE AS lv FROM t),
p AS (SELECT source, source_size, least(cap::DOUBLE, (SELECT lv FROM v WHERE lv <= ratio ORDER BY ratio, lv DESC LIMIT 1) * weight) AS target FROM v),
e AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS epochs FROM p),
o AS (
  SELECT k.doc_id, k.size, e.source_size, e.target, e.epochs, e.target - e.epochs * e.source_size AS rest,
    coalesce(sum(k.size) OVER (PARTITION BY k.source ORDER BY k.key DESC, k.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead
  FROM k JOIN e ON k.source IS NOT DISTINCT FROM e.source)
SELECT doc_id, size, source_size, target,
  CAST(size * (epochs + CASE WHEN size > 0 AND ahead + size / 2.0::DOUBLE < rest THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM o
"""
