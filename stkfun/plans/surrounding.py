"""Registered queries for the operators, sources and functions around the method."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StructField, StructType

from stkfun import oracle as o
from stkfun.config import DAY, HOUR, W_EVENTS, DistanceGrid
from stkfun.functions import geometry as geo
from stkfun.functions.shared import scratch
from stkfun.operators import estimate as est
from stkfun.operators import pairs as pr
from stkfun.operators import tabular as tab
from stkfun.sources import points as src
from stkfun.streaming import stream

T = src.table


def _orders(sp: SparkSession, d: str) -> DataFrame:
    n, r = T(sp, d, "nation"), T(sp, d, "region")
    c = T(sp, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return T(sp, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey"))


_ORDERS = "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _files(sp: SparkSession, d: str, fmt: str) -> DataFrame:
    """Points written in one format and read back."""
    path = scratch(sp, "points")
    p = src.events_skewed(sp, d).select(*src.COLUMNS)
    (p.write.option("header", True).csv(path) if fmt == "csv" else p.write.format(fmt).save(path))
    return src.read_points(sp, path, fmt).select("id", "x", "y", "t0", "mark")


_POINTS_BACK = f"SELECT id, x, y, t0, mark FROM ({o.POINTS['events_skewed']})"


def _partitioned_sink(sp: SparkSession, d: str) -> DataFrame:
    path = scratch(sp, "marks")
    src.events_skewed(sp, d).write.partitionBy("mark").parquet(path)
    return sp.read.parquet(path).where("mark = 'click'").groupBy("mark").agg(F.count("*").alias("n"), F.min("t0").alias("t_min"))


def _exported(sp: SparkSession, d: str) -> DataFrame:
    path = scratch(sp, "map")
    tab.export_surface(tab.heat_map(src.events_skewed(sp, d), W_EVENTS, 12, 10), path, "json")
    return sp.read.schema("gx int, gy int, n long").json(path)


_HEAT = f"WITH {o.pts('events_skewed')} SELECT CAST(least(floor(x / 50.0::DOUBLE), 11) AS INTEGER) AS gx, CAST(least(floor(y / 10.0::DOUBLE), 9) AS INTEGER) AS gy, count(*) AS n FROM pts GROUP BY ALL"


def _asof(sp: SparkSession, d: str) -> DataFrame:
    """Latest earlier event of the same type, by one window over the union of both sides."""
    e = T(sp, d, "events").select("event_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "value")
    left = e.where("value > 100").select("event_id", "event_type", "t", F.lit(1).alias("side"), F.lit(None).cast("long").alias("prev"))
    right = e.where("value <= 100").select(F.lit(None).cast("long").alias("event_id"), "event_type", "t", F.lit(0).alias("side"), F.col("event_id").alias("prev"))
    w = Window.partitionBy("event_type").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = left.unionByName(right).withColumn("prev_id", F.last("prev", ignorenulls=True).over(w))
    return both.where("side = 1").select("event_id", "prev_id")


@F.udtf(returnType=StructType([StructField("leaf", IntegerType()), StructField("x0", DoubleType()), StructField("x1", DoubleType())]))
class Strips:
    """Rows of equal strips of an interval."""

    def eval(self, low: float, high: float, n: int):
        for k in range(n):
            yield k, low + (high - low) * k / n, low + (high - low) * (k + 1) / n


def _udtf(sp: SparkSession, d: str) -> DataFrame:
    """Six strips of the x-range of each type of event."""
    ranges = src.events_skewed(sp, d).groupBy("mark").agg(F.min("x").alias("low"), F.max("x").alias("high"))
    return ranges.lateralJoin(Strips(F.col("low").outer(), F.col("high").outer(), F.lit(6))).select("mark", "leaf", "x0", "x1")


@F.pandas_udf(DoubleType())
def surface_integral(s: pd.Series, t: pd.Series, v: pd.Series) -> float:
    """Grouped aggregate: the trapezoid rule in both directions over a surface's grid."""
    grid = pd.DataFrame({"s": s.astype(float), "t": t.astype(float), "v": v.astype(float)}).pivot(index="s", columns="t", values="v")
    return float(np.trapezoid(np.trapezoid(grid.to_numpy(), grid.columns.to_numpy(), axis=1), grid.index.to_numpy()))


def _register(sp: SparkSession) -> None:
    """SQL names for the weights and cells of the events window."""
    sp.udf.register("stk_w_space", geo.w_space_polygon(geo.rect_ring(W_EVENTS), rect=W_EVENTS))
    sp.sql("CREATE OR REPLACE TEMPORARY FUNCTION stk_cell(v DOUBLE, size DOUBLE) RETURNS BIGINT RETURN CAST(floor(v / size) AS BIGINT)")
    sp.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION stk_w_time(t BIGINT, u BIGINT) RETURNS DOUBLE RETURN CASE WHEN t - u >= {W_EVENTS.t_start} AND t + u <= {W_EVENTS.t_end} THEN 1.0D ELSE 2.0D END")


def _sql_surface(sp: SparkSession, d: str) -> DataFrame:
    _register(sp)
    view = f"pts_{uuid.uuid4().hex}"
    src.events_skewed(sp, d).createOrReplaceTempView(view)
    return sp.sql(f"SELECT id, stk_cell(x, 5.0D) AS cx, stk_cell(y, 5.0D) AS cy, stk_w_time(t0, {20 * HOUR}) AS wt, round(stk_w_space(x, y, 5.0D), 4) AS w FROM {view}")


def _kde_sql() -> str:
    w, hs, ht = W_EVENTS, 20.0, 2 * DAY
    st = [(w.x1 - w.x0) / 6, (w.y1 - w.y0) / 5, w.period / 4]
    return f"""WITH {o.pts('events_skewed')}, g AS (SELECT i AS id, {w.x0}::DOUBLE + (i % 6 + 0.5::DOUBLE) * {st[0]}::DOUBLE AS x, {w.y0}::DOUBLE + ((i // 6) % 5 + 0.5::DOUBLE) * {st[1]}::DOUBLE AS y, {w.t_start} + CAST(floor((i // 30 + 0.5::DOUBLE) * {st[2]}::DOUBLE) AS BIGINT) AS t0 FROM range(120) r(i)),
m AS (SELECT g.id, (g.x - p.x) * (g.x - p.x) + (g.y - p.y) * (g.y - p.y) AS d2, abs(g.t0 - p.t0) AS u FROM g JOIN pts p ON p.t0 BETWEEN g.t0 - {ht} AND g.t0 + {ht}),
k AS (SELECT id, sum({2 / 3.141592653589793 / hs**2!r}::DOUBLE * (1 - d2 / {hs**2}::DOUBLE) * {0.75 / (ht / HOUR)!r}::DOUBLE * (1 - (u / {float(ht)}::DOUBLE) ** 2)) AS density, count(*) AS n FROM m WHERE d2 <= {hs**2}::DOUBLE GROUP BY id)
SELECT g.id, round(coalesce(density, 0), 6) AS density, coalesce(n, 0) AS n FROM g LEFT JOIN k USING (id)"""


def _knn_sql(k: int, speed: float) -> str:
    return f"""WITH {o.pts('events_skewed')},
r AS (SELECT c.id AS i, min({{'r': sqrt((c.x - q.x) ** 2 + (c.y - q.y) ** 2 + ({speed}::DOUBLE * abs(c.t0 - q.t0) / {float(HOUR)}::DOUBLE) ** 2), 'j': q.id}}, {k}) AS best FROM pts c JOIN pts q ON c.id <> q.id GROUP BY c.id)
SELECT i, best[rank].j AS j, round(best[rank].r, 6) AS r, CAST(rank AS INTEGER) AS rank FROM r, range(1, {k + 1}) z(rank)"""


def _events(sp, d):
    e = T(sp, d, "events")
    return e.withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))


_RING = geo.ellipse_ring(12)
_RING_SQL = " + ".join(f"CASE WHEN ({a[1]!r}::DOUBLE > y) <> ({b[1]!r}::DOUBLE > y) AND x < {b[0] - a[0]!r}::DOUBLE * (y - {a[1]!r}::DOUBLE) / {b[1] - a[1]!r}::DOUBLE + {a[0]!r}::DOUBLE THEN 1 ELSE 0 END" for a, b in zip(_RING, [*_RING[1:], _RING[0]]))


def entries() -> dict:
    skewed = src.events_skewed
    W = Window
    g5 = DistanceGrid(1.0, 5, 4 * HOUR, 5)
    stream_g = DistanceGrid(1.0, 5, 4 * HOUR, 5)
    e = {}

    def add(name, run, sql=None):
        e[name] = (run, sql)

    add("op_source_parquet_pruned", lambda s, d: T(s, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_quantity"), "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")
    add("op_source_csv", lambda s, d: _files(s, d, "csv"), _POINTS_BACK)
    add("op_source_json", lambda s, d: _files(s, d, "json"), _POINTS_BACK)
    add("op_source_generated", lambda s, d: src.clip(src.uniform_over(T(s, d, "orders").select(F.col("o_orderkey").alias("id")), W_EVENTS), W_EVENTS).select("id", F.round("x", 6).alias("x"), F.round("y", 6).alias("y"), "t0"), f"SELECT id, round(x, 6) AS x, round(y, 6) AS y, t0 FROM (SELECT o_orderkey AS id, {o.uniform_point(W_EVENTS, 'o_orderkey')} FROM orders)")
    add("op_sink_partitioned", _partitioned_sink, f"WITH {o.pts('events_skewed')} SELECT mark, count(*) AS n, min(t0) AS t_min FROM pts WHERE mark = 'click' GROUP BY mark")
    add("export_heat_map_json", _exported, _HEAT)
    add("op_clean_fill", lambda s, d: src.cleaned(skewed(s, d).withColumn("x", F.when(F.col("id") % 7 != 0, F.col("x"))), "mark").select("id", F.round("x", 4).alias("x")), f"WITH {o.pts('events_skewed')}, m AS (SELECT mark, avg(CASE WHEN id % 7 <> 0 THEN x END) AS mx FROM pts GROUP BY mark) SELECT id, round(CASE WHEN id % 7 <> 0 THEN x ELSE mx END, 4) AS x FROM pts JOIN m USING (mark)")
    add("op_projection_plane", lambda s, d: skewed(s, d).select("id", *[F.round(c, 3).alias(n) for c, n in zip(src.projected(F.col("y") - 50, F.col("x") / 10 - 30, lat0=10.0), ("ex", "ey"))], F.round(src.projected(F.col("y") - 50, F.col("x") / 10 - 30, "mercator")[1], 3).alias("my")), f"WITH {o.pts('events_skewed')} SELECT id, round(radians(y - 50) * cos(radians(10.0::DOUBLE)) * 6371008.8::DOUBLE, 3) AS ex, round(radians(x / 10 - 30) * 6371008.8::DOUBLE, 3) AS ey, round(ln(tan(0.7853981633974483::DOUBLE + radians(x / 10 - 30) / 2)) * 6371008.8::DOUBLE, 3) AS my FROM pts")
    add("op_filter_window", lambda s, d: tab.filter_points(skewed(s, d), mark=["click", "view"], since=W_EVENTS.t_start + 3 * DAY, until=W_EVENTS.t_start + 9 * DAY, box=(10, 200, 20, 80)).select("id", "x", "y", "t0"), f"WITH {o.pts('events_skewed')} SELECT id, x, y, t0 FROM pts WHERE mark IN ('click', 'view') AND t0 >= {W_EVENTS.t_start + 3 * DAY} AND t0 < {W_EVENTS.t_start + 9 * DAY} AND x BETWEEN 10 AND 200 AND y BETWEEN 20 AND 80")
    add("op_filter_ring", lambda s, d: src.clip(skewed(s, d), W_EVENTS.with_ring(_RING)).select("id"), f"WITH {o.pts('events_skewed')} SELECT id FROM pts WHERE ({_RING_SQL}) % 2 = 1")
    add("op_join_inner", lambda s, d: T(s, d, "orders").join(T(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
    add("op_join_merge_hint", lambda s, d: T(s, d, "lineitem").hint("merge").join(T(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n")), "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
    add("op_join_broadcast", lambda s, d: _orders(s, d).groupBy("r_name").agg(F.count("*").alias("n")), f"SELECT r_name, count(*) AS n FROM {_ORDERS} GROUP BY 1")
    add("op_join_range", lambda s, d: pr.pairs_cells(skewed(s, d), 2.0, 6 * HOUR, window=W_EVENTS).select("i", "j", "u"), f"WITH {o.pts('events_skewed')}, {o.pairs(2.0, 6 * HOUR)} SELECT i, j, u FROM pairs")
    add("op_join_asof", _asof, "WITH e AS (SELECT event_id, event_type, epoch_us(ts) AS t, value FROM events), r AS (SELECT event_type, t, event_id AS prev_id FROM e WHERE value <= 100) SELECT l.event_id, r.prev_id FROM (SELECT * FROM e WHERE value > 100) l ASOF LEFT JOIN r ON l.event_type = r.event_type AND l.t >= r.t")
    add("op_join_full", lambda s, d: tab.heat_map(skewed(s, d), W_EVENTS, 6, 5).withColumnRenamed("n", "n_skewed").join(tab.heat_map(src.events_uniform(s, d), W_EVENTS, 6, 5).withColumnRenamed("n", "n_uniform"), ["gx", "gy"], "full"), f"WITH a AS (SELECT CAST(least(floor(x / 100.0::DOUBLE), 5) AS INTEGER) AS gx, CAST(least(floor(y / 20.0::DOUBLE), 4) AS INTEGER) AS gy, count(*) AS n_skewed FROM ({o.POINTS['events_skewed']}) GROUP BY ALL), b AS (SELECT CAST(least(floor(x / 100.0::DOUBLE), 5) AS INTEGER) AS gx, CAST(least(floor(y / 20.0::DOUBLE), 4) AS INTEGER) AS gy, count(*) AS n_uniform FROM ({o.POINTS['events_uniform']}) GROUP BY ALL) SELECT * FROM a FULL JOIN b USING (gx, gy)")
    add("op_join_semi", lambda s, d: skewed(s, d).join(pr.pairs_cells(skewed(s, d), 2.0, 6 * HOUR, window=W_EVENTS).select(F.col("i").alias("id")), "id", "left_semi").select("id"), f"WITH {o.pts('events_skewed')}, {o.pairs(2.0, 6 * HOUR)} SELECT id FROM pts WHERE id IN (SELECT i FROM pairs)")
    add("op_join_anti", lambda s, d: skewed(s, d).join(pr.pairs_cells(skewed(s, d), 2.0, 6 * HOUR, window=W_EVENTS).select(F.col("i").alias("id")), "id", "left_anti").select("id"), f"WITH {o.pts('events_skewed')}, {o.pairs(2.0, 6 * HOUR)} SELECT id FROM pts WHERE id NOT IN (SELECT i FROM pairs)")
    add("op_join_anti_labels", lambda s, d: T(s, d, "documents").join(T(s, d, "labels").where("toxic = 1"), "doc_id", "left_anti").groupBy("lang", "source").agg(F.count("*").alias("n")), "SELECT lang, source, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1) GROUP BY ALL")
    add("op_join_cross_grid", lambda s, d: skewed(s, d).select("mark").distinct().crossJoin(est.dense_grid(skewed(s, d), g5)), "SELECT mark, CAST(a AS INTEGER) AS si, CAST(b AS INTEGER) AS ti FROM (SELECT DISTINCT event_type AS mark FROM events), range(6) s(a), range(6) t(b)")
    add("op_neighbour_count", lambda s, d: pr.neighbour_count(skewed(s, d), 2.0, 6 * HOUR, W_EVENTS), f"WITH {o.pts('events_skewed')}, {o.pairs(2.0, 6 * HOUR)}, c AS (SELECT i, count(*) AS n FROM pairs GROUP BY i) SELECT id, coalesce(n, 0) AS n FROM pts LEFT JOIN c ON id = i")
    add("op_agg_moments", lambda s, d: _events(s, d).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev("value"), 6).alias("sd"), F.round(F.variance("value"), 4).alias("var"), F.round(F.corr("value", F.col("user_id").cast("double")), 6).alias("r"), F.min("value").alias("lo"), F.max("value").alias("hi")), "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, round(stddev(value), 6) AS sd, round(variance(value), 4) AS var, round(corr(value, user_id::DOUBLE), 6) AS r, min(value) AS lo, max(value) AS hi FROM events GROUP BY 1")
    add("op_agg_distinct", lambda s, d: T(s, d, "lineitem").agg(F.countDistinct("l_quantity", "l_discount").alias("places"), F.countDistinct("l_shipdate").alias("times")), "SELECT count(DISTINCT (l_quantity, l_discount)) AS places, count(DISTINCT l_shipdate) AS times FROM lineitem")
    add("op_agg_percentile", lambda s, d: _events(s, d).groupBy("event_type").agg(*[F.round(F.expr(f"percentile(value, {q})"), 6).alias(f"q{int(q * 100)}") for q in (0.05, 0.5, 0.95)]), "SELECT event_type, " + ", ".join(f"round(quantile_cont(value, {q}), 6) AS q{int(q * 100)}" for q in (0.05, 0.5, 0.95)) + " FROM events GROUP BY 1")
    add("op_agg_max_by", lambda s, d: _events(s, d).groupBy("event_type").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top_id"), F.count_if(F.col("value") > 100).alias("n_high")), "SELECT event_type, arg_max(event_id, value) AS top_id, count(*) FILTER (value > 100) AS n_high FROM events GROUP BY 1")
    add("op_agg_collect", lambda s, d: T(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
    add("filters_rollup", lambda s, d: tab.counts_cube(_orders(s, d).withColumn("year", F.year("o_orderdate")).withColumn("month", F.month("o_orderdate")), ["r_name", "n_name", "year", "month"], "rollup"), f"SELECT r_name, n_name, CAST(year(o_orderdate) AS INTEGER) AS year, CAST(month(o_orderdate) AS INTEGER) AS month, count(*) AS n, CAST(grouping_id(r_name, n_name, year(o_orderdate), month(o_orderdate)) AS BIGINT) AS level FROM {_ORDERS} GROUP BY ROLLUP (r_name, n_name, year(o_orderdate), month(o_orderdate))")
    add("filters_cube", lambda s, d: tab.counts_cube(T(s, d, "orders"), ["o_orderpriority", "o_orderstatus"]), "SELECT o_orderpriority, o_orderstatus, count(*) AS n, CAST(grouping_id(o_orderpriority, o_orderstatus) AS BIGINT) AS level FROM orders GROUP BY CUBE (o_orderpriority, o_orderstatus)")
    add("op_grouping_sets", lambda s, d: (T(s, d, "orders").createOrReplaceTempView("stk_orders"), s.sql("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM stk_orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())"))[1], "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")
    add("heat_map", lambda s, d: tab.heat_map(skewed(s, d), W_EVENTS, 12, 10), _HEAT)
    add("op_window_ranks", lambda s, d: T(s, d, "supplier").select("s_suppkey", *[f.over(W.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")).cast("int").alias(n) for f, n in ((F.row_number(), "rn"), (F.rank(), "rk"), (F.dense_rank(), "dr"), (F.ntile(3), "nt"))], F.round(F.percent_rank().over(W.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")), 6).alias("pr")), "SELECT s_suppkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(3) OVER w AS INTEGER) AS nt, round(percent_rank() OVER w, 6) AS pr FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)")
    add("op_window_gaps", lambda s, d: _events(s, d).select("event_id", (F.col("t") - F.lag("t").over(W.partitionBy("event_type").orderBy("t", "event_id"))).alias("gap"), F.lead("event_id").over(W.partitionBy("event_type").orderBy("t", "event_id")).alias("next_id")), "SELECT event_id, t - lag(t) OVER w AS gap, lead(event_id) OVER w AS next_id FROM (SELECT *, epoch_us(ts) AS t FROM events) WINDOW w AS (PARTITION BY event_type ORDER BY t, event_id)")
    add("op_window_range_time", lambda s, d: _events(s, d).select("event_id", F.count("*").over(W.partitionBy("event_type").orderBy("t").rangeBetween(-HOUR, HOUR)).alias("n")), f"SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) RANGE BETWEEN {HOUR} PRECEDING AND {HOUR} FOLLOWING) AS n FROM events")
    add("op_window_first_last", lambda s, d: _events(s, d).select("event_id", *[f("value").over(W.partitionBy("event_type").orderBy("t", "event_id").rowsBetween(-2, 2)).alias(n) for f, n in ((F.first, "v_first"), (F.last, "v_last"))]), "SELECT event_id, first_value(value) OVER w AS v_first, last_value(value) OVER w AS v_last FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING)")
    add("op_topk", lambda s, d: tab.heat_map(skewed(s, d), W_EVENTS, 12, 10).orderBy(F.desc("n"), "gx", "gy").limit(5), f"SELECT * FROM ({_HEAT}) ORDER BY n DESC, gx, gy LIMIT 5")
    add("op_set_union", lambda s, d: skewed(s, d).select("id", F.lit("s").alias("kind")).unionByName(src.events_uniform(s, d).select("id", F.lit("u").alias("kind"))), "SELECT event_id AS id, 's' AS kind FROM events UNION ALL SELECT event_id, 'u' FROM events")
    add("op_set_intersect", lambda s, d: T(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(T(s, d, "supplier").select(F.col("s_nationkey").alias("k"))), "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
    add("op_set_except_all", lambda s, d: T(s, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(T(s, d, "supplier").select(F.col("s_nationkey").alias("k"))), "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
    add("op_sample_hash", lambda s, d: _events(s, d).where(geo.hash_uniform("sample", F.col("event_id")) < 0.1).select("event_id"), f"SELECT event_id FROM events WHERE {o.uniform('sample', 'event_id')} < 0.1")
    add("op_sample_stratified", lambda s, d: _events(s, d).where(geo.hash_uniform("strata", F.col("event_id")) < F.when(F.col("event_type") == "click", 0.5).otherwise(0.05)).groupBy("event_type").agg(F.count("*").alias("n")), f"SELECT event_type, count(*) AS n FROM events WHERE {o.uniform('strata', 'event_id')} < CASE WHEN event_type = 'click' THEN 0.5 ELSE 0.05 END GROUP BY 1")
    add("op_string", lambda s, d: T(s, d, "part").select("p_partkey", F.upper(F.regexp_extract("p_brand", "([0-9]+)", 1)).alias("num"), F.substring(F.md5("p_name"), 1, 6).alias("h"), F.element_at(F.split("p_type", " "), 1).alias("w1")), "SELECT p_partkey, upper(regexp_extract(p_brand, '([0-9]+)', 1)) AS num, substr(md5(p_name), 1, 6) AS h, string_split(p_type, ' ')[1] AS w1 FROM part")
    add("op_date", lambda s, d: T(s, d, "orders").select("o_orderkey", (F.year("o_orderdate") * 12 + F.month("o_orderdate")).alias("month_index"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"), F.unix_micros(F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))).alias("month_start"), F.unix_micros(F.add_months(F.to_date("o_orderdate"), 1).cast("timestamp")).alias("next_month")), "SELECT o_orderkey, CAST(year(o_orderdate) * 12 + month(o_orderdate) AS INTEGER) AS month_index, CAST(date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS INTEGER) AS days, epoch_us(date_trunc('month', o_orderdate)::TIMESTAMP) AS month_start, epoch_us((o_orderdate::DATE + INTERVAL 1 MONTH)::TIMESTAMP) AS next_month FROM orders")
    add("op_math", lambda s, d: skewed(s, d).select("id", *[F.round(c, 6).alias(n) for n, c in {"h": F.hypot("x", "y"), "a": F.atan2("y", "x"), "ac": F.acos(F.least(F.lit(1.0), F.col("y") / 100)), "sn": F.sin("x"), "pw": F.pow(F.col("y") / 100, F.lit(1.5))}.items()], F.pmod(F.floor("x"), F.lit(7)).alias("pm")), f"WITH {o.pts('events_skewed')} SELECT id, round(sqrt(x * x + y * y), 6) AS h, round(atan2(y, x), 6) AS a, round(acos(least(1.0::DOUBLE, y / 100)), 6) AS ac, round(sin(x), 6) AS sn, round(pow(y / 100, 1.5::DOUBLE), 6) AS pw, CAST(floor(x) AS BIGINT) % 7 AS pm FROM pts")
    add("op_bitwise", lambda s, d: skewed(s, d).select("id", F.shiftleft("id", 3).alias("sl"), F.shiftright("id", 2).alias("sr"), F.col("id").bitwiseAND(F.lit(255)).alias("ba"), F.col("id").bitwiseXOR(F.lit(170)).alias("bx")), "SELECT event_id AS id, event_id << 3 AS sl, event_id >> 2 AS sr, event_id & 255 AS ba, xor(event_id, 170) AS bx FROM events")
    add("op_array", lambda s, d: skewed(s, d).select("id", F.aggregate(F.transform(F.sequence(F.lit(1), F.lit(5)), lambda k: k * F.col("id")), F.lit(0).cast("long"), lambda a, b: a + b).alias("total"), F.size(F.filter(F.sequence(F.lit(1), F.lit(20)), lambda k: F.col("id") % k == 0)).alias("divisors")), "SELECT event_id AS id, CAST(event_id * 15 AS BIGINT) AS total, CAST(len(list_filter(range(1, 21), lambda k: event_id % k = 0)) AS INTEGER) AS divisors FROM events")
    add("op_map", lambda s, d: T(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.array_max(F.map_keys("m")).alias("k"), F.element_at("m", F.array_max(F.map_keys("m"))).alias("name")), "SELECT n_regionkey, max(n_nationkey) AS k, arg_max(n_name, n_nationkey) AS name FROM nation GROUP BY 1")
    add("op_json", lambda s, d: T(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("j")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, '{\"id\":' || event_id || '}' AS j FROM events")
    add("op_struct", lambda s, d: skewed(s, d).select(F.struct("id", "x").alias("c")).select("c.*"), "SELECT event_id AS id, value AS x FROM events")
    add("op_udf_polygon_sql", _sql_surface, f"WITH {o.pts('events_skewed')} SELECT id, CAST(floor(x / 5.0::DOUBLE) AS BIGINT) AS cx, CAST(floor(y / 5.0::DOUBLE) AS BIGINT) AS cy, {o.w_time(W_EVENTS, u=str(20 * HOUR))} AS wt, round({o.w_rect(W_EVENTS, d='5.0::DOUBLE')}, 4) AS w FROM pts")
    by_mark = lambda s, d: est.estimate_k(skewed(s, d), W_EVENTS, g5, by="mark")
    surf = f"WITH {o.pts('events_skewed')}, {o.pairs(g5.s_max, g5.t_max, ', c.mark', ' AND c.mark = q.mark')}, {o.bins(g5, o.weight(W_EVENTS), keys='mark')}, {o.cumulated(g5, 'mark', 'SELECT DISTINCT mark FROM pts')}, surf AS ({o.surface(g5, o.scale_of(W_EVENTS, '(n * (n - 1))'), 'mark', ' JOIN (SELECT mark, count(*) AS n FROM pts GROUP BY mark) nn USING (mark)')})"
    add("op_udaf", lambda s, d: by_mark(s, d).groupBy("mark").agg(F.round(surface_integral("s", "t", F.round("l", 4)), 2).alias("volume")), f"{surf} SELECT mark, round(sum(l * CASE WHEN si IN (1, {g5.s_steps}) THEN 0.5::DOUBLE ELSE 1.0::DOUBLE END * CASE WHEN ti IN (1, {g5.t_steps}) THEN 0.5::DOUBLE ELSE 1.0::DOUBLE END) * {float(g5.s_step * g5.t_step / HOUR)}::DOUBLE, 2) AS volume FROM surf GROUP BY mark")
    add("op_udtf", _udtf, "WITH r AS (SELECT event_type AS mark, min(value) AS low, max(value) AS high FROM events GROUP BY 1) SELECT mark, CAST(k AS INTEGER) AS leaf, low + (high - low) * k / 6 AS x0, low + (high - low) * (k + 1) / 6 AS x1 FROM r, range(6) z(k)")
    q = (6, 5, 4)
    add("quadrat", lambda s, d: tab.quadrat_test(skewed(s, d), W_EVENTS, *q).select("n", "cells", "used", F.round("ratio", 6).alias("ratio"), F.round("chi2", 4).alias("chi2")), f"WITH {o.pts('events_skewed')}, c AS (SELECT count(*) AS m FROM pts GROUP BY least(floor(x / 100.0::DOUBLE), 5), least(floor(y / 20.0::DOUBLE), 4), least(floor((t0 - {W_EVENTS.t_start}) / {W_EVENTS.period / 4}::DOUBLE), 3)), a AS (SELECT CAST(sum(m) AS BIGINT) AS n, CAST(sum(m * m) AS BIGINT) AS sq, count(*) AS used FROM c) SELECT n, 120 AS cells, used, round(((sq - n * (n / 120.0::DOUBLE)) / 119) / (n / 120.0::DOUBLE), 6) AS ratio, round(((sq - n * (n / 120.0::DOUBLE)) / 119) / (n / 120.0::DOUBLE) * 119, 4) AS chi2 FROM a")
    add("nearest_neighbour", lambda s, d: tab.nearest_neighbour_index(skewed(s, d), W_EVENTS, 2.0).select("n", F.round("mean", 6).alias("mean"), F.round("index", 6).alias("index")), f"WITH {o.pts('events_skewed')}, m AS (SELECT c.id, min(sqrt((c.x - q.x) ** 2 + (c.y - q.y) ** 2)) AS r FROM pts c JOIN pts q ON c.id <> q.id GROUP BY c.id) SELECT count(*) AS n, round(avg(r), 6) AS mean, round(avg(r) / (0.5::DOUBLE / sqrt(count(*) / 60000.0::DOUBLE)), 6) AS index FROM m")
    add("knn", lambda s, d: pr.knn(skewed(s, d), 3, 1.0, 10.0).select("i", "j", F.round("r", 6).alias("r"), "rank"), _knn_sql(3, 1.0))
    add("kde", lambda s, d: tab.kde(skewed(s, d), W_EVENTS, 6, 5, 4, 20.0, 2 * DAY).select("id", F.round("density", 6).alias("density"), "n"), _kde_sql())
    add("stream_windows", lambda s, d: stream.drained(stream.window_counts(stream.event_stream(s, d)), "complete").select("start", "mark", "n", F.round("sum_x", 4).alias("sum_x")), f"SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts)) AS start, event_type AS mark, count(*) AS n, round(sum(value), 4) AS sum_x FROM events GROUP BY ALL")
    add("stream_windows_sliding", lambda s, d: stream.drained(stream.window_counts(stream.event_stream(s, d), "6 hours", "3 hours"), "complete").select("start", "mark", "n"), f"SELECT b - k * {3 * HOUR} AS start, mark, count(*) AS n FROM (SELECT epoch_us(ts) - epoch_us(ts) % {3 * HOUR} AS b, event_type AS mark FROM events), range(2) r(k) GROUP BY ALL")
    add("stream_sessions", lambda s, d: stream.drained(stream.session_counts(stream.event_stream(s, d)), "complete"), f"WITH e AS (SELECT event_type AS mark, epoch_us(ts) AS t FROM events), g AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY mark ORDER BY t) < {HOUR // 2} THEN 0 ELSE 1 END AS new FROM e), n AS (SELECT *, sum(new) OVER (PARTITION BY mark ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT min(t) AS start, mark, count(*) AS n FROM n GROUP BY mark, k")
    add("stream_pairs", lambda s, d: stream.drained(stream.stream_pairs(stream.event_stream(s, d), 2.0, 6)), f"WITH {o.pts('events_skewed')}, {o.pairs(2.0, 6 * HOUR)} SELECT i, j FROM pairs")
    add("stream_incremental_k", lambda s, d: stream.drained(stream.incremental_bins(stream.event_stream(s, d), stream_g)).groupBy("si", "ti").agg((2 * F.sum("n")).alias("pairs")), o.pair_bins("events_skewed", stream_g))
    add("stream_deduplicated", lambda s, d: stream.drained(stream.event_stream(s, d).dropDuplicatesWithinWatermark(["id"])).groupBy("mark").agg(F.count("*").alias("n")), "SELECT event_type AS mark, count(*) AS n FROM events GROUP BY 1")
    return e
