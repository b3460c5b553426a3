"""Registered queries: relatives of K, weights, caches, simulations, partitions, codecs, ablations."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun import oracle as o
from stkfun.config import DAY, G10, G_LINES, G_OVERALL, HOUR, W_EMBED, W_EVENTS, W_LINES, DistanceGrid
from stkfun.functions import geometry as geo
from stkfun.functions.shared import settle
from stkfun.operators import codec, key_blocks as kb, weight_cache as wc
from stkfun.operators import estimate as est
from stkfun.operators import pairs as pr
from stkfun.operators import partition as part
from stkfun.operators import simulate as sim
from stkfun.operators import tabular as tab
from stkfun.plans import job, metrics, planner
from stkfun.sources import points as src

G5 = DistanceGrid(1.0, 5, 4 * HOUR, 5)
G_SIM = DistanceGrid(2.5, 2, 10 * HOUR, 2)
G_EMBED = DistanceGrid(0.05, 10, 1, 1)
W = W_EVENTS


def rounded(df: DataFrame, *names: str, digits: int = 4) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) for n in names})


def found(sp, d, s=5.0, t=20 * HOUR, **kw) -> DataFrame:
    return pr.pairs_cells(src.events_skewed(sp, d), s, t, window=W, **kw)


_ES = o.pts("events_skewed")
_P5 = f"{_ES}, {o.pairs(5.0, 20 * HOUR)}"


def _line_sql(points: str, join: str, weight: str, bin_: str, key: str, steps: int, step: float, extent: float, l: str, name: str, times: str = "1") -> str:
    return f"""WITH {points}, {join},
h AS (SELECT {bin_} AS {key}, CAST(sum({times}) AS BIGINT) AS pairs, CAST(sum(CAST(round(({weight}) * 1000000000) AS BIGINT) * {times}) AS BIGINT) AS wfix FROM near GROUP BY 1),
c AS (SELECT CAST(a AS INTEGER) AS {key}, CAST(sum(coalesce(pairs, 0)) OVER (ORDER BY a) AS BIGINT) AS pairs, sum(coalesce(wfix, 0)) OVER (ORDER BY a) AS wfix FROM range({steps + 1}) r(a) LEFT JOIN h ON h.{key} = a),
k AS (SELECT {key}, {key} * {step!r}::DOUBLE AS {name}, pairs, {extent!r}::DOUBLE / (n * (n - 1))::DOUBLE * (wfix / 1000000000.0::DOUBLE) AS k FROM c, (SELECT count(*) AS n FROM pts) WHERE {key} > 0)
SELECT {key}, {name}, pairs, round(k, 4) AS k, round({l}, 4) AS l FROM k"""


def _space_sql(name: str, w, g: DistanceGrid) -> str:
    near = f"near AS (SELECT c.x, c.y, sqrt((c.x - q.x) * (c.x - q.x) + (c.y - q.y) * (c.y - q.y)) AS d FROM pts c JOIN pts q ON q.x BETWEEN c.x - {g.s_max} - 0.001 AND c.x + {g.s_max} + 0.001 AND c.id <> q.id WHERE sqrt((c.x - q.x) * (c.x - q.x) + (c.y - q.y) * (c.y - q.y)) <= {g.s_max})"
    return _line_sql(o.pts(name), near, o.w_rect(w), f"CAST(ceil(d / {g.s_step}::DOUBLE) AS INTEGER)", "si", g.s_steps, float(g.s_step), w.area, f"sqrt(k / {math.pi!r}::DOUBLE) - s", "s")


def _time_sql(g: DistanceGrid) -> str:
    near = f"tm AS (SELECT t0, count(*) AS m FROM pts GROUP BY t0), near AS (SELECT c.t0, abs(c.t0 - q.t0) AS u, CASE WHEN c.t0 = q.t0 THEN c.m * (c.m - 1) ELSE c.m * q.m END AS times FROM tm c JOIN tm q ON q.t0 BETWEEN c.t0 - {g.t_max} AND c.t0 + {g.t_max})"
    return _line_sql(_ES, near, o.w_time(W), f"CAST((u + {g.t_step - 1}) // {g.t_step} AS INTEGER)", "ti", g.t_steps, g.t_step / HOUR, W.hours, "k - 2 * t", "t", "times")


def _interaction(sp, d) -> DataFrame:
    p = src.events_skewed(sp, d)
    parts = (est.estimate_k(p, W, G5), est.estimate_k_space(p, W, G5), est.estimate_k_time(p, W, G5))
    a, b, c = (rounded(x, "k") for x in parts)
    return rounded(est.interaction(a, b, c).select("si", "ti", "residual"), "residual", digits=2)


def _interaction_sql() -> str:
    return f"WITH a AS ({_plain_sql(_ES, G5)}), b AS ({_space_sql('events_skewed', W, G5)}), c AS ({_time_sql(G5)}) SELECT a.si, a.ti, round(a.k - b.k * c.k, 2) AS residual FROM a JOIN b USING (si) JOIN c USING (ti)"


def _border_sql(g: DistanceGrid) -> str:
    return f"""WITH {_ES}, gp AS (SELECT *, CAST(least(floor(least(x - 0.0, 600.0::DOUBLE - x, y - 0.0, 100.0::DOUBLE - y) / {g.s_step}::DOUBLE), {g.s_steps}) AS INTEGER) AS gs, CAST(least(least(t0 - {W.t_start}, {W.t_end} - t0) // {g.t_step}, {g.t_steps}) AS INTEGER) AS gt FROM pts),
{o.pairs(g.s_max, g.t_max, ', c.gs, c.gt', source='gp')},
b AS (SELECT CAST(ceil(d / {g.s_step}::DOUBLE) AS INTEGER) AS ps, CAST((u + {g.t_step - 1}) // {g.t_step} AS INTEGER) AS pt, gs, gt FROM pairs),
st AS (SELECT CAST(a AS INTEGER) AS si, CAST(c AS INTEGER) AS ti FROM range(1, {g.s_steps + 1}) s(a), range(1, {g.t_steps + 1}) t(c)),
r AS (SELECT si, ti, (SELECT count(*) FROM b WHERE ps <= si AND pt <= ti AND gs >= si AND gt >= ti) AS pairs, (SELECT count(*) FROM gp WHERE gs >= si AND gt >= ti) AS m FROM st),
k AS (SELECT *, si * {float(g.s_step)}::DOUBLE AS s, ti * {g.t_step / HOUR}::DOUBLE AS t, {W.area * W.hours!r}::DOUBLE * pairs / (m::DOUBLE * ((SELECT count(*) FROM pts) - 1)) AS k FROM r)
SELECT si, ti, s, t, pairs, round(k, 4) AS k, round(sqrt(k / ({2 * math.pi!r}::DOUBLE * t)) - s, 4) AS l FROM k"""


def _collapsed_points(sp, d):
    """Places rounded to whole units and times to days, so that points coincide."""
    p = src.events_skewed(sp, d)
    day = (F.floor((F.col("t0") - W.t_start) / DAY) * DAY + W.t_start + DAY // 2).cast("long")
    return p.withColumns({"x": F.floor("x") + 0.5, "y": F.floor("y").cast("double"), "t0": day, "t1": day})


_COARSE = f"pts AS (SELECT id, floor(x) + 0.5::DOUBLE AS x, floor(y) AS y, ((t0 - {W.t_start}) // {DAY}) * {DAY} + {W.t_start + DAY // 2} AS t0, mark, mult FROM ({o.POINTS['events_skewed']}))"
G_DAYS = DistanceGrid(1.0, 4, DAY, 3)


def _plain_sql(points: str, g: DistanceGrid) -> str:
    return f"WITH {points}, {o.pairs(g.s_max, g.t_max)}, {o.bins(g, o.weight(W))}, {o.cumulated(g)} {o.surface(g, o.scale_of(W, '(n * (n - 1))'), join=o.N)}"


def _lines_sql() -> str:
    g, w = G_LINES, W_LINES
    own = "hist2 AS (SELECT si, ti, CAST(sum(pairs) AS BIGINT) AS pairs, CAST(sum(wfix) AS BIGINT) AS wfix FROM (SELECT * FROM hist UNION ALL SELECT 0, 0, sum(mult * (mult - 1)), sum(mult * (mult - 1)) * 1000000000 FROM pts) GROUP BY si, ti)"
    return f"WITH {o.pts('lineitem_grid')}, {o.lattice_pairs(g.t_max)}, {o.bins(g, o.weight(w), 'c_mult * q_mult')}, {own}, {o.cumulated(g, hist='hist2')} {o.surface(g, o.scale_of(w, '(n * (n - 1))'), join=', (SELECT CAST(sum(mult) AS BIGINT) AS n FROM pts) nn')}"


def _cross_sql(g: DistanceGrid) -> str:
    where = "c_mark = 'click' AND q_mark = 'purchase'"
    return f"WITH {_ES}, {o.pairs(g.s_max, g.t_max)}, {o.bins(g, o.weight(W), where=where)}, {o.cumulated(g)} {o.surface(g, o.scale_of(W, '(na * nb)'), join=''', (SELECT count(*) FILTER (mark = 'click') AS na, count(*) FILTER (mark = 'purchase') AS nb FROM pts) nn''')}"


def _sector_sql(g: DistanceGrid) -> str:
    return f"WITH {_ES}, {o.pairs(g.s_max, g.t_max)}, {o.bins(g, o.weight(W), where='atan2(dy, dx) >= 0 AND atan2(dy, dx) < 1.5')}, {o.cumulated(g)} {o.surface(g, f'{W.area * W.hours * 2 * math.pi / 1.5!r}::DOUBLE / (n * (n - 1))::DOUBLE', join=o.N)}"


def _inhom_sql(g: DistanceGrid) -> str:
    vol = 100.0 * 50.0 * (W.period / 3) / HOUR
    cells = f"gp AS (SELECT *, count(*) OVER (PARTITION BY least(floor(x / 100.0::DOUBLE), 5), least(floor(y / 50.0::DOUBLE), 1), least(floor((t0 - {W.t_start}) / {W.period / 3}::DOUBLE), 2)) / {vol!r}::DOUBLE AS lam FROM pts)"
    return f"WITH {_ES}, {cells}, {o.pairs(g.s_max, g.t_max, ', c.lam AS cl, q.lam AS ql', source='gp')}, {o.bins(g, f'({o.weight(W)}) * {est.intensity_unit(W)!r}::DOUBLE / (cl * ql)')}, {o.cumulated(g)} {o.surface(g, f'{1.0 / (W.area * W.hours) / est.intensity_unit(W)!r}::DOUBLE')}"


_SETS = {
    "permutation": "sims AS (SELECT * FROM (SELECT row_number() OVER (ORDER BY id) AS k, id, x, y, mult, mark FROM pts) a JOIN (SELECT CAST(s AS INTEGER) AS sim, row_number() OVER (PARTITION BY s ORDER BY md5('42:' || s || ':' || id), id) AS k, t0 FROM pts, range(1, {m1}) r(s)) b USING (k))",
    "bootstrap": "sims AS (SELECT sim, draw AS id, x, y, t0, mult, mark FROM (SELECT row_number() OVER (ORDER BY id) - 1 AS k, * EXCLUDE (id) FROM pts) p JOIN (SELECT CAST(s AS INTEGER) AS sim, i AS draw, CAST(floor({u} * n) AS BIGINT) AS k FROM (SELECT count(*) AS n FROM pts), range(1, {m1}) r(s), range((SELECT count(*) FROM pts)) q(i)) d USING (k))",
    "cstr": "sims AS (SELECT CAST(s AS INTEGER) AS sim, i AS id, {xyz}, 1 AS mult, NULL AS mark FROM range(1, {m1}) r(s), range((SELECT count(*) FROM pts)) q(i))",
}


def sets_sql(method: str, m: int) -> str:
    key = "('42:' || s || ':' || i)"
    return _SETS[method].format(m1=m + 1, u=o.uniform("boot", key), xyz=o.uniform_point(W, key))


def _sim_surface_sql(method: str, m: int, g: DistanceGrid) -> str:
    """CTEs pts, sims, and surf: rounded surfaces by sim."""
    scale = o.scale_of(W, "(n * (n - 1))")
    return f"""{_ES}, {sets_sql(method, m)}, {o.pairs(g.s_max, g.t_max, ', c.sim', ' AND c.sim = q.sim', 'sims')}, {o.bins(g, o.weight(W), keys='sim')},
{o.cumulated(g, 'sim', 'SELECT DISTINCT sim FROM sims')}, surf AS ({o.surface(g, scale, 'sim', o.N)}),
op AS (SELECT c.x, c.y, c.t0, {o._D} AS d, abs(c.t0 - q.t0) AS u FROM pts c JOIN pts q ON q.t0 BETWEEN c.t0 - {g.t_max} AND c.t0 + {g.t_max} AND c.id <> q.id WHERE {o._D} <= {g.s_max}),
ob AS (SELECT CAST(ceil(d / {g.s_step}::DOUBLE) AS INTEGER) AS si, CAST((u + {g.t_step - 1}) // {g.t_step} AS INTEGER) AS ti, CAST(round(({o.weight(W)}) * 1000000000) AS BIGINT) AS w FROM op),
obs AS (SELECT a.si, a.ti, a.s, a.t, round({o.l_of(f'({scale}) * ((SELECT sum(w) FROM ob WHERE ob.si <= a.si AND ob.ti <= a.ti) / 1000000000.0::DOUBLE)', 'a.s', 'a.t')}, 4) AS l FROM (SELECT DISTINCT si, ti, s, t FROM surf) a{o.N})"""


def _sims(sp, d, method, m):
    return settle(rounded(sim.simulate_k(src.events_skewed(sp, d), W, G_SIM, method, m, ordered=True), "k", "l"), "sims")


def _observed(sp, d):
    return rounded(est.estimate_k(src.events_skewed(sp, d), W, G_SIM), "k", "l")


_SIG = """sig AS (SELECT o.si, o.ti, o.s, o.t, o.l AS l_obs, max(f.l) AS l_upper, min(f.l) AS l_lower, abs(o.l - max(f.l)) AS diff, (count(*) FILTER (f.l >= o.l) + 1) / (count(*) + 1)::DOUBLE AS p,
  CASE WHEN o.l > max(f.l) THEN 'clustered' WHEN o.l < min(f.l) THEN 'dispersed' ELSE 'random' END AS verdict FROM obs o JOIN surf f ON f.si = o.si AND f.ti = o.ti GROUP BY o.si, o.ti, o.s, o.t, o.l)"""


def _grid_stats_sql() -> str:
    """Balance of the 4 x 4 x 4 grid."""
    cell = f"least(floor(x / 150.0::DOUBLE), 3), least(floor(y / 25.0::DOUBLE), 3), least(floor((t0 - {W.t_start}) / {W.period / 4}::DOUBLE), 3)"
    return f"WITH {_ES}, c AS (SELECT count(*) AS n FROM pts GROUP BY {cell}) SELECT 'grid' AS scheme, 64 AS leaves, max(n) AS rows_max, 64 - count(*) AS empty, CAST(0 AS BIGINT) AS uncovered FROM c"


def _stats(scheme, parts):
    def run(sp, d):
        got = part.partition_stats(src.events_skewed(sp, d), W, 5.0, 20 * HOUR, parts, scheme)
        return got.withColumns({c: F.round(c, 4) for c in ("rows_avg", "max_over_mean", "cv", "cylinder_factor", "ghost_factor")})

    return run


def _ring_weights(ring, window=W):
    def run(sp, d):
        p = src.clip(src.events_skewed(sp, d), W.with_ring(ring))
        return p.select("id", F.round(geo.w_space_polygon(ring)(F.col("x"), F.col("y"), F.lit(5.0)), 4).alias("w"))

    return run


def _cache_hits(method):
    def run(sp, d):
        p = src.events_skewed(sp, d)
        cache = wc.fill(found(sp, d), W).freeze()
        sets = sim.simulated(p, W, method, 2, ordered=True)
        return wc.search_stats(sets, cache, 5.0, 20 * HOUR, ("sim",))

    return run


def _cache_sql(method: str) -> str:
    near = o.pairs(5.0, 20 * HOUR, ", c.sim", " AND c.sim = q.sim", "sims").replace("pairs AS", "sp AS", 1)
    return f"""WITH {_P5}, {sets_sql(method, 2)}, {near}, ks AS (SELECT DISTINCT x, y, d FROM pairs), kt AS (SELECT DISTINCT t0, u FROM pairs)
SELECT sim, count(*) AS lookups, count(ks.d) AS space_hits, count(kt.u) AS time_hits FROM sp LEFT JOIN ks ON ks.x = sp.x AND ks.y = sp.y AND ks.d = sp.d LEFT JOIN kt ON kt.t0 = sp.t0 AND kt.u = sp.u GROUP BY sim"""


def _index_roundtrip(sp, d):
    """All pairs, found in leaves whose index has been through its byte form."""
    return part.pairs_partitioned(src.events_skewed(sp, d), W, 5.0, 20 * HOUR, 27, local="rtree", compact=True).select("i", "j")


def _envelopes(sp, d):
    """The boxes of the events in each leaf of a 4 x 4 x 4 grid."""
    size = ((W.x1 - W.x0) / 4, (W.y1 - W.y0) / 4, W.period / 4)
    a, b, c = (F.least(F.floor((F.col(n) - lo) / z), F.lit(3)) for n, lo, z in zip(("x", "y", "t0"), (W.x0, W.y0, W.t_start), size))
    leaf = ((a * 4 + b) * 4 + c).cast("int")
    boxes = src.events_skewed(sp, d).groupBy(leaf.alias("env_id")).agg(*[f(v).alias(n) for n, f, v in (("x0", F.min, "x"), ("x1", F.max, "x"), ("y0", F.min, "y"), ("y1", F.max, "y"), ("t_first", F.min, "t0"), ("t1", F.max, "t0"))])
    boxes = boxes.withColumnRenamed("t_first", "t0").withColumn("zone", F.lit(None).cast("int"))
    return codec.decode_envelopes(codec.encode_envelopes(boxes)).drop("zone")


def _envelopes_sql() -> str:
    leaf = f"least(floor((x - {W.x0}) / {(W.x1 - W.x0) / 4}::DOUBLE), 3) * 16 + least(floor((y - {W.y0}) / {(W.y1 - W.y0) / 4}::DOUBLE), 3) * 4 + least(floor((t0 - {W.t_start}) / {W.period / 4}::DOUBLE), 3)"
    return f"WITH {_ES} SELECT CAST({leaf} AS INTEGER) AS env_id, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1, min(pts.t0) AS t0, max(pts.t0) AS t1 FROM pts GROUP BY 1"


def _planned(sp, d):
    p = planner.plan(src.events_skewed(sp, d), W, G5)
    return sp.createDataFrame([(p.index, p.cache, p.partitioner, p.replication, p.codec, p.distribute, p.parts)], "index boolean, cache boolean, partitioner string, replication string, codec boolean, distribute boolean, parts int")


def _planned_sql() -> str:
    """The rules for a set of at most 20,000 points, whose load is counted in full."""
    cells = f"floor(x / {2 * G5.s_max}::DOUBLE), floor(y / {2 * G5.s_max}::DOUBLE), floor(t0 / {2.0 * G5.t_max}::DOUBLE)"
    small = str(G5.s_max < W.short_side / 32 and G5.t_max < W.period / 32).lower()
    return f"""WITH {_ES}, c AS (SELECT count(*) AS m FROM pts GROUP BY {cells}), l AS (SELECT sum(m * (m - 1)) / sum(m)::DOUBLE * {math.pi / 4!r}::DOUBLE AS load, CAST(sum(m) AS BIGINT) AS n FROM c)
SELECT {small} AND load <= 5000 AS index, false AS cache, 'domain' AS partitioner, 'cylinder' AS replication, true AS codec, n > 50000 AS distribute, CAST(least(2000, greatest(1, ceil(n * (1 + load / 100) / 20000))) AS INTEGER) AS parts FROM l"""


#: The surveyed ranges of the experiments.
FRACTIONS = (1 / 128, 1 / 64, 1 / 32, 1 / 16, 1 / 8, 1 / 4)
VERTICES = (4, 10, 50, 100, 500, 1000, 5000)
PARTS = (8, 64, 2048)
STRATEGIES = {
    "index": replace(job.NONE, index=True), "cache": replace(job.NONE, cache=True), "partition": replace(job.NONE, partitioner="domain", parts=64),
    "codec": replace(job.NONE, index=True, codec=True, partitioner="domain", parts=64), "all": job.ALL,
}


def _union(frames) -> DataFrame:
    out = None
    for f in frames:
        out = f if out is None else out.unionByName(f)
    return out


def index_workload(sp, d) -> DataFrame:
    """Pairs that each access path finds while the thresholds double (W2)."""
    frames = []
    for name, points in (("skewed", src.events_skewed), ("uniform", src.events_uniform)):
        p = settle(points(sp, d), "index")
        for k, f in enumerate(FRACTIONS):
            g = DistanceGrid.from_fraction(W, f)
            paths = {"cells": pr.pairs_cells(p, g.s_max, g.t_max, window=W)}
            paths |= {kind: part.pairs_partitioned(p, W, g.s_max, g.t_max, 8, "grid", local=kind) for kind in (("rtree", "octree", "kdtree") if name == "skewed" else ("rtree",))}
            frames += [x.agg(F.count("*").alias("pairs")).select(F.lit(name).alias("points"), F.lit(k).alias("step"), F.lit(v).alias("path"), "pairs") for v, x in paths.items()]
    return _union(frames)


def _index_sql() -> str:
    out = []
    for name, kinds in (("skewed", ("cells", "rtree", "octree", "kdtree")), ("uniform", ("cells", "rtree"))):
        for k, f in enumerate(FRACTIONS):
            g = DistanceGrid.from_fraction(W, f)
            paths = ", ".join(f"('{v}')" for v in kinds)
            out.append(f"SELECT '{name}' AS points, {k} AS step, path, pairs FROM (WITH {o.pts('events_' + name)}, {o.pairs(g.s_max, g.t_max)} SELECT count(*) AS pairs FROM pairs), (VALUES {paths}) v(path)")
    return " UNION ALL ".join(out)


def cache_workload(sp, d) -> DataFrame:
    """The same window with more and more vertices: pairs, distinct keys and the mean weight (W3)."""
    p = settle(found(sp, d).select("x", "y", "d"), "cache")
    keys = settle(p.groupBy("x", "y", "d").agg(F.count("*").alias("n")), "cachekeys")
    frames = []
    for v in VERTICES:
        ring = geo.rect_ring(W, v)
        for variant, rows, memo in (("plain", p.withColumn("n", F.lit(1).cast("long")), False), ("cached", keys, True)):
            w = rows.select("n", geo.w_space_polygon(ring, memo=memo, rect=W)("x", "y", "d").alias("w"))
            frames.append(w.agg(F.sum("n").alias("pairs"), F.count("*").alias("computed"), F.round(F.sum(F.col("w") * F.col("n")) / F.sum("n"), 4).alias("w_mean")).select(F.lit(v).alias("vertices"), F.lit(variant).alias("variant"), "pairs", "computed", "w_mean"))
    return _union(frames)


def _cache_workload_sql() -> str:
    return f"""WITH {_P5}, one AS (SELECT count(*) AS pairs, count(DISTINCT (x, y, d)) AS keys, round(avg({o.w_rect(W)}), 4) AS w_mean FROM pairs)
SELECT v AS vertices, variant, pairs, CASE WHEN variant = 'plain' THEN pairs ELSE keys END AS computed, w_mean FROM one, (VALUES {', '.join(f'({v})' for v in VERTICES)}) a(v), (VALUES ('plain'), ('cached')) b(variant)"""


def partition_workload(sp, d) -> DataFrame:
    """Pairs found under every scheme while the number of leaves grows to 2,048 (W4)."""
    p, frames = settle(src.events_skewed(sp, d), "partitions"), []
    for n in PARTS:
        for scheme in ("hash", "grid", "quadtree", "rtree", "domain") if n <= 64 else ("grid", "quadtree", "rtree", "domain"):
            got = part.pairs_partitioned(p, W, G5.s_max, G5.t_max, n, scheme)
            frames.append(got.agg(F.count("*").alias("pairs")).select(F.lit(n).alias("parts"), F.lit(scheme).alias("scheme"), "pairs"))
    return _union(frames)


def _partition_workload_sql() -> str:
    return f"WITH {_P5} SELECT p AS parts, s AS scheme, n AS pairs FROM (SELECT count(*) AS n FROM pairs), (VALUES {', '.join(f'({n})' for n in PARTS)}) a(p), (VALUES ('hash'), ('grid'), ('quadtree'), ('rtree'), ('domain')) b(s) WHERE p <= 64 OR s <> 'hash'"


def codec_workload(sp, d) -> DataFrame:
    """Every point set through the compact form: rows, bytes, and sums over what comes back (W5)."""
    frames = []
    for name, points in (("events", src.events_skewed), ("orders", src.orders_month), ("lines", src.lineitem_grid)):
        coded = settle(codec.encode_points(points(sp, d)), "coded")
        back = codec.decode_points(coded).agg(F.count("*").alias("n"), F.sum("id").alias("ids"), F.sum(F.col("t0").cast("decimal(38,0)")).cast("string").alias("times"), F.sum("mult").alias("mult"))
        size = coded.agg(F.sum(F.length("b")).alias("bytes"))
        frames.append(back.crossJoin(size).select(F.lit(name).alias("points"), "n", "bytes", "ids", "times", "mult"))
    return _union(frames)


def _codec_workload_sql() -> str:
    return " UNION ALL ".join(f"SELECT '{name}' AS points, count(*) AS n, count(*) * {codec.LAYOUTS[codec.POINT].itemsize} AS bytes, CAST(sum(id) AS BIGINT) AS ids, CAST(sum(t0) AS VARCHAR) AS times, CAST(sum(mult) AS BIGINT) AS mult FROM ({o.POINTS[table]})" for name, table in (("events", "events_skewed"), ("orders", "orders_month"), ("lines", "lineitem_grid")))


_RING85 = geo.ellipse_ring(85)


def uniform_ring(sp, d) -> DataFrame:
    """Uniform points in an 85-vertex outline, polygon weights: L near 0 (W9)."""
    w = W.with_ring(_RING85)
    return rounded(est.estimate_k(settle(src.clip(src.events_uniform(sp, d), w), "ring"), w, G10), "k", "l")


def _uniform_ring_sql() -> str:
    w = W.with_ring(_RING85)
    near = o.pairs(G10.s_max, G10.t_max).replace("pairs AS", "near AS", 1)
    points = f"pts AS (SELECT * FROM ({o.POINTS['events_uniform']}) WHERE {o.inside(_RING85)})"
    return f"WITH {points}, {near}, circles AS MATERIALIZED (SELECT * EXCLUDE (i), row_number() OVER () AS id FROM near), {o.ring_weights(_RING85, 'circles')}, pairs AS (SELECT c.*, rw.w AS ws FROM circles c JOIN rw USING (id)), {o.bins(G10, f'ws * ({o.w_time(W)})')}, {o.cumulated(G10)} {o.surface(G10, o.scale_of(w, '(n * (n - 1))'), join=o.N)}"


def _ring_sql(ring) -> str:
    return f"WITH {_ES}, circles AS (SELECT id, x, y, 5.0::DOUBLE AS d FROM pts WHERE {o.inside(ring)}), {o.ring_weights(ring, 'circles')} SELECT id, round(w, 4) AS w FROM rw"


def _hash_stats_sql(parts: int, s: float, t: int) -> str:
    gap = lambda c: f"greatest(b.{c}0 - p.{c}, p.{c} - b.{c}1, 0)"
    return f"""WITH {_ES}, p AS (SELECT x, y, t0::DOUBLE AS t, CAST(floor({o.uniform('leaf', 'id')} * {parts}) AS INTEGER) AS leaf FROM pts),
b AS (SELECT leaf, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1, min(t) AS t0, max(t) AS t1, count(*) AS m FROM p GROUP BY leaf),
g AS (SELECT {gap('x')} AS gx, {gap('y')} AS gy, {gap('t')} AS gt FROM p, b),
f AS (SELECT count(*) FILTER (gx * gx + gy * gy <= {s * s}::DOUBLE AND gt <= {t}) AS cyl, count(*) FILTER (gx <= {s} AND gy <= {s} AND gt <= {t}) AS gh FROM g)
SELECT 'hash' AS scheme, {parts} AS leaves, (SELECT max(m) FROM b) AS rows_max, round(cyl / (SELECT count(*) FROM p)::DOUBLE, 4) AS cylinder_factor, round(gh / (SELECT count(*) FROM p)::DOUBLE, 4) AS ghost_factor FROM f"""


def _intervals(sp, d):
    """Events that last up to four hours."""
    return src.events_skewed(sp, d).withColumn("t1", F.col("t0") + (F.col("id") % 5) * HOUR)


_INTERVAL_SQL = f"""WITH {_ES}, iv AS (SELECT id, x, y, t0, t0 + (id % 5) * {HOUR} AS t1 FROM pts)
SELECT i, j, u FROM (SELECT c.id AS i, q.id AS j, greatest(c.t0 - q.t1, q.t0 - c.t1, 0) AS u, {o._D} AS d FROM iv c JOIN iv q ON q.t0 BETWEEN c.t0 - {16 * HOUR} AND c.t0 + {16 * HOUR} AND c.id <> q.id) WHERE u <= {10 * HOUR} AND d <= 2.0"""


def _application(method, m):
    """Full set, m simulations, decision at every distance (W10); p can reach 1 / (m + 1)."""
    return lambda s, d: rounded(sim.significance(_observed(s, d), _sims(s, d, method, m)), "diff")


_SIG_ROWS = "SELECT si, ti, s, t, l_obs, l_upper, l_lower, round(diff, 4) AS diff, p, verdict FROM sig"


def entries() -> dict:
    es = src.events_skewed
    e = {}

    def add(name, run, sql=None):
        e[name] = (run, sql)

    add("k_surface_lines", lambda s, d: rounded(est.estimate_k(src.lineitem_grid(s, d), W_LINES, G_LINES, mult="mult"), "k", "l"), _lines_sql())
    add("k_border", lambda s, d: rounded(est.estimate_k(es(s, d), W, G5, correction="border"), "k", "l"), _border_sql(G5))
    add("k_space_events", lambda s, d: rounded(est.estimate_k_space(es(s, d), W, G5), "k", "l"), _space_sql("events_skewed", W, G5))
    add("k_space_embeddings", lambda s, d: rounded(est.estimate_k_space(src.embedding_plane(s, d), W_EMBED, G_EMBED), "k", "l"), _space_sql("embedding_plane", W_EMBED, G_EMBED))
    add("k_time_events", lambda s, d: rounded(est.estimate_k_time(es(s, d), W, G5), "k", "l"), _time_sql(G5))
    add("k_interaction", _interaction, _interaction_sql())
    add("k_collapsed", lambda s, d: rounded(est.estimate_k(est.collapse_coincident(_collapsed_points(s, d)), W, G_DAYS, mult="mult"), "k", "l"), _plain_sql(_COARSE, G_DAYS))
    add("k_cross_types", lambda s, d: rounded(est.estimate_k_cross(es(s, d), "click", "purchase", W, G5), "k", "l"), _cross_sql(G5))
    add("k_sector", lambda s, d: rounded(est.estimate_k_sector(es(s, d), W, G5, 0.0, 1.5), "k", "l"), _sector_sql(G5))
    add("k_inhom", lambda s, d: rounded(est.estimate_k_inhom(est.grid_intensity(es(s, d), W, 6, 2, 3), W, G5, "lam"), "k", "l"), _inhom_sql(G5))
    add("k_by_type", lambda s, d: rounded(est.estimate_k_by(es(s, d), W, G5, "mark"), "k", "l"), f"WITH {_ES}, {o.pairs(5.0, 20 * HOUR, ', c.mark', ' AND c.mark = q.mark')}, {o.bins(G5, o.weight(W), keys='mark')}, {o.cumulated(G5, 'mark', 'SELECT DISTINCT mark FROM pts')} {o.surface(G5, o.scale_of(W, '(n * (n - 1))'), 'mark', ' JOIN (SELECT mark, count(*) AS n FROM pts GROUP BY mark) nn USING (mark)')}")
    add("k_tolerance", lambda s, d: kb.space_cache(src.events_skewed(s, d), W, 5.0, 20 * HOUR, 0.5, 0.25).select("kx", "ky", "kd", F.round("ws", 6).alias("ws")), f"WITH {_P5}, k AS (SELECT DISTINCT round(x / 0.5::DOUBLE) * 0.5::DOUBLE AS kx, round(y / 0.5::DOUBLE) * 0.5::DOUBLE AS ky, round(d / 0.25::DOUBLE) * 0.25::DOUBLE AS kd FROM pairs) SELECT kx, ky, kd, round({o.w_rect(W, 'kx', 'ky', 'kd')}, 6) AS ws FROM k")
    add("weights_rect", lambda s, d: found(s, d).select("i", "j", F.round(geo.w_space_rect(F.col("x"), F.col("y"), F.col("d"), W), 6).alias("w")), f"WITH {_P5} SELECT i, j, round({o.w_rect(W)}, 6) AS w FROM pairs")
    add("weights_time", lambda s, d: found(s, d).select("i", "j", geo.w_time(F.col("t0"), F.col("u"), W).alias("w")), f"WITH {_P5} SELECT i, j, {o.w_time(W)} AS w FROM pairs")
    add("weights_polygon_rect_100", lambda s, d: found(s, d).select("i", "j", F.round(geo.w_space_polygon(geo.rect_ring(W, 100), rect=W)("x", "y", "d"), 3).alias("w")), f"WITH {_P5} SELECT i, j, round({o.w_rect(W)}, 3) AS w FROM pairs")
    for name, ring in (("ngon", geo.ellipse_ring(85)), ("lshape", geo.l_ring(W)), ("star", geo.ellipse_ring(40, star=0.6))):
        add(f"weights_{name}", _ring_weights(ring), _ring_sql(ring))
    add("weights_guard", lambda s, d: est.guarded(found(s, d), W, 1.5).select("pairs", "capped"), f"WITH {_P5} SELECT count(*) AS pairs, count(*) FILTER ({o.w_rect(W)} > 1.5) AS capped FROM pairs")
    add("pairs_interval", lambda s, d: pr.pairs_intervals(_intervals(s, d), 2.0, 10 * HOUR, window=W).select("i", "j", "u"), _INTERVAL_SQL)
    overall = o.k_surface("events_skewed", G_OVERALL)
    add("k_plain", lambda s, d: job.job_surface(es(s, d), W, G_OVERALL, "plain"), overall)
    add("k_planned", lambda s, d: job.job_surface(es(s, d), W, G_OVERALL), overall)
    for name, plan in STRATEGIES.items():
        add(f"k_strategy_{name}", lambda s, d, x=plan: job.job_surface(es(s, d), W, G_OVERALL, strategies=x), overall)
    add("cache_keys", lambda s, d: kb.key_counts(src.events_skewed(s, d), W, 5.0, 20 * HOUR), f"WITH {_P5} SELECT count(*) AS pairs, count(DISTINCT (x, y)) AS places, count(DISTINCT (x, y, d)) AS space_keys, count(DISTINCT t0) AS times, count(DISTINCT (t0, u)) AS time_keys FROM pairs")
    for method in ("permutation", "bootstrap", "cstr"):
        cols = "sim, id, x, y, t0"
        add(f"sim_{method}", lambda s, d, m=method: sim.simulated(es(s, d), W, m, 2, ordered=True).select("sim", "id", "x", "y", "t0"), f"WITH {_ES}, {sets_sql(method, 2)} SELECT {cols} FROM sims")
        add(f"cache_hits_{method}", _cache_hits(method), _cache_sql(method))
    for method in ("permutation", "cstr"):
        add(f"envelope_{method}", lambda s, d, m=method: sim.envelope(_sims(s, d, m, 19)).select("si", "ti", "l_min", "l_max", F.round("l_mean", 3).alias("l_mean"), "m"), f"WITH {_sim_surface_sql(method, 19, G_SIM)} SELECT si, ti, min(l) AS l_min, max(l) AS l_max, round(avg(l), 3) AS l_mean, count(l) AS m FROM surf GROUP BY si, ti")
        add(f"significance_{method}", lambda s, d, m=method: rounded(sim.significance(_observed(s, d), _sims(s, d, m, 19)), "diff"), f"WITH {_sim_surface_sql(method, 19, G_SIM)}, {_SIG} {_SIG_ROWS}")
    add("peak_scale", lambda s, d: rounded(sim.peak_scale(sim.significance(_observed(s, d), _sims(s, d, "cstr", 19))), "diff"), f"WITH {_sim_surface_sql('cstr', 19, G_SIM)}, {_SIG}, b AS (SELECT si, ti, diff FROM sig ORDER BY diff DESC, si, ti LIMIT 1) SELECT b.si, b.ti, round(b.diff, 4) AS diff, max(s) FILTER (verdict = 'clustered') AS s_significant, max(t) FILTER (verdict = 'clustered') AS t_significant, count(*) FILTER (verdict = 'clustered') AS n_significant FROM sig, b GROUP BY b.si, b.ti, b.diff")
    add("sequential_k", lambda s, d: sim.sequential_k(es(s, d), W, G_SIM, "cstr", 19, 19).select("si", "ti", "p"), f"WITH {_sim_surface_sql('cstr', 19, G_SIM)}, {_SIG} SELECT si, ti, p FROM sig")
    add("sim_permutation_keyed", lambda s, d: sim.simulate_permutation(es(s, d), 2).groupBy("sim").agg(F.count("*").alias("n"), F.countDistinct("id").alias("ids"), F.sum(F.col("t0").cast("decimal(38,0)")).cast("string").alias("t_sum")), f"WITH {_ES} SELECT CAST(s AS INTEGER) AS sim, count(*) AS n, count(DISTINCT id) AS ids, CAST(sum(t0) AS VARCHAR) AS t_sum FROM pts, range(1, 3) r(s) GROUP BY s")
    add("sim_static_pairs", lambda s, d: rounded(sim.simulate_k(es(s, d), W, G_SIM, "permutation", 2, ordered=True, reuse="spatial_pairs"), "k", "l"), f"WITH {_sim_surface_sql('permutation', 2, G_SIM)} SELECT * FROM surf")
    add("grid_partition_stats", lambda s, d: _stats("grid", 64)(s, d).select("scheme", "leaves", "rows_max", "empty", "uncovered"), _grid_stats_sql())
    add("hash_replication", lambda s, d: _stats("hash", 16)(s, d).select("scheme", "leaves", "rows_max", "cylinder_factor", "ghost_factor"), _hash_stats_sql(16, 5.0, 20 * HOUR))
    pc = ["id", "x", "y", "mult", "t0", "t1"]
    add("codec_roundtrip_points", lambda s, d: codec.decode_points(codec.encode_points(src.orders_month(s, d))).select(*pc, "zone"), f"SELECT id, x, y, mult, t0, t0 AS t1, zone FROM ({o.POINTS['orders_month']})")
    add("codec_roundtrip_cylinders", lambda s, d: codec.decode_cylinders(codec.encode_cylinders(es(s, d), 5.0, 20 * HOUR)), f"SELECT id, x, y, t0, 5.0::DOUBLE AS rs, CAST({20 * HOUR} AS BIGINT) AS rt, 'h' AS unit FROM ({o.POINTS['events_skewed']})")
    add("codec_roundtrip_envelopes", _envelopes, _envelopes_sql())
    add("codec_roundtrip_index", _index_roundtrip, f"WITH {o.pts('events_skewed')}, {o.pairs(5.0, 20 * HOUR)} SELECT i, j FROM pairs")
    add("surface_pivot", lambda s, d: rounded(tab.surface_matrix(est.estimate_k(es(s, d), W, G5), 5), "1", "2", "3", "4", "5"), f"PIVOT ({_plain_sql(_ES, G5)}) ON ti IN (1, 2, 3, 4, 5) USING first(l) GROUP BY si")
    add("pair_comparisons", lambda s, d: metrics.pair_stats(es(s, d), 5.0, 20 * HOUR).select("n", "compared_all", "pairs"), f"WITH {_P5} SELECT (SELECT count(*) FROM pts) AS n, (SELECT count(*) * (count(*) - 1) FROM pts) AS compared_all, count(*) AS pairs FROM pairs")
    add("strategy_plan", _planned, _planned_sql())
    add("workload_index", index_workload, _index_sql())
    add("workload_cache", cache_workload, _cache_workload_sql())
    add("workload_partitions", partition_workload, _partition_workload_sql())
    add("workload_codec", codec_workload, _codec_workload_sql())
    add("workload_uniform_ring", uniform_ring, _uniform_ring_sql())
    for method in ("cstr", "permutation"):
        add(f"workload_application_{method}", _application(method, 99), f"WITH {_sim_surface_sql(method, 99, G_SIM)}, {_SIG} {_SIG_ROWS}")
    return e
