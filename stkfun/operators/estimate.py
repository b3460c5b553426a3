"""The space-time K function: bins, prefix sums, L, corrections and relatives.

K(s, t) = area * hours / (n (n - 1)) * sum of weights of ordered pairs with
d <= s and u <= t. Pairs fall into one bin each; the surface is the prefix sum
over bins in both directions. Pair weights are summed in fixed point (1e-9), so
that sums do not depend on their order. Time in K is in hours.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stkfun.config import HOUR, DistanceGrid, StudyWindow
from stkfun.functions.geometry import border_gap, w_space, w_time, w_translation
from stkfun.functions.shared import settle
from stkfun.operators.pairs import pairs_cells

FIXED = 1_000_000_000


def bin_pairs(pairs: DataFrame, grid: DistanceGrid) -> DataFrame:
    """si, ti of each pair; 0 holds d = 0 or u = 0."""
    si = F.ceil(F.col("d") / grid.s_step).cast("int")
    ti = F.floor((F.col("u") + (grid.t_step - 1)) / grid.t_step).cast("int")
    return pairs.withColumn("si", si).withColumn("ti", ti).where((F.col("si") <= grid.s_steps) & (F.col("ti") <= grid.t_steps))


def fixed(w: Column) -> Column:
    return F.round(w * FIXED).cast("long")


def wide_sum(w: Column, times: Column | None = None) -> Column:
    """An exact sum of longs, each taken ``times``, that may exceed a long: 9.2e9 pairs of
    weight 1 do. The low 20 bits are summed apart, which holds for 8e12 rows."""
    high, low = F.shiftright(w, 20), w.bitwiseAND(F.lit((1 << 20) - 1).cast("long"))
    if times is not None:
        high, low = high * times, low * times
    return F.sum(high).cast("decimal(27,0)") * F.lit(1 << 20).cast("decimal(10,0)") + F.sum(low)


def pair_weight(window: StudyWindow, correction: str = "isotropic", w_cap: float | None = None, end: str = "", **polygon) -> Column:
    """The weight of a pair seen from its centre, or (``end`` = "2") from its neighbour."""
    if correction == "none":
        return F.lit(1.0)
    if correction == "translation":
        return w_translation(F.col("dx"), F.col("dy"), F.col("u"), window)
    x, y, t = ("x2", "y2", "t2") if end else ("x", "y", "t0")
    w = w_space(F.col(x), F.col(y), F.col("d"), window, **polygon)
    return (F.least(w, F.lit(w_cap)) if w_cap else w) * w_time(F.col(t), F.col("u"), window)


def guarded(pairs: DataFrame, window: StudyWindow, w_cap: float, **polygon) -> DataFrame:
    """How many pairs the cap on spatial weights touches, and the largest weight."""
    w = w_space(F.col("x"), F.col("y"), F.col("d"), window, **polygon)
    return pairs.select(w.alias("w")).agg(F.count("*").alias("pairs"), F.coalesce(F.count_if(F.col("w") > w_cap), F.lit(0)).alias("capped"), F.max("w").alias("largest"))


def histogram(pairs: DataFrame, grid: DistanceGrid, weight: Column, keys: tuple[str, ...] = ()) -> DataFrame:
    """pairs and fixed-point weight of each (keys, si, ti) bin."""
    return bin_pairs(pairs, grid).select(*keys, "si", "ti", fixed(weight).alias("w")).groupBy(*keys, "si", "ti").agg(F.count("*").alias("pairs"), wide_sum(F.col("w")).alias("wfix"))


def dense_grid(like: DataFrame, grid: DistanceGrid) -> DataFrame:
    spark = like.sparkSession
    s = spark.range(grid.s_steps + 1).select(F.col("id").cast("int").alias("si"))
    t = spark.range(grid.t_steps + 1).select(F.col("id").cast("int").alias("ti"))
    return F.broadcast(s.crossJoin(F.broadcast(t)))


def cumulate(hist: DataFrame, grid: DistanceGrid, groups: DataFrame | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Sums over all smaller bins, empty bins filled; ``groups`` lists the key values."""
    dense = dense_grid(hist, grid)
    dense = groups.crossJoin(dense) if keys else dense
    full = dense.join(hist, [*keys, "si", "ti"], "left").select(*keys, "si", "ti", F.coalesce("pairs", F.lit(0)).alias("pairs"), F.coalesce(F.col("wfix").cast("decimal(38,0)"), F.lit(0)).alias("wfix"))
    for along, other in (("si", "ti"), ("ti", "si")):
        run = Window.partitionBy(*keys, other).orderBy(along).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        full = full.withColumn("pairs", F.sum("pairs").over(run)).withColumn("wfix", F.sum("wfix").over(run))
    return full


def to_l(k: Column, s: Column, t: Column, kind: str = "centred") -> Column:
    """L of K; t in hours. Null at t = 0, where the reference volume vanishes."""
    root = F.sqrt(k / (2 * math.pi * t))
    value = {"centred": root - s, "root": root, "difference": k - 2 * math.pi * s * s * t}[kind]
    return F.when(t > 0, value)


def surface(cum: DataFrame, grid: DistanceGrid, scale: Column, keys: tuple[str, ...] = (), include_zero: bool = False, kind: str = "centred") -> DataFrame:
    """s, t (hours), pairs, k, l from cumulated bins and the factor of the weight sum."""
    s, t = F.col("si") * float(grid.s_step), F.col("ti") * (grid.t_step / HOUR)
    out = cum.withColumn("s", s).withColumn("t", t).withColumn("k", scale * (F.col("wfix").cast("double") / float(FIXED)))
    if not include_zero:
        out = out.where("si > 0 and ti > 0")
    return out.select(*keys, "si", "ti", "s", "t", "pairs", "k", to_l(F.col("k"), F.col("s"), F.col("t"), kind).alias("l"))


def norm_of(n: Column, norm: str) -> Column:
    """n (n - 1), or n squared; null where it is 0."""
    value = n * (n - 1) if norm == "n(n-1)" else n * n
    return F.when(value > 0, value.cast("double"))


def estimate_k(points: DataFrame, window: StudyWindow, grid: DistanceGrid, *, correction: str = "isotropic", norm: str = "n(n-1)", kind: str = "centred", include_zero: bool = False, w_cap: float | None = None, pairs: DataFrame | None = None, cache=None, by: str | None = None, mult: str | None = None, salt: int = 1, **polygon) -> DataFrame:
    """The K and L surface, one for each value of ``by``.

    ``pairs`` may come from any pair operator, else each unordered pair is found
    once and weighed from both ends; ``cache`` (a ``WeightCache``) looks the weights
    of ordered pairs up; ``mult`` counts coincident points."""
    if correction == "border":
        return estimate_border(points, window, grid, kind=kind)
    keys = (by,) if by else ()
    carry = (mult,) if mult else ()
    half = pairs is None and cache is None
    found = pairs if pairs is not None else pairs_cells(points, grid.s_max, grid.t_max, keys, carry, window, salt, half=half, both=half)
    binned = bin_pairs(found, grid)
    times = F.col(f"c_{mult}").cast("long") * F.col(f"q_{mult}") if mult else F.lit(1).cast("long")
    if cache is not None:
        binned = cache.applied(binned)
        weight = fixed(F.least("w", F.lit(w_cap)) if w_cap else F.col("w"))
    else:
        weight = fixed(pair_weight(window, correction, w_cap, **polygon))
        weight = weight + fixed(pair_weight(window, correction, w_cap, "2", **polygon)) if half else weight
    rows = binned.select(*keys, "si", "ti", times.alias("m"), weight.alias("w"))
    ends = 2 if half else 1
    hist = rows.groupBy(*keys, "si", "ti").agg((F.sum("m") * ends).cast("long").alias("pairs"), wide_sum(F.col("w"), F.col("m")).alias("wfix"))
    counts = points.groupBy(*keys).agg((F.sum(F.col(mult).cast("long")) if mult else F.count("*")).alias("n"), *([F.sum(F.col(mult).cast("long") * (F.col(mult) - 1)).alias("own")] if mult else []))
    if mult:
        own = counts.select(*keys, F.lit(0).alias("si"), F.lit(0).alias("ti"), F.col("own").alias("pairs"), (F.col("own").cast("decimal(28,0)") * F.lit(FIXED).cast("decimal(10,0)")).alias("wfix"))
        hist = hist.unionByName(own).groupBy(*keys, "si", "ti").agg(F.sum("pairs").alias("pairs"), F.sum("wfix").alias("wfix"))
    cum = cumulate(hist, grid, counts.select(*keys).distinct() if keys else None, keys)
    whole = cum.join(F.broadcast(counts), list(keys)) if keys else cum.crossJoin(F.broadcast(counts))
    scale = F.lit(window.area * window.hours) / norm_of(F.col("n"), norm)
    return surface(whole, grid, scale, keys, include_zero, kind)


def estimate_k_by(points: DataFrame, window: StudyWindow, grid: DistanceGrid, by: str, **options) -> DataFrame:
    return estimate_k(points, window, grid, by=by, **options)


def estimate_border(points: DataFrame, window: StudyWindow, grid: DistanceGrid, kind: str = "centred") -> DataFrame:
    """Guard zones: at (s, t) only centres at least s from the border and t from
    the period's ends count, over their own number."""
    guarded = points.withColumn("g", border_gap(F.col("x"), F.col("y"), window)).withColumn("h", F.least(F.col("t0") - window.t_start, F.lit(window.t_end) - F.col("t0")))
    gs = F.least(F.floor(F.col("g") / grid.s_step), F.lit(grid.s_steps)).cast("int")
    gt = F.least(F.floor(F.col("h") / grid.t_step), F.lit(grid.t_steps)).cast("int")
    guarded = guarded.withColumn("gs", gs).withColumn("gt", gt)
    steps = dense_grid(points, grid).where("si > 0 and ti > 0")
    zones = guarded.groupBy("gs", "gt").agg(F.count("*").alias("n"))
    centres = steps.join(zones, (zones.gs >= steps.si) & (zones.gt >= steps.ti)).groupBy("si", "ti").agg(F.sum("n").alias("centres"))
    found = bin_pairs(pairs_cells(guarded, grid.s_max, grid.t_max, carry=("gs", "gt"), window=window), grid)
    bins = found.groupBy(F.col("si").alias("ps"), F.col("ti").alias("pt"), "c_gs", "c_gt").agg(F.count("*").alias("n"))
    seen = steps.join(bins, (F.col("ps") <= F.col("si")) & (F.col("pt") <= F.col("ti")) & (F.col("c_gs") >= F.col("si")) & (F.col("c_gt") >= F.col("ti"))).groupBy("si", "ti").agg(F.sum("n").alias("pairs"))
    n = points.agg(F.count("*").alias("n"))
    out = steps.join(centres, ["si", "ti"], "left").join(seen, ["si", "ti"], "left").crossJoin(F.broadcast(n))
    s, t = F.col("si") * float(grid.s_step), F.col("ti") * (grid.t_step / HOUR)
    k = F.lit(window.area * window.hours) * F.coalesce("pairs", F.lit(0)) / (F.when(F.col("centres") > 0, F.col("centres").cast("double")) * (F.col("n") - 1))
    out = out.select("si", "ti", s.alias("s"), t.alias("t"), F.coalesce("pairs", F.lit(0)).alias("pairs"), k.alias("k"))
    return out.withColumn("l", to_l(F.col("k"), F.col("s"), F.col("t"), kind))


def collapse_coincident(points: DataFrame, coord_tol: float | None = None) -> DataFrame:
    """Points of one place and time become one with their number."""
    snap = (lambda c: F.round(F.col(c) / coord_tol) * coord_tol) if coord_tol else F.col
    return points.groupBy(snap("x").alias("x"), snap("y").alias("y"), "t0").agg(F.min("id").alias("id"), F.max("t1").alias("t1"), F.sum("mult").cast("int").alias("mult"), F.min("zone").alias("zone"), F.min("mark").alias("mark"))


def estimate_k_space(points: DataFrame, window: StudyWindow, grid: DistanceGrid, corrected: bool = True) -> DataFrame:
    """Spatial K and L = sqrt(K / pi) - s: time is ignored."""
    flat = points.withColumn("t0", F.lit(0).cast("long")).withColumn("t1", F.lit(0).cast("long"))
    found = pairs_cells(flat, grid.s_max, 1, half=True, both=True)
    ends = [w_space(F.col(x), F.col(y), F.col("d"), window) if corrected else F.lit(1.0) for x, y in (("x", "y"), ("x2", "y2"))]
    si = F.ceil(F.col("d") / grid.s_step).cast("int")
    rows = found.select(si.alias("si"), (fixed(ends[0]) + fixed(ends[1])).alias("w")).where(F.col("si") <= grid.s_steps)
    hist = rows.groupBy("si").agg((F.count("*") * 2).alias("pairs"), wide_sum(F.col("w")).alias("wfix"))
    return _line(points, hist, "si", grid.s_steps, float(grid.s_step), window.area, lambda k, s: F.sqrt(k / math.pi) - s, "s")


def estimate_k_time(points: DataFrame, window: StudyWindow, grid: DistanceGrid, corrected: bool = True) -> DataFrame:
    """Temporal K (hours) and its difference from 2 t.

    Pairs are not formed: a centre has as many neighbours up to u as there are points
    up to t + u less those before t - u, and weight 2 beyond its distance from the
    period's nearer end. Bounds and points are sorted together; ``asked`` holds how
    often a bound's rank counts in the number of pairs (a) and in that beyond the ends (b)."""
    m, t0, edge = F.col("m"), F.col("t0"), F.least(F.col("t0") - window.t_start, F.lit(window.t_end) - F.col("t0"))
    times = points.groupBy("t0").agg(F.count("*").alias("m"))
    bounds = []
    for k in range(grid.t_steps + 1):
        u = F.lit(k * grid.t_step).cast("long")
        twice = F.when(u > edge, m).otherwise(0) if corrected else F.lit(0).cast("long")
        upto = F.when(edge >= 0, twice).otherwise(0)
        for v, sign, a, b in ((t0 + u, 1, m, twice), (t0 - u - 1, -1, m, twice), (t0 + edge, -1, m * 0, upto), (t0 - edge - 1, 1, m * 0, upto)):
            bounds.append(F.struct(F.lit(k).alias("ti"), v.alias("v"), (a * sign).alias("a"), (b * sign).alias("b")))
    asked = times.select(F.explode(F.array(*bounds)).alias("z")).select("z.*", F.lit(0).cast("long").alias("m")).where("a <> 0 or b <> 0")
    known = times.select(F.lit(-1).alias("ti"), t0.alias("v"), F.lit(0).cast("long").alias("a"), F.lit(0).cast("long").alias("b"), "m")
    placed = settle(known.unionByName(asked).repartitionByRange("v").withColumn("slice", F.spark_partition_id()), "bounds")
    before = placed.groupBy("slice").agg(F.sum("m").alias("held")).withColumn("before", F.sum("held").over(Window.partitionBy().orderBy("slice")) - F.col("held"))
    rank = F.col("before") + F.sum("m").over(Window.partitionBy("slice").orderBy("v"))
    ranked = placed.join(before.select("slice", "before").hint("merge"), "slice").withColumn("rank", rank).where("ti >= 0")
    sums = ranked.groupBy("ti").agg(wide_sum(F.col("rank") * F.col("a")).alias("a"), wide_sum(F.col("rank") * F.col("b")).alias("b"))
    alone = times.agg(F.sum("m").alias("all"), F.sum(F.when((edge < 0) & F.lit(corrected), m).otherwise(0)).alias("outside"))
    cum = sums.crossJoin(F.broadcast(alone)).select("ti", (F.col("a") - F.col("all")).alias("a"), (F.col("b") - F.col("outside")).alias("b"))
    gained = lambda c: F.col(c) - F.coalesce(F.lag(c).over(Window.partitionBy().orderBy("ti")), F.lit(0))
    hist = cum.select("ti", gained("a").cast("long").alias("pairs"), ((gained("a") + gained("b")).cast("decimal(28,0)") * F.lit(FIXED).cast("decimal(10,0)")).alias("wfix"))
    return _line(points, hist, "ti", grid.t_steps, grid.t_step / HOUR, window.hours, lambda k, t: k - 2 * t, "t")


def _line(points: DataFrame, hist: DataFrame, key: str, steps: int, step: float, extent: float, l_of, name: str) -> DataFrame:
    run = Window.partitionBy().orderBy(key).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    dense = points.sparkSession.range(steps + 1).select(F.col("id").cast("int").alias(key))
    cum = dense.join(hist, key, "left").withColumn("pairs", F.sum(F.coalesce("pairs", F.lit(0))).over(run)).withColumn("wfix", F.sum(F.coalesce("wfix", F.lit(0))).over(run))
    n = points.agg(F.count("*").alias("n"))
    out = cum.crossJoin(F.broadcast(n)).withColumn(name, F.col(key) * step).withColumn("k", F.lit(extent) / norm_of(F.col("n"), "n(n-1)") * (F.col("wfix").cast("double") / float(FIXED)))
    return out.where(F.col(key) > 0).select(key, name, "pairs", "k", l_of(F.col("k"), F.col(name)).alias("l"))


def interaction(st: DataFrame, ks: DataFrame, kt: DataFrame) -> DataFrame:
    """D(s, t) = K(s, t) - K_space(s) K_time(t)."""
    a, b = ks.select("si", F.col("k").alias("ks")), kt.select("ti", F.col("k").alias("kt"))
    return st.join(F.broadcast(a), "si").join(F.broadcast(b), "ti").select("si", "ti", "s", "t", "k", "ks", "kt", (F.col("k") - F.col("ks") * F.col("kt")).alias("residual"))


def estimate_k_cross(points: DataFrame, mark_a: str, mark_b: str, window: StudyWindow, grid: DistanceGrid, correction: str = "isotropic") -> DataFrame:
    """Centres of one mark, neighbours of another, over n_a n_b."""
    some = points.where(F.col("mark").isin(mark_a, mark_b))
    found = pairs_cells(some, grid.s_max, grid.t_max, carry=("mark",), window=window).where((F.col("c_mark") == mark_a) & (F.col("q_mark") == mark_b))
    cum = cumulate(histogram(found, grid, pair_weight(window, correction)), grid)
    n = some.agg(F.count_if(F.col("mark") == mark_a).alias("na"), F.count_if(F.col("mark") == mark_b).alias("nb"))
    number = F.col("na") * (F.col("nb") - 1) if mark_a == mark_b else F.col("na") * F.col("nb")
    return surface(cum.crossJoin(F.broadcast(n)), grid, F.lit(window.area * window.hours) / F.when(number > 0, number.cast("double")))


def estimate_k_inhom(points: DataFrame, window: StudyWindow, grid: DistanceGrid, lambda_col: str) -> DataFrame:
    """Pairs weighted by 1 / (lambda_i lambda_j), over area times hours."""
    found = pairs_cells(points, grid.s_max, grid.t_max, carry=(lambda_col,), window=window)
    w = pair_weight(window) * intensity_unit(window) / (F.col(f"c_{lambda_col}") * F.col(f"q_{lambda_col}"))
    return surface(cumulate(histogram(found, grid, w), grid), grid, F.lit(1.0 / (window.area * window.hours) / intensity_unit(window)))


def intensity_unit(window: StudyWindow) -> float:
    """The squared density of 10,000 points: keeps inverse intensities in the range of fixed point."""
    return (1e4 / (window.area * window.hours)) ** 2


def grid_intensity(points: DataFrame, window: StudyWindow, nx: int, ny: int, nt: int) -> DataFrame:
    """Points with lam: events per unit area and hour of their coarse cell."""
    size = [(window.x1 - window.x0) / nx, (window.y1 - window.y0) / ny, window.period / nt]
    keys = [F.least(F.floor((F.col(c) - o) / z), F.lit(n - 1)).alias(k) for c, o, z, n, k in (("x", window.x0, size[0], nx, "gx"), ("y", window.y0, size[1], ny, "gy"), ("t0", window.t_start, size[2], nt, "gt"))]
    placed = points.select("*", *keys)
    counts = placed.groupBy("gx", "gy", "gt").agg(F.count("*").alias("m"))
    volume = size[0] * size[1] * size[2] / HOUR
    return placed.join(counts, ["gx", "gy", "gt"]).withColumn("lam", F.col("m") / volume).drop("gx", "gy", "gt", "m")


def estimate_k_sector(points: DataFrame, window: StudyWindow, grid: DistanceGrid, a0: float, a1: float) -> DataFrame:
    """Only neighbours whose direction lies in [a0, a1), scaled to the full circle."""
    found = pairs_cells(points, grid.s_max, grid.t_max, window=window)
    angle = F.atan2("dy", "dx")
    cum = cumulate(histogram(found.where((angle >= a0) & (angle < a1)), grid, pair_weight(window)), grid)
    n = points.agg(F.count("*").alias("n"))
    return surface(cum.crossJoin(F.broadcast(n)), grid, F.lit(window.area * window.hours * 2 * math.pi / (a1 - a0)) / norm_of(F.col("n"), "n(n-1)"))


def classify(l: Column, lower: Column, upper: Column) -> Column:
    return F.when(l > upper, "clustered").when(l < lower, "dispersed").otherwise("random")


def max_abs_diff(a: DataFrame, b: DataFrame, value: str = "k") -> DataFrame:
    """Largest difference of two surfaces."""
    both = a.select("si", "ti", F.col(value).alias("va")).join(b.select("si", "ti", F.col(value).alias("vb")), ["si", "ti"], "full")
    return both.agg(F.max(F.abs(F.col("va") - F.col("vb"))).alias("max_abs_diff"), F.count_if(F.col("va").isNull() != F.col("vb").isNull()).alias("unmatched"))
