"""Simulated point sets, envelopes and significance."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stkfun.config import DistanceGrid, StudyWindow
from stkfun.functions.geometry import hash_uniform, inside_ring, w_space, w_time
from stkfun.functions.shared import settle
from stkfun.operators.estimate import bin_pairs, classify, cumulate, estimate_k, fixed, norm_of, surface, wide_sum
from stkfun.operators.pairs import pairs_cells


def sims(spark, m: int, first: int = 1) -> DataFrame:
    return spark.range(first, first + m).select(F.col("id").cast("int").alias("sim"))


def dense_index(points: DataFrame, name: str = "k", by: tuple[str, ...] = ("id",)) -> tuple[DataFrame, int]:
    """``points`` with a dense 0-based index in the order of ``by``, and their number.

    Rows are range-partitioned; partition counts (one small row each) give the offsets."""
    parts = settle(points.repartitionByRange(*by).withColumn("__p", F.spark_partition_id()), "indexed")
    counts = sorted(parts.groupBy("__p").agg(F.count("*").alias("n")).collect())
    offset, at = [], 0
    for p, n in counts:
        offset.append((p, at))
        at += n
    table = points.sparkSession.createDataFrame(offset or [(0, 0)], "__p int, __o long")
    local = F.row_number().over(Window.partitionBy("__p").orderBy(*by))
    return parts.withColumn("__r", local - 1).join(F.broadcast(table), "__p").withColumn(name, F.col("__o") + F.col("__r")).drop("__p", "__o", "__r"), at


def bijection(k: Column, n: int, seed: int, sim: Column, rounds: int = 6) -> Column:
    """A keyed permutation of 0 .. n-1: a Feistel network on the least power of two
    that holds n (rounds change the high and the low bits in turn), walked until the
    value falls below n. At most half of the values lie above, so a walk of 256
    steps ends but for one point in 10 ** 77."""
    bits = max(2, (max(n - 1, 1)).bit_length())
    low = bits // 2
    masks = [(1 << low) - 1, (1 << (bits - low)) - 1]
    bit_and = lambda v, m: v.bitwiseAND(F.lit(m).cast("long"))

    def once(v: Column) -> Column:
        def step(p: Column, r: Column) -> Column:
            f = lambda half: F.xxhash64(F.lit(seed), sim, r, half)
            high = F.struct(p["a"].bitwiseXOR(bit_and(f(p["b"]), masks[1])).alias("a"), p["b"].alias("b"))
            return F.when(r % 2 == 1, high).otherwise(F.struct(p["a"].alias("a"), p["b"].bitwiseXOR(bit_and(f(p["a"]), masks[0])).alias("b")))

        pair = F.struct(F.shiftright(v, low).alias("a"), bit_and(v, masks[0]).alias("b"))
        return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), pair, step, lambda p: F.shiftleft(p["a"], low).bitwiseOR(p["b"]))

    return F.aggregate(F.sequence(F.lit(1), F.lit(256)), once(k.cast("long")), lambda v, _: F.when(v < n, v).otherwise(once(v)))


def simulate_permutation(points: DataFrame, m: int, seed: int = 42, ordered: bool = False) -> DataFrame:
    """Places stay, times are exchanged: by a keyed bijection of the points' ranks, or
    (``ordered``) in the order of md5 keys, which any engine can repeat."""
    spark = points.sparkSession
    if ordered:
        places, n = dense_index(points)
        keyed = points.select("id", "t0", "t1").crossJoin(F.broadcast(sims(spark, m)))
        keyed = keyed.withColumn("h", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("sim").cast("string"), F.col("id").cast("string"))))
        times = dense_index(keyed, "k", ("sim", "h", "id"))[0].select("sim", (F.col("k") - (F.col("sim") - 1).cast("long") * n).alias("k"), "t0", "t1")
        return places.drop("t0", "t1").join(times, "k").drop("k")
    indexed, n = dense_index(points)
    indexed = settle(indexed, "permuted")
    moved = indexed.drop("t0", "t1").withColumn("sim", F.explode(F.sequence(F.lit(1), F.lit(m)))).withColumn("k2", bijection(F.col("k"), n, seed, F.col("sim"))).drop("k")
    return moved.join(indexed.select(F.col("k").alias("k2"), "t0", "t1"), "k2").drop("k2")


def simulate_bootstrap(points: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """n whole rows drawn with replacement by rank; ids are fresh (draw numbers)."""
    spark = points.sparkSession
    indexed, n = dense_index(points)
    draws = spark.range(n).select(F.col("id").alias("draw")).crossJoin(F.broadcast(sims(spark, m)))
    u = hash_uniform("boot", F.concat_ws(":", F.lit(str(seed)), F.col("sim").cast("string"), F.col("draw").cast("string")))
    draws = draws.withColumn("k", F.floor(u * n).cast("long"))
    return draws.join(indexed.withColumn("k", F.col("k").cast("long")), "k").drop("k", "id").withColumnRenamed("draw", "id")


_BLOCK = 1 << 16


def simulate_cstr(spark, n: int, window: StudyWindow, m: int, seed: int = 42) -> DataFrame:
    """Uniform places and times; in a ring the first n of each simulation that fall inside,
    from as many candidates as that takes."""

    def drawn(many: int) -> DataFrame:
        base = spark.range(many).crossJoin(F.broadcast(sims(spark, m)))
        key = F.concat_ws(":", F.lit(str(seed)), F.col("sim").cast("string"), F.col("id").cast("string"))
        x = F.lit(window.x0) + (window.x1 - window.x0) * hash_uniform("x", key)
        y = F.lit(window.y0) + (window.y1 - window.y0) * hash_uniform("y", key)
        t = (F.lit(window.t_start) + F.floor(float(window.period) * hash_uniform("t", key))).cast("long")
        return base.select("sim", "id", x.alias("x"), y.alias("y"), t.alias("t0"), t.alias("t1"), F.lit(1).alias("mult"))

    if not window.ring:
        return drawn(n)
    share = window.area / ((window.x1 - window.x0) * (window.y1 - window.y0))
    if share <= 0:
        raise ValueError("the ring has no area")
    many = int(n / share * 1.1) + 100
    while True:
        inside = settle(drawn(many).where(inside_ring(F.col("x"), F.col("y"), window.ring)).withColumn("block", F.shiftright("id", 16)), "inside")
        counts = inside.groupBy("sim", "block").agg(F.count("*").alias("held"))
        if n == 0 or (counts.groupBy("sim").agg(F.sum("held").alias("held")).where(F.col("held") >= n).count() == m):
            break
        many *= 2
    # Ranks are prefix sums over blocks of ids; rows are numbered within a block only.
    line = Window.partitionBy("sim").orderBy("block")
    before = counts.withColumn("before", F.sum("held").over(line) - F.col("held")).where(F.col("before") < n).select("sim", "block", "before")
    ranked = inside.join(before, ["sim", "block"]).withColumn("r", F.row_number().over(Window.partitionBy("sim", "block").orderBy("id")))
    return ranked.where(F.col("before") + F.col("r") <= n).drop("block", "before", "r")


def simulated(points: DataFrame, window: StudyWindow, method: str, m: int, seed: int = 42, ordered: bool = False, n: int | None = None) -> DataFrame:
    if method == "permutation":
        return simulate_permutation(points, m, seed, ordered)
    if method == "bootstrap":
        return simulate_bootstrap(points, m, seed)
    if method == "cstr":
        return simulate_cstr(points.sparkSession, points.count() if n is None else n, window, m, seed)
    raise ValueError(f"unknown simulation {method}")


def simulate_k(points: DataFrame, window: StudyWindow, grid: DistanceGrid, method: str = "permutation", m: int = 19, seed: int = 42, ordered: bool = False, reuse: str = "none", **options) -> DataFrame:
    """Surfaces of all simulations (column sim)."""
    if reuse == "spatial_pairs":
        return _static_pairs(points, window, grid, m, seed, ordered)
    sets = simulated(points, window, method, m, seed, ordered)
    return estimate_k(sets, window, grid, by="sim", **options)


def _static_pairs(points: DataFrame, window: StudyWindow, grid: DistanceGrid, m: int, seed: int, ordered: bool, block: int = 32) -> DataFrame:
    """Permutation moves times only: every spatial pair is found once for ``block``
    simulations, each point carrying its times in all of them, and its two spatial
    weights serve them all. Pairs are not kept, so there is no table of them.

    Pays where a point has few spatial neighbours; else the cells of space and time
    of each simulation are the smaller search."""
    flat = points.withColumns({"t0": F.lit(0).cast("long"), "t1": F.lit(0).cast("long")})
    moved = simulate_permutation(points, m, seed, ordered).select("sim", "id", "t0")
    parts = []
    for first in range(1, m + 1, block):
        last = min(first + block - 1, m)
        some = moved.where(F.col("sim").between(first, last)).groupBy("id").agg(F.sort_array(F.collect_list(F.struct("sim", "t0"))).alias("tt"))
        found = pairs_cells(flat.join(some.select("id", F.col("tt.t0").alias("tt")), "id"), grid.s_max, 1, carry=("tt",), half=True, both=True)
        ws = [w_space(F.col(x), F.col(y), F.col("d"), window) for x, y in (("x", "y"), ("x2", "y2"))]
        timed = found.select("d", ws[0].alias("w1"), ws[1].alias("w2"), F.posexplode(F.arrays_zip("c_tt", "q_tt")).alias("k", "z"))
        timed = timed.select((F.col("k") + first).cast("int").alias("sim"), "d", "w1", "w2", F.col("z.c_tt").alias("ta"), F.col("z.q_tt").alias("tb")).withColumn("u", F.abs(F.col("ta") - F.col("tb"))).where(F.col("u") <= grid.t_max)
        weight = fixed(F.col("w1") * w_time(F.col("ta"), F.col("u"), window)) + fixed(F.col("w2") * w_time(F.col("tb"), F.col("u"), window))
        parts.append(bin_pairs(timed, grid).groupBy("sim", "si", "ti").agg((F.count("*") * 2).alias("pairs"), wide_sum(weight).alias("wfix")))
    hist = parts[0]
    for p in parts[1:]:
        hist = hist.unionByName(p)
    cum = cumulate(hist, grid, sims(points.sparkSession, m), ("sim",))
    n = points.agg(F.count("*").alias("n"))
    return surface(cum.crossJoin(F.broadcast(n)), grid, F.lit(window.area * window.hours) / norm_of(F.col("n"), "n(n-1)"), ("sim",))


def envelope(surfaces: DataFrame) -> DataFrame:
    """Lowest, highest and mean L of the simulations, and their middle 90 %."""
    return surfaces.groupBy("si", "ti").agg(
        F.min("l").alias("l_min"), F.max("l").alias("l_max"), F.avg("l").alias("l_mean"), F.expr("percentile(l, 0.05)").alias("l_q05"), F.expr("percentile(l, 0.95)").alias("l_q95"), F.count("l").alias("m")
    )


def significance(observed: DataFrame, surfaces: DataFrame) -> DataFrame:
    """Decision and p = (1 + simulations at or above) / (m + 1) at every distance."""
    o = observed.select("si", "ti", "s", "t", F.col("l").alias("l_obs"))
    both = surfaces.select("si", "ti", "l").join(F.broadcast(o), ["si", "ti"])
    out = both.groupBy("si", "ti", "s", "t", "l_obs").agg(F.max("l").alias("l_upper"), F.min("l").alias("l_lower"), F.count_if(F.col("l") >= F.col("l_obs")).alias("above"), F.count("l").alias("m"))
    return out.select("si", "ti", "s", "t", "l_obs", "l_upper", "l_lower", F.abs(F.col("l_obs") - F.col("l_upper")).alias("diff"), ((F.col("above") + 1) / (F.col("m") + 1)).alias("p"), classify(F.col("l_obs"), F.col("l_lower"), F.col("l_upper")).alias("verdict"))


def peak_scale(decisions: DataFrame) -> DataFrame:
    """Where |L_obs - L_upper| is largest (ties: smallest si, then ti), and the significant range."""
    best = F.max(F.struct("diff", (-F.col("si")).alias("a"), (-F.col("ti")).alias("b")))
    hit = F.col("verdict") == "clustered"
    one = decisions.agg(best.alias("p"), F.max(F.when(hit, F.col("s"))).alias("s_significant"), F.max(F.when(hit, F.col("t"))).alias("t_significant"), F.count_if(hit).alias("n_significant"))
    return one.select((-F.col("p.a")).alias("si"), (-F.col("p.b")).alias("ti"), F.col("p.diff").alias("diff"), "s_significant", "t_significant", "n_significant")


def sequential_k(points: DataFrame, window: StudyWindow, grid: DistanceGrid, method: str = "cstr", batch: int = 10, max_sims: int = 100, seed: int = 42, stop: int = 5) -> DataFrame:
    """Simulate in batches until every distance has ``stop`` simulations at or above the
    observed L, or ``max_sims`` are made: each has its p-value."""
    observed = settle(estimate_k(points, window, grid), "observed")
    made, done = None, 0
    while done < max_sims:
        part = settle(simulate_k(points, window, grid, method, min(batch, max_sims - done), seed + done), "simbatch")
        made = part if made is None else made.unionByName(part)
        done += batch
        if significance(observed, made).where((F.col("p") * (F.lit(min(done, max_sims)) + 1) - 1) < stop).limit(1).count() == 0:
            break
    return significance(observed, made)
