"""Reuse of edge weights.

A cache is a table of distinct keys: (place, distance) -> spatial weight and
(time, gap) -> temporal weight. Estimation fills it; simulations only look up,
and compute what is missing. With tolerances the key is snapped and the weight
is that of the snapped values, so results do not depend on arrival order.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.config import StudyWindow
from stkfun.functions.geometry import w_space, w_time
from stkfun.functions.shared import settle
from stkfun.operators.pairs import pairs_cells


def snapped(c: Column, tol: float | None) -> Column:
    return F.round(c / tol) * tol if tol else c


@dataclass
class WeightCache:
    window: StudyWindow
    space: DataFrame
    time: DataFrame
    coord_tol: float | None = None
    dist_tol: float | None = None

    def applied(self, pairs: DataFrame) -> DataFrame:
        """``pairs`` with w: looked up where the key is there, computed elsewhere."""
        return looked_up(pairs, self)

    def keyed(self, pairs: DataFrame) -> DataFrame:
        return keyed(pairs, self.coord_tol, self.dist_tol)

    def freeze(self) -> WeightCache:
        """Written once; later lookups do not add to it."""
        return WeightCache(self.window, settle(self.space, "wspace"), settle(self.time, "wtime"), self.coord_tol, self.dist_tol)


def keyed(pairs: DataFrame, coord_tol: float | None = None, dist_tol: float | None = None) -> DataFrame:
    return pairs.withColumns({"kx": snapped(F.col("x"), coord_tol), "ky": snapped(F.col("y"), coord_tol), "kd": snapped(F.col("d"), dist_tol)})


def space_cache(pairs: DataFrame, window: StudyWindow, coord_tol: float | None = None, dist_tol: float | None = None) -> DataFrame:
    """kx, ky, kd -> ws, each distinct key once."""
    keys = keyed(pairs, coord_tol, dist_tol).select("kx", "ky", "kd").distinct()
    return keys.select("kx", "ky", "kd", w_space(F.col("kx"), F.col("ky"), F.col("kd"), window).alias("ws"))


def time_cache(pairs: DataFrame, window: StudyWindow) -> DataFrame:
    """t0, u -> wt, each distinct key once."""
    return pairs.select("t0", "u").distinct().select("t0", "u", w_time(F.col("t0"), F.col("u"), window).alias("wt"))


def fill(pairs: DataFrame, window: StudyWindow, coord_tol: float | None = None, dist_tol: float | None = None) -> WeightCache:
    return WeightCache(window, space_cache(pairs, window, coord_tol, dist_tol), time_cache(pairs, window), coord_tol, dist_tol)


def looked_up(pairs: DataFrame, cache: WeightCache) -> DataFrame:
    """``pairs`` with w, s_hit and t_hit; missing weights are computed and not stored."""
    named = cache.keyed(pairs)
    space = cache.space.withColumn("s_hit", F.lit(True))
    time = cache.time.withColumn("t_hit", F.lit(True))
    both = named.join(space, ["kx", "ky", "kd"], "left").join(time, ["t0", "u"], "left")
    if cache.window.ring:
        known, missing = both.where("ws is not null"), both.where("ws is null").drop("ws")
        both = known.unionByName(missing.withColumn("ws", w_space(F.col("kx"), F.col("ky"), F.col("kd"), cache.window)))
        ws = F.col("ws")
    else:
        ws = F.coalesce("ws", w_space(F.col("kx"), F.col("ky"), F.col("kd"), cache.window))
    wt = F.coalesce("wt", w_time(F.col("t0"), F.col("u"), cache.window))
    return both.withColumns({"w": ws * wt, "s_hit": F.coalesce("s_hit", F.lit(False)), "t_hit": F.coalesce("t_hit", F.lit(False))})


def cache_stats(pairs: DataFrame, cache: WeightCache, keys: tuple[str, ...] = ()) -> DataFrame:
    """Lookups and hits of both tiers."""
    got = looked_up(pairs, cache)
    return got.groupBy(*keys).agg(F.count("*").alias("lookups"), F.count_if("s_hit").alias("space_hits"), F.count_if("t_hit").alias("time_hits"))


def search_stats(points: DataFrame, cache: WeightCache, s: float, t: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """``cache_stats`` of the pairs of ``points``, which stay where they are found: a centre
    brings the distances of its place and the gaps of its time that the cache knows."""
    ds = cache.space.groupBy("kx", "ky").agg(F.collect_list("kd").alias("known_d"))
    us = cache.time.groupBy(F.col("t0").alias("kt")).agg(F.collect_list("u").alias("known_u"))
    centres = points.withColumns({"kx": snapped(F.col("x"), cache.coord_tol), "ky": snapped(F.col("y"), cache.coord_tol)})
    centres = centres.join(ds.hint("merge"), ["kx", "ky"], "left").join(us.hint("merge"), F.col("t0") == F.col("kt"), "left")
    pairs = pairs_cells(points, s, t, keys, window=cache.window, centres=centres, brought=("known_d", "known_u"))
    hit = lambda known, v: F.count_if(F.coalesce(F.array_contains(known, v), F.lit(False)))
    return pairs.groupBy(*keys).agg(F.count("*").alias("lookups"), hit("c_known_d", snapped(F.col("d"), cache.dist_tol)).alias("space_hits"), hit("c_known_u", F.col("u")).alias("time_hits"))


def key_counts(pairs: DataFrame) -> DataFrame:
    """Pairs and distinct keys of both tiers and of their first levels."""
    return pairs.agg(
        F.count("*").alias("pairs"), F.countDistinct("x", "y").alias("places"), F.countDistinct("x", "y", "d").alias("space_keys"),
        F.countDistinct("t0").alias("times"), F.countDistinct("t0", "u").alias("time_keys"),
    )


def nested(cache: WeightCache) -> DataFrame:
    """The two-tier shape: place -> map of distance -> weight (for small caches)."""
    return cache.space.groupBy("kx", "ky").agg(F.map_from_entries(F.collect_list(F.struct("kd", "ws"))).alias("by_distance"))
