"""The registered queries: (spark, sf_dir) -> DataFrame, each with its SQL."""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun import oracle as o
from stkfun.config import G10, G20, G_ORDERS, HOUR, W_EVENTS, W_ORDERS, DistanceGrid
from stkfun.operators import estimate as est
from stkfun.operators import pairs as pr
from stkfun.operators import partition as part
from stkfun.plans import surrounding, variants
from stkfun.sources import points as src

#: Space 5, time 20 h in 5 x 5 bins, for the pair variants.
G5 = DistanceGrid(1.0, 5, 4 * HOUR, 5)


def rounded(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, 4) for n in names})


def _surface(points, window, grid, **options):
    def run(spark, sf_dir):
        return rounded(est.estimate_k(points(spark, sf_dir), window, grid, **options), "k", "l")

    return run


def _bins(found):
    """Pair counts by bin of any pair operator's result."""

    def run(spark, sf_dir):
        p = found(spark, sf_dir)
        return est.bin_pairs(p, G5).groupBy("si", "ti").agg(F.count("*").alias("pairs"))

    return run


def _partitioned(scheme, replication, local="cells"):
    return _bins(lambda spark, d: part.pairs_partitioned(src.events_skewed(spark, d), W_EVENTS, G5.s_max, G5.t_max, 27, scheme, replication, local))


def core() -> dict:
    s, t = G5.s_max, G5.t_max
    skewed, uniform = src.events_skewed, src.events_uniform
    bins = o.pair_bins("events_skewed", G5)
    out = {
        "k_surface_skewed": (_surface(skewed, W_EVENTS, G20), o.k_surface("events_skewed", G20)),
        "k_surface_uniform": (_surface(uniform, W_EVENTS, G10), o.k_surface("events_uniform", G10)),
        "k_surface_orders": (_surface(src.orders_month, W_ORDERS, G_ORDERS), o.k_surface("orders_month", G_ORDERS)),
        "k_uncorrected": (_surface(skewed, W_EVENTS, G10, correction="none"), o.k_surface("events_skewed", G10, "none")),
        "k_translation": (_surface(skewed, W_EVENTS, G10, correction="translation"), o.k_surface("events_skewed", G10, "translation")),
        "pairs_cells": (_bins(lambda sp, d: pr.pairs_cells(skewed(sp, d), s, t, window=W_EVENTS)), bins),
        "pairs_cells_salted": (_bins(lambda sp, d: pr.pairs_cells(skewed(sp, d), s, t, window=W_EVENTS, salt=4)), bins),
        "pairs_cellcode": (_bins(lambda sp, d: pr.pairs_cellcode(skewed(sp, d), s, t, W_EVENTS)), bins),
        "pairs_sweep": (_bins(lambda sp, d: pr.pairs_sweep(skewed(sp, d), s, t, window=W_EVENTS)), bins),
        "pairs_bruteforce": (_bins(lambda sp, d: pr.pairs_bruteforce(skewed(sp, d), s, t)), bins),
    }
    for kind in ("rtree", "octree", "kdtree"):
        out[f"pairs_{kind}"] = (_partitioned("domain", "cylinder", kind), bins)
    for scheme in ("hash", "grid", "quadtree", "rtree", "domain"):
        for rep in ("ghost", "cylinder"):
            out[f"pairs_{rep}_{scheme}"] = (_partitioned(scheme, rep), bins)
    return out


@cache
def entries() -> dict:
    return core() | variants.entries() | surrounding.entries()
