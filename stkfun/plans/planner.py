"""Strategy choice: the published guidelines as rules."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.config import DistanceGrid, StudyWindow
from stkfun.functions.geometry import hash_uniform


@dataclass
class StrategyPlan:
    """What to switch on, and why."""

    index: bool
    cache: bool
    partitioner: str
    replication: str
    codec: bool
    distribute: bool
    parts: int
    reasons: list[str] = field(default_factory=list)


def mean_neighbours(points: DataFrame, window: StudyWindow, grid: DistanceGrid, fraction: float = 0.01, cap: int = 20_000) -> float:
    """Neighbours in the threshold cylinder, estimated from the loads of coarse cells of a hash sample."""
    n = points.count()
    share = min(1.0, max(fraction, min(1.0, cap / max(n, 1))))
    rows = points.where(hash_uniform("load", F.col("id")) < share)
    cells = rows.groupBy(F.floor(F.col("x") / (2 * grid.s_max)), F.floor(F.col("y") / (2 * grid.s_max)), F.floor(F.col("t0") / (2 * grid.t_max))).agg(F.count("*").alias("m"))
    got = cells.agg(F.sum(F.col("m") * (F.col("m") - 1)).alias("sq"), F.sum("m").alias("m")).first()
    load = (got.sq or 0) / max(got.m or 0, 1) / share
    return load * 3.141592653589793 / 4


def plan(points: DataFrame, window: StudyWindow, grid: DistanceGrid, m: int = 0, *, index_fraction: float = 1 / 32, cache_vertices: int = 100, distribute_above: int = 50_000, rows_per_leaf: int = 20_000, max_parts: int = 2_000, load_limit: float = 5_000.0) -> StrategyPlan:
    n = points.count()
    load = mean_neighbours(points, window, grid)
    small = grid.s_max < index_fraction * window.short_side and grid.t_max < index_fraction * window.period
    index = small and load <= load_limit
    parts = int(min(max_parts, max(1, -(-n * (1 + load / 100) // rows_per_leaf))))
    reasons = [
        f"thresholds are {'below' if small else 'not below'} {index_fraction:.4g} of the short side and the period; about {load:.0f} neighbours a point",
        f"{window.vertices} boundary vertices, weights are cached above {cache_vertices}",
        f"n = {n} is {'above' if n > distribute_above else 'at most'} {distribute_above}",
        f"{parts} leaves of about {rows_per_leaf} rows, weighed by their load; at most {max_parts}",
    ]
    if n <= 200_000:
        reasons.append("four nodes of 8 cores and 16 GB suffice at this size")
    return StrategyPlan(index, window.vertices > cache_vertices, "domain", "cylinder", True, n > distribute_above, parts, reasons)
