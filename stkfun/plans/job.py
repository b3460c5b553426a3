"""A whole run: parameters, strategies, pairs, weights, K, simulations, decisions.

``planned`` asks the planner and runs what it says: points are clipped, a sample
is cut into leaves, centres are replicated to the leaves that their cylinders
meet, each leaf is searched by cells or by its local R-tree (which travels in its
compact form), weights come from a cache of distinct keys that the simulations
only read, and the bins of all pairs are summed up. ``plain`` compares all pairs
and weighs each of them. Both give the same surface.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.config import DistanceGrid, KJob, StudyWindow
from stkfun.functions.shared import settle
from stkfun.operators import partition as part
from stkfun.operators import weight_cache as wc
from stkfun.operators.estimate import estimate_k
from stkfun.operators.pairs import pairs_bruteforce, pairs_cells
from stkfun.operators.simulate import envelope, peak_scale, significance, simulated
from stkfun.plans import planner
from stkfun.plans.planner import StrategyPlan
from stkfun.sources.points import clip

#: Every strategy off, and every one on.
NONE = StrategyPlan(False, False, "none", "cylinder", False, False, 1)
ALL = StrategyPlan(True, True, "domain", "cylinder", True, True, 64)


@dataclass
class JobResult:
    plan: StrategyPlan
    surface: DataFrame
    simulations: DataFrame | None = None
    envelope: DataFrame | None = None
    decisions: DataFrame | None = None
    peak: DataFrame | None = None


def acquire(points: DataFrame, window: StudyWindow, grid: DistanceGrid, plan: StrategyPlan, keys: tuple[str, ...] = (), leaves: part.Leaves | None = None) -> DataFrame:
    """Ordered pairs by the plan's partitioner, index and codec."""
    if plan.partitioner == "none":
        if not plan.index:
            return pairs_cells(points, grid.s_max, grid.t_max, keys, window=window)
        leaves = part.leaves_grid(window, 1, 1, 1)
    placed = None if leaves is None else (part.assign_leaf(points, leaves, window), leaves)
    return part.pairs_partitioned(points, window, grid.s_max, grid.t_max, plan.parts, plan.partitioner, plan.replication, "rtree" if plan.index else "cells", keys=keys, compact=plan.codec, placed=placed)


def run_job(points: DataFrame, job: KJob, mode: str = "planned", strategies: StrategyPlan | None = None) -> JobResult:
    """The surface of ``job`` and, with ``job.m``, its simulations and decisions.

    ``strategies`` replaces the planner's choice; ``job.options`` may override
    single fields of it."""
    if mode not in ("planned", "plain"):
        raise ValueError(f"unknown mode {mode}")
    job.validate()
    window, grid = job.window, job.grid
    points = clip(points, window)
    chosen = NONE if mode == "plain" else strategies
    if chosen is None:
        chosen = planner.plan(points, window, grid, job.m)
        chosen = chosen if chosen.distribute else replace(chosen, partitioner="none")
    chosen = replace(chosen, **job.options)
    if job.correction == "border":
        return JobResult(chosen, estimate_k(points, window, grid, correction="border"))

    def pairs_of(rows: DataFrame, keys: tuple[str, ...] = (), leaves: part.Leaves | None = None) -> DataFrame:
        if mode == "plain":
            return pairs_bruteforce(rows, grid.s_max, grid.t_max, keys)
        return acquire(rows, window, grid, chosen, keys, leaves)

    leaves, cache = None, None
    if chosen.partitioner not in ("none", "hash"):
        leaves = part.spacetime_partition(points, window, chosen.parts, scheme=chosen.partitioner)[1]
        leaves = leaves if leaves.cover else None
    found = pairs_of(points, (), leaves)
    if chosen.cache and job.correction == "isotropic":
        found = settle(found, "jobpairs")
        cache = wc.fill(found, window).freeze()
    surface = estimate_k(points, window, grid, correction=job.correction, pairs=found, cache=cache)
    if not job.m:
        return JobResult(chosen, surface)
    observed = settle(surface, "jobsurface")
    sets = settle(simulated(points, window, job.simulation, job.m, job.seed), "jobsets")
    made = settle(estimate_k(sets, window, grid, correction=job.correction, pairs=pairs_of(sets, ("sim",), leaves), cache=cache, by="sim"), "jobsims")
    decisions = significance(observed, made)
    return JobResult(chosen, observed, made, envelope(made), decisions, peak_scale(decisions))


def job_surface(points: DataFrame, window: StudyWindow, grid: DistanceGrid, mode: str = "planned", strategies: StrategyPlan | None = None, **options) -> DataFrame:
    return run_job(points, KJob("points", window, grid, options=options), mode, strategies).surface.withColumns({n: F.round(n, 4) for n in ("k", "l")})
