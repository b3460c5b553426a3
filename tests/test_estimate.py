"""Pairs, surfaces and simulations on small sets."""

import math

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from stkfun.config import HOUR, W_EVENTS, DistanceGrid, StudyWindow
from stkfun.functions.geometry import ellipse_ring, rect_ring
from stkfun.operators import estimate as est
from stkfun.operators import key_blocks as kb
from stkfun.operators import pairs as pr
from stkfun.operators import partition as part
from stkfun.operators import simulate as sim
from stkfun.operators import tabular as tab
from stkfun.operators import weight_cache as wc
from stkfun.config import KJob
from stkfun.plans import job, metrics, planner
from stkfun.sources import points as src

SQUARE = StudyWindow(0.0, 10.0, 0.0, 10.0, 0, 100 * HOUR)
GRID = DistanceGrid(1.0, 2, 10 * HOUR, 2)
SF = "/root/testdata/sf0.001"


def make(spark, rows):
    return spark.createDataFrame([(i, float(x), float(y), int(t), int(t), 1, None, "m") for i, x, y, t in rows], src.SCHEMA)


def keyset(df):
    return sorted((r.i, r.j) for r in df.select("i", "j").collect())


def test_tiny_sets(spark):
    for rows in ([], [(1, 5, 5, 0)]):
        p = make(spark, rows)
        assert keyset(pr.pairs_cells(p, 2.0, 20 * HOUR)) == []
        got = est.estimate_k(p, SQUARE, GRID).collect()
        assert all(r.k is None and r.pairs == 0 for r in got)
    twins = make(spark, [(1, 5, 5, HOUR), (2, 5, 5, HOUR)])
    got = pr.pairs_cells(twins, 2.0, 20 * HOUR).collect()
    assert sorted((r.i, r.j, r.d, r.u) for r in got) == [(1, 2, 0.0, 0), (2, 1, 0.0, 0)]
    k = {(r.si, r.ti): r for r in est.estimate_k(twins, SQUARE, GRID, include_zero=True).collect()}
    assert k[0, 0].pairs == 2 and k[0, 0].l is None and k[2, 2].pairs == 2


def test_thresholds_are_closed(spark):
    p = make(spark, [(1, 5, 5, 0), (2, 7, 5, 20 * HOUR), (3, 7.0001, 5, 0), (4, 5, 5, 20 * HOUR + 1)])
    for got in (pr.pairs_cells(p, 2.0, 20 * HOUR), pr.pairs_bruteforce(p, 2.0, 20 * HOUR), pr.pairs_sweep(p, 2.0, 20 * HOUR), pr.pairs_cellcode(p, 2.0, 20 * HOUR, SQUARE)):
        assert keyset(got) == [(1, 2), (2, 1), (2, 3), (2, 4), (3, 2), (4, 2)]
    assert len(keyset(pr.pairs_cells(p, 2.0, 20 * HOUR, half=True))) == 3


def test_null_places_and_times_are_dropped(spark):
    df = spark.createDataFrame([(1, 1.0, 1.0, 5), (2, None, 1.0, 5), (3, 1.0, 1.0, None)], "id long, x double, y double, t long")
    assert src.point_set(df, *map(F.col, ("id", "x", "y", "t"))).count() == 1


def test_partitioned_pairs_are_exactly_once(spark):
    p = src.events_skewed(spark, SF)
    want = keyset(pr.pairs_bruteforce(p, 5.0, 20 * HOUR))
    for scheme in ("hash", "grid", "quadtree", "rtree", "domain"):
        assert keyset(part.pairs_partitioned(p, W_EVENTS, 5.0, 20 * HOUR, 8, scheme)) == want
    for local in ("rtree", "octree", "kdtree"):
        assert keyset(part.pairs_partitioned(p, W_EVENTS, 5.0, 20 * HOUR, 8, "domain", "ghost", local)) == want


def test_no_nested_loop_in_the_cell_join(spark):
    p = src.events_skewed(spark, SF)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = pr.pairs_cells(p, 5.0, 20 * HOUR)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_uniform_points_give_the_reference(spark):
    p = src.generated(spark, 3000, W_EVENTS)
    g = DistanceGrid(25.0, 1, 180 * HOUR, 1)
    for correction, low, high in (("isotropic", 0.95, 1.05), ("translation", 0.95, 1.05), ("border", 0.9, 1.1), ("none", 0.7, 0.85)):
        r = est.estimate_k(p, W_EVENTS, g, correction=correction).first()
        assert low < r.k / (2 * math.pi * r.s**2 * r.t) < high, correction


def test_k_is_monotone_and_scales(spark):
    p = src.events_skewed(spark, SF)
    g = DistanceGrid(2.0, 3, 20 * HOUR, 3)
    k = {(r.si, r.ti): r.k for r in est.estimate_k(p, W_EVENTS, g).collect()}
    assert all(k[a, b] <= k[a + 1, b] and k[b, a] <= k[b, a + 1] for a in (1, 2) for b in (1, 2, 3))
    twice = p.withColumns({"x": F.col("x") * 2, "y": F.col("y") * 2})
    w2 = StudyWindow(0.0, 1200.0, 0.0, 200.0, W_EVENTS.t_start, W_EVENTS.t_end)
    big = {(r.si, r.ti): r.k for r in est.estimate_k(twice, w2, DistanceGrid(4.0, 3, 20 * HOUR, 3)).collect()}
    assert all(big[x] == pytest.approx(4 * k[x]) for x in k)


def test_polygon_equals_rectangle(spark):
    p = src.events_skewed(spark, SF)
    g = DistanceGrid(2.0, 2, 20 * HOUR, 2)
    a = est.estimate_k(p, W_EVENTS, g)
    b = est.estimate_k(p, W_EVENTS.with_ring(rect_ring(W_EVENTS, 40)), g, memo=True)
    assert est.max_abs_diff(a, b).first().max_abs_diff < 1e-3 * max(r.k for r in a.collect())


def test_permutation_is_a_bijection(spark):
    p = src.events_skewed(spark, SF)
    for ordered in (True, False):
        got = sim.simulate_permutation(p, 2, ordered=ordered)
        for s in (1, 2):
            one = got.where(F.col("sim") == s)
            assert sorted(r.t0 for r in one.collect()) == sorted(r.t0 for r in p.collect())
            assert sorted((r.id, r.x) for r in one.collect()) == sorted((r.id, r.x) for r in p.collect())
    boot = sim.simulate_bootstrap(p, 1)
    rows = {(r.x, r.y, r.t0) for r in p.collect()}
    assert boot.count() == p.count() and all((r.x, r.y, r.t0) in rows for r in boot.collect())


def test_bijection_of_every_size(spark):
    for n in (1, 2, 3, 5, 64, 65, 1000):
        got = spark.range(n).select(sim.bijection(F.col("id"), n, 7, F.lit(1)).alias("v")).collect()
        assert sorted(r.v for r in got) == list(range(n))


def test_intervals(spark):
    rows = [(1, 5, 5, 0, 10), (2, 6, 5, 8, 9), (3, 5, 6, 14, 40), (4, 5, 5, 100, 101), (5, 9, 9, 0, 200)]
    p = spark.createDataFrame([(i, float(x), float(y), a, b, 1, None, "m") for i, x, y, a, b in rows], src.SCHEMA)
    for t in (0, 3, 4, 5, 60, 1000):
        assert sorted((r.i, r.j, r.u) for r in pr.pairs_intervals(p, 2.0, t).collect()) == sorted((r.i, r.j, r.u) for r in pr.pairs_bruteforce(p, 2.0, t, mode="interval").collect())


def test_half_pairs_give_the_same_surface(spark):
    p = src.events_skewed(spark, SF)
    g = DistanceGrid(2.0, 3, 20 * HOUR, 3)
    for ring in ((), tuple(ellipse_ring(30, rx=320.0, ry=70.0))):
        w = W_EVENTS.with_ring(ring)
        for correction in ("isotropic", "translation", "none"):
            a = est.estimate_k(p, w, g, correction=correction)
            b = est.estimate_k(p, w, g, correction=correction, pairs=pr.pairs_bruteforce(p, g.s_max, g.t_max))
            assert sorted(map(tuple, a.select("si", "ti", "pairs", "k").collect())) == sorted(map(tuple, b.select("si", "ti", "pairs", "k").collect()))
    assert est.guarded(pr.pairs_cells(p, 5.0, 20 * HOUR), W_EVENTS, 1.5).first().capped > 0


def test_cstr_in_a_ring_has_n_points_inside(spark):
    w = W_EVENTS.with_ring(ellipse_ring(20))
    thin = W_EVENTS.with_ring([(0.0, 0.0), (600.0, 99.0), (600.0, 100.0), (0.0, 1.0)])
    for ring, n in ((w, 500), (thin, 1000), (w, 0)):
        got = sim.simulate_cstr(spark, n, ring, 2)
        assert {r["count"] for r in got.groupBy("sim").count().collect()} == ({n} if n else set())
        assert src.clip(got, ring).count() == 2 * n


def test_cache_is_read_only_and_equal(spark):
    p = src.events_skewed(spark, SF)
    pairs = pr.pairs_cells(p, 5.0, 20 * HOUR, window=W_EVENTS)
    cache = wc.fill(pairs, W_EVENTS).freeze()
    before = cache.space.count()
    other = pr.pairs_cells(sim.simulate_permutation(p, 1), 5.0, 20 * HOUR, ("sim",), window=W_EVENTS)
    r = wc.cache_stats(other, cache, ("sim",)).first()
    assert r.space_hits <= r.lookups and cache.space.count() == before
    got = wc.looked_up(pairs, cache)
    direct = est.pair_weight(W_EVENTS)
    assert got.where((F.abs(F.col("w") - direct) > 1e-9) | ~F.col("s_hit") | ~F.col("t_hit")).count() == 0
    small = wc.WeightCache(W_EVENTS, cache.space.limit(0), cache.time.limit(0))
    assert wc.looked_up(pairs, small).where((F.abs(F.col("w") - direct) > 1e-9) | F.col("s_hit")).count() == 0


def test_knn_and_neighbours(spark):
    p = make(spark, [(1, 1, 1, 0), (2, 2, 1, 0), (3, 4, 1, 0), (4, 9, 9, HOUR)])
    got = {(r.i, r.rank): r.j for r in pr.knn(p, 2, 1.0, 0.5).collect()}
    assert got[1, 1] == 2 and got[1, 2] == 3 and got[4, 1] == 3 and len(got) == 8
    apart = make(spark, [(1, 0, 0, 0), (2, 1, 0, 0), (3, 9, 9, 0), (4, 9.5, 9, 99 * HOUR)])
    assert pr.knn(apart, 3, 1.0, 5.0).count() == 12 and pr.knn(apart, 5, 1.0, 60.0).count() == 12
    counts = {r.id: r.n for r in pr.neighbour_count(p, 1.5, HOUR).collect()}
    assert counts == {1: 1, 2: 1, 3: 0, 4: 0}


def test_planner_rules(spark):
    p = src.events_skewed(spark, SF)
    near = planner.plan(p, W_EVENTS, DistanceGrid(1.0, 2, HOUR, 20))
    far = planner.plan(p, W_EVENTS.with_ring(ellipse_ring(200)), DistanceGrid(5.0, 5, 36 * HOUR, 5))
    assert near.index and not near.cache and not near.distribute
    assert not far.index and far.cache and far.partitioner == "domain" and far.reasons


def test_job_gives_the_same_results_with_and_without_strategies(spark):
    p = src.events_skewed(spark, SF)
    g = DistanceGrid(2.5, 2, 20 * HOUR, 2)
    rows = lambda df, *c: sorted(map(tuple, df.select(*c).collect()))
    plain = job.run_job(p, KJob("events", W_EVENTS, g, simulation="permutation", m=3), "plain")
    full = job.run_job(p, KJob("events", W_EVENTS, g, simulation="permutation", m=3), strategies=job.ALL)
    planned = job.run_job(p, KJob("events", W_EVENTS, g, options={"index": True}))
    assert planned.plan.index and planned.simulations is None
    for other in (full, planned):
        assert rows(plain.surface, "si", "ti", "pairs", "k") == rows(other.surface, "si", "ti", "pairs", "k")
    assert rows(plain.simulations, "sim", "si", "ti", "k") == rows(full.simulations, "sim", "si", "ti", "k")
    assert rows(plain.decisions, "si", "ti", "p", "verdict") == rows(full.decisions, "si", "ti", "p", "verdict")
    assert full.peak.count() == 1
    with pytest.raises(ValueError):
        job.run_job(p, KJob("events", W_EVENTS, g), "fast")


def test_suggested_thresholds_stay_within_limits():
    for n in (10, 10_000, 10_000_000):
        DistanceGrid.suggest(W_EVENTS, n).validate(W_EVENTS)
    assert DistanceGrid.suggest(W_EVENTS, 10).s_max >= DistanceGrid.suggest(W_EVENTS, 10_000_000).s_max


def test_domain_leaves_cover_every_point_evenly(spark):
    p = src.events_skewed(spark, SF)
    r = part.partition_stats(p, W_EVENTS, 5.0, 20 * HOUR, 8, "domain").first()
    assert r.uncovered == 0 and r.max_over_mean < 2.5 and 1 <= r.cylinder_factor <= r.ghost_factor


def test_shuffle_and_memory_are_measured(spark):
    got = metrics.measured(spark, lambda: spark.range(100_000).groupBy((F.col("id") % 1000).alias("k")).count())
    assert got["shuffle_write_mb"] > 0 and got["shuffle_read_mb"] > 0 and got["stages"] >= 1 and got["spill_mb"] == 0
    assert metrics.measured(spark, lambda: spark.range(10))["shuffle_write_mb"] == 0
    assert metrics.acceleration(6.0, 2.0) == 3.0


def test_pair_searches_broadcast_no_side_of_points(spark):
    """A centre side that visits 27 cells is as large as its files only in the planner's eyes."""
    p = src.events_skewed(spark, SF)
    a = (p, 5.0, 20 * HOUR)
    found = [pr.pairs_cells(*a, window=W_EVENTS), pr.pairs_cells(*a, window=W_EVENTS, half=True, salt=3), pr.pairs_cellcode(*a, W_EVENTS), pr.pairs_sweep(*a, window=W_EVENTS), pr.pairs_intervals(*a, window=W_EVENTS)]
    for df in found:
        df.collect()
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "BroadcastExchange" not in plan
    line = est.estimate_k_time(p, W_EVENTS, DistanceGrid(1.0, 5, 4 * HOUR, 5))
    assert "SortMergeJoin [slice" in line._jdf.queryExecution().executedPlan().toString()


def test_points_beyond_the_window_have_a_leaf(spark):
    """They are counted in the leaf of the nearest face, and no pair of theirs is lost."""
    p = make(spark, [(1, 1, 1, HOUR), (2, 9, 9, HOUR), (3, 10.5, 9, HOUR), (4, 12.4, 9, HOUR), (5, -3, 1, 2 * HOUR), (6, -2, 2, 101 * HOUR)])
    got = part.partition_stats(p, SQUARE, 2.0, 20 * HOUR, 8, "grid").first()
    assert (got.leaves, got.rows_max, got.empty, got.uncovered) == (8, 3, 5, 0)
    want = keyset(pr.pairs_cells(p, 2.0, 20 * HOUR))
    assert (3, 4) in want
    for scheme in ("grid", "quadtree", "domain"):
        for replication in ("cylinder", "ghost"):
            assert keyset(part.pairs_partitioned(p, SQUARE, 2.0, 20 * HOUR, 8, scheme, replication)) == want


def test_time_only_counts_equal_pairs(spark):
    """Also of equal times, and of points at and beyond the period's ends; the weight sum may exceed a long."""
    hours = [0, 0, 0, 1, 3, 7.5, 7.5, 40, 59, 61, 96, 99, 99.5, 100, 103, -2, 30, 30.25]
    p = make(spark, [(i, 1, 1, int(h * HOUR)) for i, h in enumerate(hours)])
    grid = DistanceGrid(1.0, 1, 5 * HOUR, 4)
    got = {r.ti: (r.pairs, r.k) for r in est.estimate_k_time(p, SQUARE, grid).collect()}
    plain = {r.ti: r.k for r in est.estimate_k_time(p, SQUARE, grid, corrected=False).collect()}
    ts = [int(h * HOUR) for h in hours]
    for ti in range(1, 5):
        near = [(a, abs(a - b)) for i, a in enumerate(ts) for j, b in enumerate(ts) if i != j and abs(a - b) <= ti * grid.t_step]
        w = sum(1 if a - u >= 0 and a + u <= SQUARE.t_end else 2 for a, u in near)
        pairs = len(ts) * (len(ts) - 1)
        assert got[ti][0] == len(near) and math.isclose(got[ti][1], 100 / pairs * w) and math.isclose(plain[ti], 100 / pairs * len(near))
    same = make(spark, [(0, 1, 1, 50 * HOUR)]).drop("id").crossJoin(spark.range(200_000))
    line = est.estimate_k_time(same, SQUARE, grid).first()
    assert line.pairs == 200_000 * 199_999 and math.isclose(line.k, 100.0)
    assert est.estimate_k_time(p.limit(0), SQUARE, grid).where("pairs = 0 and k is null").count() == 4


def test_space_only_counts_each_pair_from_both_ends(spark):
    p = make(spark, [(i, (i * 7) % 11, (i * 5) % 9, i * HOUR) for i in range(40)])
    got = {r.si: (r.pairs, r.k) for r in est.estimate_k_space(p, StudyWindow(0.0, 10.0, 0.0, 8.0), DistanceGrid(1.0, 3, HOUR, 1), corrected=False).collect()}
    xy = [((i * 7) % 11, (i * 5) % 9) for i in range(40)]
    for si in (1, 2, 3):
        near = sum(math.dist(a, b) <= si for i, a in enumerate(xy) for j, b in enumerate(xy) if i != j)
        assert got[si][0] == near and math.isclose(got[si][1], 80 / (40 * 39) * near)


def test_wide_sums_exceed_a_long(spark):
    got = spark.range(5).select((F.lit(2**62) - F.col("id")).alias("w"), (-F.col("id")).alias("v")).agg(est.wide_sum(F.col("w")).alias("w"), est.wide_sum(F.col("v")).alias("v")).first()
    assert (int(got.w), int(got.v)) == (5 * 2**62 - 10, -10)


def test_nearest_neighbours_start_where_few_pairs_are_ranked(spark):
    """Dense places begin with a small radius; those apart are reached by doubling, ties go by id."""
    rows = [(i, (i % 40) * 0.01, (i // 40) * 0.01, 0) for i in range(1600)] + [(1600, 2, 1, 0), (1601, 2, 1, 0), (1602, 1, 1, HOUR)]
    p = make(spark, rows)
    assert pr.first_radius(p, 3, 1.0, 10.0) < 0.05
    assert pr.first_radius(make(spark, [(i, 1, 1, 0) for i in range(50)]), 3, 1.0, 10.0) == 10.0
    assert pr.first_radius(p.limit(0), 3, 1.0, 10.0) == 10.0
    got = {(r.i, r.rank): (r.j, r.r) for r in pr.knn(p, 3, 1.0, 10.0).collect()}
    assert len(got) == 3 * 1603
    for i in (0, 41, 820, 1599, 1600, 1602):
        a = rows[i]
        want = sorted((math.sqrt((a[1] - b[1]) ** 2 + (a[2] - b[2]) ** 2 + ((a[3] - b[3]) / HOUR) ** 2), b[0]) for b in rows if b[0] != i)[:3]
        for rank, (r, _) in enumerate(want, 1):
            assert math.isclose(got[i, rank][1], r, abs_tol=1e-9)


def test_hits_are_counted_where_pairs_are_found(spark):
    """The same counts as by joining pairs with the cache, with copies and tolerances; pairs are not shuffled."""
    rows = [(i, float(i * 7 % 40), float(i * 11 % 30), (i * 13 % 50) * HOUR) for i in range(300)]
    rows += [(1000 + i, x, y, t) for i, x, y, t in rows[:60]]
    points = spark.createDataFrame([(i, x, y, t, t) for i, x, y, t in rows], "id long, x double, y double, t0 long, t1 long")
    sets = points.withColumn("sim", F.lit(1)).unionByName(points.withColumns({"t0": F.col("t0") + F.col("id") % 9 * HOUR, "sim": F.lit(2)}))
    for tols in ((None, None), (2.0, 0.5)):
        cache = wc.fill(pr.pairs_cells(points.where("id % 2 = 0"), 5.0, 6 * HOUR, window=W_EVENTS), W_EVENTS, *tols)
        want = wc.cache_stats(pr.pairs_cells(sets, 5.0, 6 * HOUR, ("sim",), window=W_EVENTS), cache, ("sim",))
        got = wc.search_stats(sets, cache, 5.0, 6 * HOUR, ("sim",))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and all(0 < r.space_hits < r.lookups for r in got.collect())
        last = next(line for line in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if " Join " in line or line.strip(" +-:").startswith("Join "))
        assert "c_id" in last and "q_id" in last  # nothing is joined after the pairs


def heavy(spark):
    """Two places of 70,000 coincident points each: 4.9e9 pairs at distance 1, 4.9e9 at 0 in each."""
    return spark.createDataFrame([(i, 5.0 + i, 5.0, 50 * HOUR, 50 * HOUR, 70_000, None, "m") for i in (0, 1)], src.SCHEMA)



def test_unweighted_pairs_sum_beyond_a_long(spark):
    got = est.estimate_k(heavy(spark), SQUARE, GRID, correction="none", mult="mult").where("si = 2 and ti = 2").first()
    assert got.pairs == 140_000 * 139_999 and math.isclose(got.k, 100 * 100)


def scattered(spark):
    """Dense and sparse places, some of several points, times that recur."""
    rows = [(i, 20 + (i * 37 % 400) / 100, 20 + (i * 53 % 300) / 100, (i * 7 % 96) * HOUR // 4) for i in range(600)]
    rows += [(1000 + i, 100 + i * 7 % 9, 50 + i * 5 % 7, i * 5 % 24 * HOUR) for i in range(40)]
    rows += [(2000 + i, x, y, t + (i % 3) * HOUR) for i, x, y, t in rows[:90]] + [(3000, -3.0, -0.5, 0), (3001, -1.25, 0.0, -HOUR), (3002, 300, 50, 0)]
    return make(spark, rows)


def test_tolerance_keys_are_found_in_blocks(spark):
    """The keys of all pairs; pairs are not shuffled, and a place that shows every distance is left."""
    p, key = scattered(spark), lambda df: sorted(map(tuple, df.collect()))
    got = kb.space_cache(p, W_EVENTS, 2.0, 20 * HOUR, 1.0, 0.5)
    assert key(got) == key(wc.space_cache(pr.pairs_cells(p, 2.0, 20 * HOUR, window=W_EVENTS), W_EVENTS, 1.0, 0.5))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "FlatMapGroupsInArrow" in plan
    v = np.array([0.0, 0.125, 0.1249999999999999, 0.375, 4.999])
    assert list(kb.rounded_steps(v, 0.25)) == [0, 1, 0, 2, 20] and kb.rounded_steps(np.array([0.49999999999999994]), 1.0)[0] == 0


def test_keys_are_counted_in_blocks(spark, monkeypatch):
    """Distinct keys as by sets of all pairs, also when values of a key are thinned on the way; pairs are not shuffled."""
    p = scattered(spark)
    pairs = pr.pairs_cells(p, 2.0, 20 * HOUR, window=W_EVENTS)
    got = kb.key_counts(p, W_EVENTS, 2.0, 20 * HOUR)
    want = wc.key_counts(pairs).first()
    assert got.first() == want and want.space_keys < want.pairs and want.time_keys < want.pairs
    assert tuple(kb.key_counts(p.limit(0), W_EVENTS, 2.0, HOUR).first()) == (0, 0, 0, 0, 0)
    joins = [line for line in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join" in line]
    assert len(joins) == 1 and "Cross" in joins[0] or "Join Inner" in joins[0]  # of the two single rows
    table = pa.Table.from_pandas(p.select("id", "x", "y", "t0").toPandas().assign(own=True))
    whole = kb.counting(2.0, 20 * HOUR, ("t0",))(table).to_pylist()
    monkeypatch.setattr(kb, "GATHERED", 10)
    assert kb.counting(2.0, 20 * HOUR, ("t0",))(table).to_pylist() == whole and whole[0]["keys"] == want.time_keys


def test_surfaces_sum_more_weight_than_a_long_holds(spark):
    got = est.estimate_k(heavy(spark), SQUARE, GRID, mult="mult").where("si = 1 and ti = 1").first()
    assert got.pairs == 140_000 * 139_999 and math.isclose(got.k, 100 * 100)
    hist = spark.createDataFrame([(i, 1, 1, 8 * 10**18) for i in (0, 1)], "si int, ti int, pairs long, wfix long")
    assert int(est.cumulate(hist, GRID).agg(F.max("wfix")).first()[0]) == 16 * 10**18


def test_translation_weights_sum_beyond_a_long(spark):
    got = est.estimate_k(heavy(spark), SQUARE, GRID, correction="translation", mult="mult").where("si = 1 and ti = 1").first()
    m = 70_000
    assert math.isclose(got.k, 1e4 * (2 * m * (m - 1) + 2 * m * m / 0.9) / (2 * m * (2 * m - 1)), rel_tol=1e-8)


def test_matrix_of_a_surface_beyond_a_long(spark):
    got = {r["si"]: r for r in tab.surface_matrix(est.estimate_k(heavy(spark), SQUARE, GRID, mult="mult"), 2).collect()}
    for si in (1, 2):
        for ti in (1, 2):
            assert math.isclose(got[si][str(ti)], math.sqrt(1e4 / (2 * math.pi * 10 * ti)) - si)
