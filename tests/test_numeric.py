"""Checks without Spark: weights, indexes, codecs, leaves, grids."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from stkfun.config import W_EVENTS, DistanceGrid, KJob, StudyWindow
from stkfun.functions.geometry import ellipse_ring, inside_np, l_ring, rect_ring, ring_weights
from stkfun.operators.codec import decode_index, encode_index
from stkfun.operators.local_index import BUILDERS
from stkfun.operators.partition import Leaves, leaves_domain_tree, leaves_grid, leaves_quadtree
from stkfun.sources.points import ring_from_wkt

SQUARE = StudyWindow(0.0, 10.0, 0.0, 10.0, 0, 1000)


def weight(x, y, d, ring, **kw):
    return ring_weights(np.array([x], float), np.array([y], float), np.array([d], float), np.array(ring, float), **kw)[0]


@pytest.mark.parametrize("early", [True, False])
@pytest.mark.parametrize("vertices", [4, 10, 57])
def test_closed_form_weights(vertices, early):
    ring = rect_ring(SQUARE, vertices)
    assert len(ring) == vertices
    assert weight(5, 5, 1, ring, early_exit=early) == pytest.approx(1)
    assert weight(5, 1e-9, 1, ring, early_exit=early) == pytest.approx(2, abs=1e-6)
    assert weight(1e-9, 1e-9, 1, ring, early_exit=early) == pytest.approx(4, abs=1e-6)
    assert weight(5, 5, 0, ring, early_exit=early) == 1


def test_weights_against_sampled_circles():
    rng = np.random.default_rng(1)
    for ring in (ellipse_ring(85), ellipse_ring(30, star=0.6), l_ring(W_EVENTS)):
        r = np.array(ring)
        p = np.stack([rng.uniform(20, 580, 60), rng.uniform(6, 94, 60)], 1)
        p = p[inside_np(p[:, 0], p[:, 1], r)]
        d = rng.uniform(1, 30, len(p))
        got = ring_weights(p[:, 0], p[:, 1], d, r)
        a = (np.arange(20000) + 0.5) / 20000 * 2 * np.pi
        for k in range(len(p)):
            f = inside_np(p[k, 0] + d[k] * np.cos(a), p[k, 1] + d[k] * np.sin(a), r).mean()
            assert 1 / got[k] == pytest.approx(f, abs=2e-3)


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10**6), st.integers(0, 200), st.sampled_from(sorted(BUILDERS)))
def test_indexes_find_all_pairs(seed, n, kind):
    rng = np.random.default_rng(seed)
    p = np.stack([rng.exponential(3, n), rng.integers(0, 5, n).astype(float), rng.integers(0, 50, n).astype(float)], 1)
    tree = BUILDERS[kind](p, 4 if kind != "kdtree" else 1)
    if not n:
        return
    for tight in (True, False):
        got = {(int(a), int(b)) for x, y in tree.query(p, p, 1.5, 7, tight, block=64) for a, b in zip(x, y)}
        d2 = (p[:, None, 0] - p[None, :, 0]) ** 2 + (p[:, None, 1] - p[None, :, 1]) ** 2
        want = {tuple(map(int, w)) for w in np.argwhere((d2 <= 1.5 * 1.5) & (abs(p[:, None, 2] - p[None, :, 2]) <= 7))}
        assert got == want


def test_index_codec_round_trip():
    p = np.random.default_rng(0).uniform(0, 10, (500, 3))
    tree = BUILDERS["rtree"](p, 8)
    back = decode_index(encode_index(tree))
    one = sorted((int(a), int(b)) for x, y in tree.query(p, p, 1, 1) for a, b in zip(x, y))
    two = sorted((int(a), int(b)) for x, y in back.query(p, p, 1, 1) for a, b in zip(x, y))
    assert one == two and back.stats()["nodes"] == tree.stats()["nodes"] and back.height == tree.height
    with pytest.raises(ValueError):
        decode_index(b"\x01" + encode_index(tree)[1:])


@pytest.mark.parametrize("build", ["domain", "grid", "quadtree", "domain4"])
def test_leaves_tile_the_window(build):
    rng = np.random.default_rng(3)
    p = np.stack([np.minimum(rng.exponential(60, 3000), 599), rng.integers(0, 100, 3000).astype(float), rng.uniform(W_EVENTS.t_start, W_EVENTS.t_end, 3000)], 1)
    leaves: Leaves = {"domain": lambda: leaves_domain_tree(p, W_EVENTS, 32), "domain4": lambda: leaves_domain_tree(p, W_EVENTS, 32, 4), "grid": lambda: leaves_grid(W_EVENTS, 3, 3, 3), "quadtree": lambda: leaves_quadtree(p, W_EVENTS, 100)}[build]()
    volume = (leaves.hi - leaves.lo).prod(1).sum()
    assert volume == pytest.approx(W_EVENTS.area * W_EVENTS.period, rel=1e-9)
    top = np.array([600.0, 100.0, float(W_EVENTS.t_end)])
    home = leaves.home(np.concatenate([p, leaves.lo, [[600.0, 100.0, float(W_EVENTS.t_end)]]]), top)
    assert (home >= 0).all()
    if build == "domain":
        counts = np.bincount(home[:3000], minlength=len(leaves))
        assert counts.max() / counts.mean() < 2.5
    ghost = sum(len(i) for i, _ in leaves.meets(p, 5.0, 7.2e10, True))
    cylinder = sum(len(i) for i, _ in leaves.meets(p, 5.0, 7.2e10, False))
    assert len(p) <= cylinder <= ghost


def test_grids_and_jobs():
    g = DistanceGrid.from_fraction(W_EVENTS, 1 / 4)
    assert g.validate(W_EVENTS) is g
    with pytest.raises(ValueError):
        DistanceGrid(30.0, 1, 1, 1).validate(W_EVENTS)
    with pytest.warns(UserWarning):
        DistanceGrid(30.0, 1, 1, 1).validate(W_EVENTS, "warn")
    KJob("events", W_EVENTS, g).validate()
    with pytest.raises(ValueError):
        KJob("events", W_EVENTS, g, correction="?").validate()
    assert ring_from_wkt("POLYGON ((0 0, 4 0, 4 3, 0 0))") == ((0, 0), (4, 0), (4, 3))
    assert StudyWindow.from_ring([(0, 0), (4, 0), (4, 3)], "2024-01-01", "2024-01-02").area == 6


def test_rectangle_outline_equals_its_formula_outside_and_where_circles_touch(spark):
    from stkfun.config import W_EVENTS
    from stkfun.functions import geometry as geo

    rows = spark.createDataFrame([(3.22, 95.0, 5.0), (601.5, 50.0, 5.0), (604.0, 3.0, 5.0), (700.0, 50.0, 5.0), (5.0, 50.0, 5.0), (1.0, 1.0, 0.0)], "x double, y double, d double")
    for memo in (False, True):
        got = rows.select(geo.w_space_polygon(geo.rect_ring(W_EVENTS, 9), memo=memo, rect=W_EVENTS)("x", "y", "d").alias("w"), geo.w_space_rect(rows.x, rows.y, rows.d, W_EVENTS).alias("v")).collect()
        assert all(abs(r.w - r.v) < 1e-9 for r in got), got
