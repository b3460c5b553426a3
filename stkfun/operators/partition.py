"""Space-time partitioning and replication.

Leaves are half-open boxes; a point's home leaf is a function of its place and
time, so pairs are found exactly once: where the neighbour lives (cylinder
replication) or where the centre lives (ghost buffers).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.config import StudyWindow
from stkfun.functions.geometry import hash_uniform
from stkfun.operators.codec import decode_index, encode_index
from stkfun.operators.local_index import BUILDERS, _tiles
from stkfun.operators.pairs import cell, finished, near, same, sides, time_cell

SAMPLE_CAP = 1_000_000
_FAN = 8


@dataclass
class Leaves:
    """Boxes of all leaves (time in µs as floats); ``cover``: they tile the window."""

    lo: np.ndarray
    hi: np.ndarray
    cover: bool = True
    nodes: list | None = None

    def __len__(self) -> int:
        return len(self.lo)

    def outward(self, window: StudyWindow) -> Leaves:
        """The same leaves with those at the window's faces open to the outside, so that
        points beyond it have the home of the nearest face and meet what they are near."""
        low, top = _corner(window)
        return Leaves(np.where(self.lo <= low, -np.inf, self.lo), np.where(self.hi >= top, np.inf, self.hi), self.cover, self.nodes)

    def _levels(self) -> list[tuple[np.ndarray, np.ndarray]]:
        """Boxes of a tree over the leaves in their order, top first: each node covers the next ``_FAN`` below."""
        out = [(self.lo, self.hi)]
        while len(out[-1][0]) > _FAN:
            lo, hi = out[-1]
            cuts = np.arange(0, len(lo), _FAN)
            out.append((np.minimum.reduceat(lo, cuts), np.maximum.reduceat(hi, cuts)))
        return out[::-1]

    def _descend(self, p: np.ndarray, meets) -> tuple[np.ndarray, np.ndarray]:
        """(point, leaf) of the leaves reached through boxes that ``meets`` accepts; points in order."""
        levels = self._levels()
        top = len(levels[0][0])
        who, node = np.repeat(np.arange(len(p)), top), np.tile(np.arange(top), len(p))
        for depth, (lo, hi) in enumerate(levels):
            ok = meets(lo[node], hi[node], p[who])
            who, node = who[ok], node[ok]
            if depth + 1 < len(levels):
                many = np.minimum(_FAN, len(levels[depth + 1][0]) - node * _FAN)
                node = np.repeat(node * _FAN - np.cumsum(many) + many, many) + np.arange(many.sum())
                who = np.repeat(who, many)
        return who, node

    def home(self, p: np.ndarray, top: np.ndarray) -> np.ndarray:
        """Home leaf of each point, -1 where no leaf covers it; faces at the top belong to the last box."""
        out = np.full(len(p), -1, np.int64)
        for a in range(0, len(p), 4096):
            who, leaf = self._descend(p[a : a + 4096], lambda lo, hi, q: ((q >= lo) & (q <= hi)).all(1))
            q, lo, hi = p[a + who], self.lo[leaf], self.hi[leaf]
            inside = ((q >= lo) & ((q < hi) | ((hi >= top) & (q <= hi)))).all(1)
            first, at = np.unique(who[inside], return_index=True)
            out[a + first] = leaf[inside][at]
        return out

    def meets(self, p: np.ndarray, s: float, t: float, ghost: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(point index, leaf) of every leaf that the point's cylinder, or its buffer box, meets."""

        def near(lo: np.ndarray, hi: np.ndarray, q: np.ndarray) -> np.ndarray:
            gap = np.maximum(np.maximum(lo - q, q - hi), 0)
            space = (gap[:, 0] <= s) & (gap[:, 1] <= s) if ghost else gap[:, 0] ** 2 + gap[:, 1] ** 2 <= s * s
            return space & (gap[:, 2] <= t)

        for a in range(0, len(p), 4096):
            who, leaf = self._descend(p[a : a + 4096], near)
            yield who + a, leaf


def _corner(window: StudyWindow) -> tuple[np.ndarray, np.ndarray]:
    return np.array([window.x0, window.y0, float(window.t_start)]), np.array([window.x1, window.y1, float(window.t_end)])


def sample_points(points: DataFrame, fraction: float = 0.01, floor: int = 0, cap: int = SAMPLE_CAP, n: int | None = None) -> np.ndarray:
    """A sample by id hash, the same whatever the layout: at least ``floor`` rows
    if there are so many, about ``cap`` at most (both bounds on driver memory)."""
    n = points.count() if n is None else n
    share = min(1.0, max(fraction, floor / max(1, n)), cap / max(1, n))
    h = F.pmod(F.xxhash64(F.lit("sample"), "id"), F.lit(1 << 30)) < int(share * (1 << 30)) + (share >= 1)
    got = points.where(h).select("x", "y", F.col("t0").cast("double").alias("t"), "id").toArrow().sort_by("id")
    return np.stack([got.column(c).to_numpy() for c in ("x", "y", "t")], 1) if got.num_rows else np.zeros((0, 3))


def leaves_grid(window: StudyWindow, nx: int, ny: int, nt: int) -> Leaves:
    lo, hi = _corner(window)
    edges = [np.linspace(lo[k], hi[k], n + 1) for k, n in enumerate((nx, ny, nt))]
    a = np.array(np.meshgrid(*[e[:-1] for e in edges], indexing="ij")).reshape(3, -1).T
    b = np.array(np.meshgrid(*[e[1:] for e in edges], indexing="ij")).reshape(3, -1).T
    return Leaves(a, b)


def leaves_quadtree(sample: np.ndarray, window: StudyWindow, max_items: int, max_depth: int = 8) -> Leaves:
    """The window halved on all axes while a cube holds more than ``max_items`` of the sample."""
    lo, hi = _corner(window)
    out, todo = [], [(sample, lo, hi, 0)]
    while todo:
        rows, a, b, depth = todo.pop(0)
        if len(rows) <= max_items or depth >= max_depth:
            out.append((a, b))
            continue
        mid = (a + b) / 2
        code = ((rows >= mid) * np.array([1, 2, 4])).sum(1)
        for o in range(8):
            up = np.array([o & 1, o & 2, o & 4], bool)
            todo.append((rows[code == o], np.where(up, mid, a), np.where(up, b, mid), depth + 1))
    return Leaves(np.array([o[0] for o in out]), np.array([o[1] for o in out]))


def leaves_rtree(sample: np.ndarray, parts: int) -> Leaves:
    """Boxes of sort-tile-recursive tiles of the sample: even, but they may miss points."""
    groups = _tiles(sample, np.arange(len(sample)), max(1, -(-len(sample) // parts)))
    return Leaves(np.array([sample[g].min(0) for g in groups]), np.array([sample[g].max(0) for g in groups]), cover=False)


def leaves_domain_tree(sample: np.ndarray, window: StudyWindow, parts: int, max_children: int = 2) -> Leaves:
    """The window itself cut at sample medians (quantiles for more children), axes in
    turn; an axis without a strict cut is skipped. Leaves are numbered depth first."""
    lo, hi = _corner(window)
    target = max(1, -(-len(sample) // max(1, parts)))
    out, nodes = [], []

    def grow(rows: np.ndarray, a: np.ndarray, b: np.ndarray, depth: int) -> None:
        nodes.append((a, b, depth))
        if len(rows) > target:
            for axis in [(depth + k) % 3 for k in range(3)]:
                cuts = np.unique(np.quantile(rows[:, axis], np.arange(1, max_children) / max_children, method="higher"))
                cuts = cuts[(cuts > a[axis]) & (cuts < b[axis])]
                edges = np.concatenate([[a[axis]], cuts, [b[axis]]])
                bins = np.searchsorted(cuts, rows[:, axis], "right")
                if len(cuts) and np.bincount(bins, minlength=len(cuts) + 1).max() < len(rows):
                    for k in range(len(edges) - 1):
                        low, high = a.copy(), b.copy()
                        low[axis], high[axis] = edges[k], edges[k + 1]
                        grow(rows[bins == k], low, high, depth + 1)
                    return
        out.append((a, b))

    grow(sample, lo, hi, 0)
    return Leaves(np.array([o[0] for o in out]), np.array([o[1] for o in out]), nodes=nodes)


def hash_leaf(parts: int) -> Column:
    return F.floor(hash_uniform("leaf", F.col("id")) * parts).cast("int")


def leaves_hash(points: DataFrame, parts: int) -> Leaves:
    """Bounding boxes of partitions by id hash (baseline): they overlap."""
    got = points.groupBy(hash_leaf(parts).alias("leaf")).agg(*[f(c).alias(f"{f.__name__}_{c}") for c in ("x", "y", "t0") for f in (F.min, F.max)]).toPandas().set_index("leaf").reindex(range(parts))
    got = got.fillna(np.inf)
    return Leaves(got[["min_x", "min_y", "min_t0"]].to_numpy(float), got[["max_x", "max_y", "max_t0"]].to_numpy(float), cover=False)


def _batch_points(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(float) for c in ("x", "y", "t0")], 1)


def assign_leaf(points: DataFrame, leaves: Leaves, window: StudyWindow) -> DataFrame:
    """``points`` with their home leaf (-1: no leaf covers it)."""
    top = _corner(window)[1]

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(leaves.home(_batch_points(b), top).astype(np.int32))], [*b.schema.names, "leaf"])

    return points.mapInArrow(run, ", ".join(f"{n} {t}" for n, t in points.dtypes) + ", leaf int")


def assign_hash(points: DataFrame, parts: int) -> DataFrame:
    return points.withColumn("leaf", hash_leaf(parts))


def replicate(points: DataFrame, leaves: Leaves, s: float, t: float, ghost: bool = False) -> DataFrame:
    """A row for each leaf that a point's cylinder (or buffer box) meets, in ``leaf``."""

    def run(batches):
        for b in batches:
            for i, leaf in leaves.meets(_batch_points(b), s, float(t), ghost):
                part = b.take(pa.array(i))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(leaf.astype(np.int32))], [*b.schema.names, "leaf"])

    return points.mapInArrow(run, ", ".join(f"{n} {k}" for n, k in points.dtypes) + ", leaf int")


def replicate_cylinders(points: DataFrame, leaves: Leaves, s: float, t: float) -> DataFrame:
    return replicate(points, leaves, s, t)


def replicate_ghost(points: DataFrame, leaves: Leaves, s: float, t: float) -> DataFrame:
    return replicate(points, leaves, s, t, ghost=True)


def spacetime_partition(points: DataFrame, window: StudyWindow, parts: int = 64, fraction: float = 0.01, scheme: str = "domain") -> tuple[DataFrame, Leaves]:
    """Sample, build, ship, look up: points with ``leaf``, and the leaves."""
    if scheme == "hash":
        return assign_hash(points, parts), leaves_hash(points, parts)
    side = max(1, round(parts ** (1 / 3)))
    if scheme == "grid":
        leaves = leaves_grid(window, side, side, side)
    else:
        sample = sample_points(points, fraction, floor=50 * parts)
        if scheme == "quadtree":
            leaves = leaves_quadtree(sample, window, max(1, len(sample) // parts))
        elif scheme == "rtree":
            leaves = leaves_rtree(sample, parts)
        else:
            leaves = leaves_domain_tree(sample, window, parts)
    leaves = leaves.outward(window) if leaves.cover else leaves
    placed = assign_leaf(points, leaves, window)
    if not leaves.cover:
        # Points outside all boxes get a leaf of their own, which meets every cylinder.
        big = np.full((1, 3), np.inf)
        leaves = Leaves(np.concatenate([leaves.lo, -big]), np.concatenate([leaves.hi, big]), cover=False)
        placed = placed.withColumn("leaf", F.when(F.col("leaf") < 0, F.lit(len(leaves) - 1)).otherwise(F.col("leaf")))
    return placed, leaves


def pairs_partitioned(points: DataFrame, window: StudyWindow, s: float, t: int, parts: int = 64, scheme: str = "domain", replication: str = "cylinder", local: str = "cells", capacity: int = 32, keys: tuple[str, ...] = (), compact: bool = False, placed: tuple[DataFrame, Leaves] | None = None) -> DataFrame:
    """Pairs found leaf by leaf; ``local``: cells (equi-join) or rtree, octree, kdtree (Arrow).

    ``compact`` passes each local index through its byte form; ``placed`` takes
    points with their leaves from ``spacetime_partition`` instead of a new sample."""
    placed, leaves = placed or spacetime_partition(points, window, parts, scheme=scheme)
    copies = replicate(placed.select(*keys, "id", "x", "y", "t0", "t1"), leaves, s, t, replication == "ghost")
    home = placed.select(*keys, "id", "x", "y", "t0", "t1", "leaf")
    ghost = replication == "ghost"
    if local != "cells":
        return _indexed(copies if ghost else home, home if ghost else copies, s, t, local, capacity, keys, compact)
    c, q = (home, copies) if ghost else (copies, home)
    c, q = sides(c, ("leaf", *keys))[0], sides(q, ("leaf", *keys))[1]
    size = max(int(t), 1)
    place = lambda p, o: F.struct(*[(v + F.lit(k).cast("long")).alias(n) for v, k, n in zip((cell(F.col(f"{p}_x"), s), cell(F.col(f"{p}_y"), s), time_cell(F.col(f"{p}_t0"), size, window.t_start)), o, "abe")])
    c = c.withColumn("k", F.explode(F.array(*[place("c", o) for o in product((-1, 0, 1), repeat=3)])))
    q = q.withColumn("k", place("q", (0, 0, 0)))
    # Replication hides in Arrow: the planner would take the copies for small and broadcast them.
    return finished(c.join(q.hint("merge"), (c.c_leaf == q.q_leaf) & (c.k == q.k) & same(keys) & near(s, t)), keys)


def _indexed(base: DataFrame, ask: DataFrame, s: float, t: int, kind: str, capacity: int, keys: tuple[str, ...], compact: bool) -> DataFrame:
    """A local index in each leaf over the side that is searched; the centres that ask
    it stream by behind it, so a task holds the points of one leaf and a few hits."""
    names = ["leaf", *keys]
    rows = base.select(*names, F.lit(0).alias("kind"), "id", "x", "y", "t0").unionByName(ask.select(*names, F.lit(1).alias("kind"), "id", "x", "y", "t0"))
    dealt = rows.repartition(*names).sortWithinPartitions(*names, "kind")
    types = dict(rows.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, held, tree = None, [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            col = {n: batch.column(n).to_numpy(zero_copy_only=False) for n in (*names, "kind", "id")}
            xyz = np.stack([batch.column(n).to_numpy(zero_copy_only=False).astype(float) for n in ("x", "y", "t0")], 1)
            new = np.zeros(batch.num_rows - 1, bool)
            for n in (*names, "kind"):
                new |= col[n][1:] != col[n][:-1]
            cuts = [0, *(np.flatnonzero(new) + 1).tolist(), batch.num_rows]
            for a, b in zip(cuts, cuts[1:]):
                mine = tuple(col[n][a] for n in names)
                if mine != group:
                    group, held, tree = mine, [], None
                if col["kind"][a] == 0:
                    held.append((col["id"][a:b], xyz[a:b]))
                    continue
                if not held:
                    continue
                if tree is None:
                    ids, points = (np.concatenate(v) for v in zip(*held))
                    tree = BUILDERS[kind](points, capacity if kind != "kdtree" else 1)
                    tree = decode_index(encode_index(tree)) if compact else tree
                who, c = col["id"][a:b], xyz[a:b]
                for i, j in tree.query(points, c, s * (1 + 1e-12), float(t)):
                    d = np.sqrt((c[i, 0] - points[j, 0]) * (c[i, 0] - points[j, 0]) + (c[i, 1] - points[j, 1]) * (c[i, 1] - points[j, 1]))
                    ok = (d <= s) & (who[i] != ids[j])
                    i, j, d = i[ok], j[ok], d[ok]
                    ends = [c[i, 0], c[i, 1], c[i, 2].astype(np.int64), d, np.abs(c[i, 2] - points[j, 2]).astype(np.int64), points[j, 0] - c[i, 0], points[j, 1] - c[i, 1]]
                    yield pa.RecordBatch.from_arrays([*(pa.array(np.full(len(i), v, col[n].dtype)) for v, n in zip(group[1:], keys)), pa.array(who[i]), pa.array(ids[j]), *map(pa.array, ends)], [*keys, "i", "j", "x", "y", "t0", "d", "u", "dx", "dy"])

    schema = ", ".join([*(f"{k} {types[k]}" for k in keys), "i long, j long, x double, y double, t0 long, d double, u long, dx double, dy double"])
    return dealt.mapInArrow(run, schema)


def partition_stats(points: DataFrame, window: StudyWindow, s: float, t: int, parts: int, scheme: str) -> DataFrame:
    """One row: balance, cover and replication of a scheme."""
    placed, leaves = spacetime_partition(points, window, parts, scheme=scheme)
    n_leaves = len(leaves)
    extra = 0 if leaves.cover or scheme == "hash" else 1
    per = placed.groupBy("leaf").agg(F.count("*").alias("n"))
    body = per.where(F.col("leaf") < n_leaves - extra) if extra else per
    one = body.agg(F.max("n").alias("rows_max"), F.sum("n").alias("rows"), F.sum(F.col("n") * F.col("n")).alias("sq"), F.count("*").alias("used"))
    out_of = per.where(F.col("leaf") >= n_leaves - extra).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("uncovered"))
    total = points.agg(F.count("*").alias("points"))
    copies = replicate(points.select("id", "x", "y", "t0"), leaves, s, t).agg(F.count("*").alias("cylinder"))
    ghosts = replicate(points.select("id", "x", "y", "t0"), leaves, s, t, ghost=True).agg(F.count("*").alias("ghost"))
    row = one.crossJoin(out_of).crossJoin(total).crossJoin(copies).crossJoin(ghosts)
    boxes = n_leaves - extra
    mean = F.col("rows") / boxes
    return row.select(
        F.lit(scheme).alias("scheme"), F.lit(boxes).alias("leaves"), "rows_max", mean.alias("rows_avg"), (F.col("rows_max") / mean).alias("max_over_mean"),
        (F.sqrt(F.greatest(F.lit(0.0), F.col("sq") / boxes - mean * mean)) / mean).alias("cv"), (F.lit(boxes) - F.col("used")).alias("empty"), "uncovered",
        (F.col("cylinder") / F.col("points")).alias("cylinder_factor"), (F.col("ghost") / F.col("points")).alias("ghost_factor"),
    )
