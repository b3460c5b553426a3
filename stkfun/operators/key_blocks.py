"""Distinct keys of pairs, found where the pairs are found.

Points go to blocks together with all that lie within reach, and a task walks the
centres of a block key by key (a place, a time). A key's pairs are held only until
its distinct values are counted, so that the shuffle carries points and never pairs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.config import StudyWindow
from stkfun.functions.geometry import w_space

#: Cells and reaches are wider than the threshold by this share: rounding loses no neighbour.
SLACK = 1 + 1e-9
#: Values of one key that are gathered before copies among them are dropped.
GATHERED = 1 << 21


def _visited(v: Column, reach: float, size: float) -> Column:
    return F.sequence(F.floor((v - reach) / size), F.floor((v + reach) / size))


def space_blocks(points: DataFrame, s: float, kx: Column, ky: Column, tol: float = 0.0) -> DataFrame:
    """Blocks of side 2 s; a point is a centre in the block of its key (kx, ky)."""
    size, reach = 2 * s, (s + tol) * SLACK
    p = points.where("id is not null").select("id", "x", "y", "t0", kx.alias("kx"), ky.alias("ky"))
    p = p.withColumn("a", F.explode(_visited(F.col("x"), reach, size))).withColumn("b", F.explode(_visited(F.col("y"), reach, size)))
    return p.withColumn("own", (F.floor(F.col("kx") / size) == F.col("a")) & (F.floor(F.col("ky") / size) == F.col("b")))


def time_blocks(points: DataFrame, t: int, window: StudyWindow) -> DataFrame:
    """Slices of half of t; the key is the time."""
    size, since = max(1, int(t) // 2), F.col("t0") - window.t_start
    slice_ = lambda v: F.floor(v / F.lit(size)).cast("long")
    p = points.where("id is not null").select("id", "x", "y", "t0")
    p = p.withColumn("a", F.explode(F.sequence(slice_(since - int(t)) - 1, slice_(since + int(t)) + 1)))
    p = p.where((F.col("a") * size <= since + int(t)) & ((F.col("a") + 1) * size > since - int(t)))
    return p.withColumns({"b": F.lit(0).cast("long"), "own": (F.col("a") * size <= since) & ((F.col("a") + 1) * size > since)})


class Around:
    """The points of one block in cells; what lies around a cell is put in order of time once."""

    def __init__(self, x: np.ndarray, y: np.ndarray, t: np.ndarray, id: np.ndarray, s: float, reach: int):
        self.s, self.reach, self.kept = s, reach, {}
        self.ca, self.cb = np.floor(x / (s * SLACK)), np.floor(y / (s * SLACK))
        order = np.lexsort((t, self.ca))
        self.sorted = [v[order] for v in (self.ca, self.cb, x, y, t, id)]

    def at(self, a: float, b: float) -> tuple[np.ndarray, ...]:
        if (a, b) not in self.kept:
            ca, cb, *rest = self.sorted
            lo, hi = np.searchsorted(ca, a - 1, "left"), np.searchsorted(ca, a + 1, "right")
            near = lo + np.flatnonzero(np.abs(cb[lo:hi] - b) <= 1)
            near = near[np.argsort(rest[2][near], kind="stable")]
            self.kept[a, b] = tuple(v[near] for v in rest)
        return self.kept[a, b]

    def pairs(self, k: int, x: np.ndarray, y: np.ndarray, t: np.ndarray, id: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """d and u of the neighbours of the block's row k."""
        qx, qy, qt, qid = self.at(self.ca[k], self.cb[k])
        lo, hi = np.searchsorted(qt, t[k] - self.reach, "left"), np.searchsorted(qt, t[k] + self.reach, "right")
        dx, dy = x[k] - qx[lo:hi], y[k] - qy[lo:hi]
        dx *= dx
        dy *= dy
        dx += dy
        d = np.sqrt(dx)
        met = np.flatnonzero(d <= self.s)
        met = met[qid[lo:hi][met] != id[k]]
        return d[met], np.abs(qt[lo:hi][met] - t[k])


def _walked(table: pa.Table, s: float, t: int, keys: tuple[str, ...]) -> Iterator[tuple[list[np.ndarray], int, Around, list[np.ndarray]]]:
    """(columns, first, after, order) of each key: the block's rows order[first:after] are its centres."""
    cols = [table.column(n).to_numpy() for n in ("x", "y", "t0", "id")]
    own = np.flatnonzero(table.column("own").to_numpy(zero_copy_only=False))
    by = [table.column(n).to_numpy()[own] for n in keys]
    order = np.lexsort(by[::-1])
    own, by = own[order], [v[order] for v in by]
    new = np.ones(len(own), bool)
    new[1:] = np.any([v[1:] != v[:-1] for v in by], axis=0)
    around, heads = Around(*cols, s, t), np.flatnonzero(new)
    for first, after in zip(heads, [*heads[1:], len(own)]):
        yield cols, own[first:after], around, [v[first] for v in by]


def counting(s: float, t: int, keys: tuple[str, ...]) -> Callable[[pa.Table], pa.Table]:
    """pairs, keys with a pair, and distinct values: distances of a place or gaps of a time."""

    def count(table: pa.Table) -> pa.Table:
        pairs = met = distinct = 0
        for cols, rows, around, _ in _walked(table, s, t, keys):
            got, size = [], 0
            for k in rows:
                found = around.pairs(k, *cols)[keys == ("t0",)]
                pairs += len(found)
                size += len(found)
                got.append(found)
                if size > GATHERED:
                    got = [np.unique(np.concatenate(got))]
                    size = len(got[0])
            if size:
                met += 1
                v = np.sort(got[0] if len(got) == 1 else np.concatenate(got))
                distinct += 1 + int(np.count_nonzero(v[1:] != v[:-1]))
        return pa.table({"pairs": pa.array([pairs], "int64"), "met": pa.array([met], "int64"), "keys": pa.array([distinct], "int64")})

    return count


def key_counts(points: DataFrame, window: StudyWindow, s: float, t: int) -> DataFrame:
    """``weight_cache.key_counts`` of the pairs of ``points``: once by places, once by times."""
    kind, t = "pairs long, met long, keys long", max(int(t), 1)
    x, y = F.col("x") + 0.0, F.col("y") + 0.0
    places = space_blocks(points, s, x, y).groupBy("a", "b").applyInArrow(counting(s, t, ("kx", "ky")), kind)
    times = time_blocks(points, t, window).groupBy("a", "b").applyInArrow(counting(s, t, ("t0",)), kind)
    total = lambda n, a: F.coalesce(F.sum(n), F.lit(0)).cast("long").alias(a)
    both = places.agg(total("pairs", "pairs"), total("met", "places"), total("keys", "space_keys")).crossJoin(times.agg(total("met", "times"), total("keys", "time_keys")))
    return both.select("pairs", "places", "space_keys", "times", "time_keys")


def rounded_steps(d: np.ndarray, tol: float) -> np.ndarray:
    """Nearest multiples, halves up."""
    v = d / tol
    whole = np.floor(v)
    return (whole + (v - whole >= 0.5)).astype(int)


def showing(s: float, t: int, tol: float) -> Callable[[pa.Table], pa.Table]:
    """kx, ky, kd of each key; one that shows every snapped distance has no further one."""
    every = int(Decimal(repr(s / tol)).quantize(Decimal(1), ROUND_HALF_UP)) + 1

    def show(table: pa.Table) -> pa.Table:
        out = [[], [], []]
        for cols, rows, around, (kx, ky) in _walked(table, s, t, ("kx", "ky")):
            seen = np.zeros(every, bool)
            for k in rows:
                seen[rounded_steps(around.pairs(k, *cols)[0], tol)] = True
                if seen.all():
                    break
            at = np.flatnonzero(seen)
            for column, v in zip(out, (np.full(len(at), kx), np.full(len(at), ky), at * tol)):
                column.append(v)
        return pa.table({n: pa.array(np.concatenate(v) if v else [], "double") for n, v in zip(("kx", "ky", "kd"), out)})

    return show


def space_cache(points: DataFrame, window: StudyWindow, s: float, t: int, coord_tol: float, dist_tol: float) -> DataFrame:
    """``weight_cache.space_cache`` of the pairs of ``points``, with tolerances."""
    snap = lambda c: F.round(F.col(c) / coord_tol) * coord_tol
    keys = space_blocks(points, s, snap("x"), snap("y"), coord_tol).groupBy("a", "b").applyInArrow(showing(s, max(int(t), 1), dist_tol), "kx double, ky double, kd double")
    return keys.select("kx", "ky", "kd", w_space(F.col("kx"), F.col("ky"), F.col("kd"), window).alias("ws"))
