"""In-worker spatial indexes over points in space-time, queried by cylinders.

A query descends blocks of centres through the tree together: candidate
(centre, node) arrays shrink or grow level by level, and leaf items are tested
exactly. ``visited`` and ``compared`` count box tests and distance tests.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass
class BoxTree:
    """Nodes as boxes with child ranges; leaves hold ranges of ``order``."""

    lo: np.ndarray
    hi: np.ndarray
    first: np.ndarray
    last: np.ndarray
    leaf: np.ndarray
    order: np.ndarray
    capacity: int
    height: int
    visited: int = field(default=0)
    compared: int = field(default=0)

    def query(self, points: np.ndarray, centres: np.ndarray, s: float, t: float, tight: bool = True, block: int = 1024):
        """Yield (centre index, item index) arrays with d <= s and u <= t."""
        for a in range(0, len(centres), block):
            c = centres[a : a + block]
            who, node = np.arange(len(c)), np.zeros(len(c), np.int64)
            out_c, out_i = [], []
            while len(who):
                ok = box_hits_cylinder(self.lo[node], self.hi[node], c[who], s, t, tight)
                self.visited += len(who)
                who, node = who[ok], node[ok]
                many = self.last[node] - self.first[node]
                at = np.repeat(self.first[node], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                w, is_leaf = np.repeat(who, many), np.repeat(self.leaf[node], many)
                items = self.order[at[is_leaf]]
                wc = w[is_leaf]
                self.compared += len(items)
                d = points[items] - c[wc]
                hit = (d[:, 0] ** 2 + d[:, 1] ** 2 <= s * s) & (np.abs(d[:, 2]) <= t)
                out_c.append(wc[hit] + a)
                out_i.append(items[hit])
                who, node = w[~is_leaf], at[~is_leaf]
            yield (np.concatenate(out_c) if out_c else np.zeros(0, np.int64)), (np.concatenate(out_i) if out_i else np.zeros(0, np.int64))

    def stats(self) -> dict:
        sizes = (self.last - self.first)[self.leaf]
        return {"nodes": len(self.first), "leaves": int(self.leaf.sum()), "height": self.height, "largest_leaf": int(sizes.max(initial=0)), "visited": self.visited, "compared": self.compared}


def box_hits_cylinder(lo: np.ndarray, hi: np.ndarray, c: np.ndarray, s: float, t: float, tight: bool = True) -> np.ndarray:
    """Whether a box meets the cylinder (tight), or its bounding box (loose)."""
    ok = (lo[:, 2] <= c[:, 2] + t) & (hi[:, 2] >= c[:, 2] - t)
    dx = np.maximum(np.maximum(lo[:, 0] - c[:, 0], c[:, 0] - hi[:, 0]), 0)
    dy = np.maximum(np.maximum(lo[:, 1] - c[:, 1], c[:, 1] - hi[:, 1]), 0)
    return ok & ((dx * dx + dy * dy <= s * s) if tight else ((dx <= s) & (dy <= s)))


def _tiles(points: np.ndarray, idx: np.ndarray, capacity: int) -> list[np.ndarray]:
    """Equal cuts along x, then y, then time; runs of at most ``capacity``."""
    leaves = -(-len(idx) // capacity)
    side = max(1, round(leaves ** (1 / 3)))
    out = []
    for slab in np.array_split(idx[np.argsort(points[idx, 0], kind="stable")], side):
        for bar in np.array_split(slab[np.argsort(points[slab, 1], kind="stable")], side):
            bar = bar[np.argsort(points[bar, 2], kind="stable")]
            out += [bar[k : k + capacity] for k in range(0, len(bar), capacity)]
    return [o for o in out if len(o)]


def build_str_rtree(points: np.ndarray, capacity: int = 32) -> BoxTree:
    """Sort-tile-recursive bulk load: leaves by tiling, upper levels by tiling the boxes' centres."""
    if not len(points):
        return BoxTree(np.zeros((1, 3)), np.zeros((1, 3)), np.zeros(1, int), np.zeros(1, int), np.ones(1, bool), np.zeros(0, int), capacity, 1)
    groups = _tiles(points, np.arange(len(points)), capacity)
    levels = [(np.array([points[g].min(0) for g in groups]), np.array([points[g].max(0) for g in groups]), groups)]
    while len(levels[-1][0]) > 1:
        lo, hi, _ = levels[-1]
        packs = _tiles((lo + hi) / 2, np.arange(len(lo)), capacity)
        order = np.concatenate(packs)
        lo, hi, kids = lo[order], hi[order], [levels[-1][2][k] for k in order]
        levels[-1] = (lo, hi, kids)
        cuts = np.cumsum([0, *map(len, packs)])
        levels.append((np.array([lo[a:b].min(0) for a, b in zip(cuts, cuts[1:])]), np.array([hi[a:b].max(0) for a, b in zip(cuts, cuts[1:])]), [range(a, b) for a, b in zip(cuts, cuts[1:])]))
    levels.reverse()
    base = np.cumsum([0, *(len(x[0]) for x in levels)])
    lo, hi = np.concatenate([x[0] for x in levels]), np.concatenate([x[1] for x in levels])
    first, last, leaf, order, at = [], [], [], [], 0
    for depth, (_, _, kids) in enumerate(levels):
        bottom = depth == len(levels) - 1
        for k in kids:
            if bottom:
                first.append(at)
                at += len(k)
                last.append(at)
                order.append(k)
            else:
                first.append(base[depth + 1] + k.start)
                last.append(base[depth + 1] + k.stop)
            leaf.append(bottom)
    return BoxTree(lo, hi, np.array(first), np.array(last), np.array(leaf), np.concatenate(order), capacity, len(levels))


def _split_tree(points: np.ndarray, capacity: int, cut, max_depth: int) -> BoxTree:
    """Breadth-first top-down tree; ``cut(idx, lo, hi, depth)`` gives children (idx, lo, hi)."""
    n = len(points)
    lo0, hi0 = (points.min(0), points.max(0)) if n else (np.zeros(3), np.zeros(3))
    queue, k = [(np.arange(n), lo0, hi0, 0)], 0
    lo, hi, first, last, leaf, order, at, height = [], [], [], [], [], [], 0, 1
    while k < len(queue):
        idx, a, b, depth = queue[k]
        k += 1
        lo.append(a)
        hi.append(b)
        height = max(height, depth + 1)
        kids = cut(idx, a, b, depth) if len(idx) > capacity and depth < max_depth else []
        if len(kids) < 2 and not (kids and len(kids[0][0]) < len(idx)):
            first.append(at)
            at += len(idx)
            last.append(at)
            leaf.append(True)
            order.append(idx)
        else:
            first.append(len(queue))
            queue += [(i, x, y, depth + 1) for i, x, y in kids]
            last.append(len(queue))
            leaf.append(False)
    return BoxTree(np.array(lo), np.array(hi), np.array(first), np.array(last), np.array(leaf), np.concatenate(order) if order else np.zeros(0, int), capacity, height)


def build_octree(points: np.ndarray, max_items: int = 32, max_depth: int = 16) -> BoxTree:
    """Cubes halved on all three axes."""

    def cut(idx, lo, hi, depth):
        mid = (lo + hi) / 2
        code = ((points[idx] > mid) * np.array([1, 2, 4])).sum(1)
        out = []
        for o in np.unique(code):
            up = np.array([o & 1, o & 2, o & 4], bool)
            out.append((idx[code == o], np.where(up, mid, lo), np.where(up, hi, mid)))
        return out if len(out) > 1 or (len(out) == 1 and (hi - lo).max() > 1e-12) else []

    tree = _split_tree(points, max_items, cut, max_depth)
    return tree


def build_kdtree(points: np.ndarray, max_items: int = 1, max_depth: int = 64) -> BoxTree:
    """Median cuts on axes in turn, tight boxes."""

    def cut(idx, lo, hi, depth):
        axis = depth % 3
        order = idx[np.argsort(points[idx, axis], kind="stable")]
        half = len(order) // 2
        parts = [order[:half], order[half:]]
        return [(p, points[p].min(0), points[p].max(0)) for p in parts if len(p)]

    return _split_tree(points, max_items, cut, max_depth)


BUILDERS = {"rtree": build_str_rtree, "octree": build_octree, "kdtree": build_kdtree}
