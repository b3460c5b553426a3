"""Compact binary forms of points, cylinders, envelopes and indexes.

Each record starts with a one-byte class id; only fields travel. The default
form (baseline) pickles one object per row.
"""

from __future__ import annotations

import pickle
import struct
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType

from stkfun.operators.local_index import BoxTree

POINT, CYLINDER, ENVELOPE, RTREE, DOMAIN = 1, 2, 3, 4, 5
CODEC_IDS = {"point": POINT, "cylinder": CYLINDER, "envelope": ENVELOPE, "rtree": RTREE, "domain": DOMAIN}
_POINT = np.dtype([("cls", "u1"), ("id", "<i8"), ("x", "<f8"), ("y", "<f8"), ("mult", "<i4"), ("t0", "<i8"), ("t1", "<i8"), ("zone", "<i4")])
_CYLINDER = np.dtype([("cls", "u1"), ("point", _POINT), ("rs", "<f8"), ("rt", "<i8"), ("unit", "u1")])
_ENVELOPE = np.dtype([("cls", "u1"), ("x0", "<f8"), ("x1", "<f8"), ("y0", "<f8"), ("y1", "<f8"), ("t0", "<i8"), ("t1", "<i8"), ("zone", "<i4"), ("env_id", "<i4")])
LAYOUTS = {POINT: _POINT, CYLINDER: _CYLINDER, ENVELOPE: _ENVELOPE}
NO_ZONE = -(2**31)
TIME_UNITS = ("us", "s", "min", "h", "d", "week", "month")


def _packed(table: np.ndarray) -> pd.Series:
    size, raw = table.dtype.itemsize, table.tobytes()
    return pd.Series([raw[k : k + size] for k in range(0, len(raw), size)], dtype=object)


def _unpacked(rows: pd.Series, dtype: np.dtype) -> np.ndarray:
    return np.frombuffer(b"".join(rows), dtype)


def _point_rows(id, x, y, mult, t0, t1, zone) -> np.ndarray:
    out = np.zeros(len(id), _POINT)
    out["cls"] = POINT
    for name, values in (("id", id), ("x", x), ("y", y), ("mult", mult), ("t0", t0), ("t1", t1)):
        out[name] = values.to_numpy()
    out["zone"] = zone.fillna(NO_ZONE).to_numpy().astype(np.int64)
    return out


@F.pandas_udf(BinaryType())
def pack_point(id: pd.Series, x: pd.Series, y: pd.Series, mult: pd.Series, t0: pd.Series, t1: pd.Series, zone: pd.Series) -> pd.Series:
    return _packed(_point_rows(id, x, y, mult, t0, t1, zone))


def encode_points(points: DataFrame) -> DataFrame:
    return points.select(pack_point("id", "x", "y", "mult", "t0", "t1", "zone").alias("b"))


def decode_points(coded: DataFrame) -> DataFrame:
    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            r = _unpacked(p["b"], _POINT)
            yield pd.DataFrame({n: r[n] for n in ("id", "x", "y", "mult", "t0", "t1")} | {"zone": pd.Series(r["zone"]).astype("Int32").mask(r["zone"] == NO_ZONE)})

    return coded.mapInPandas(run, "id long, x double, y double, mult int, t0 long, t1 long, zone int")


def encode_cylinders(points: DataFrame, rs: float, rt: int, unit: str = "h") -> DataFrame:
    @F.pandas_udf(BinaryType())
    def pack(id: pd.Series, x: pd.Series, y: pd.Series, mult: pd.Series, t0: pd.Series, t1: pd.Series, zone: pd.Series) -> pd.Series:
        out = np.zeros(len(id), _CYLINDER)
        out["cls"], out["point"], out["rs"], out["rt"], out["unit"] = CYLINDER, _point_rows(id, x, y, mult, t0, t1, zone), rs, rt, TIME_UNITS.index(unit)
        return _packed(out)

    return points.select(pack("id", "x", "y", "mult", "t0", "t1", "zone").alias("b"))


def decode_cylinders(coded: DataFrame) -> DataFrame:
    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            r = _unpacked(p["b"], _CYLINDER)
            q = r["point"]
            yield pd.DataFrame({n: q[n] for n in ("id", "x", "y", "t0")} | {"rs": r["rs"], "rt": r["rt"], "unit": [TIME_UNITS[u] for u in r["unit"]]})

    return coded.mapInPandas(run, "id long, x double, y double, t0 long, rs double, rt long, unit string")


def encode_envelopes(boxes: DataFrame) -> DataFrame:
    """Rows env_id, x0, x1, y0, y1, t0, t1, zone."""

    @F.pandas_udf(BinaryType())
    def pack(env_id: pd.Series, x0: pd.Series, x1: pd.Series, y0: pd.Series, y1: pd.Series, t0: pd.Series, t1: pd.Series, zone: pd.Series) -> pd.Series:
        out = np.zeros(len(env_id), _ENVELOPE)
        out["cls"] = ENVELOPE
        for name, v in (("env_id", env_id), ("x0", x0), ("x1", x1), ("y0", y0), ("y1", y1), ("t0", t0), ("t1", t1)):
            out[name] = v.to_numpy()
        out["zone"] = zone.fillna(NO_ZONE).to_numpy().astype(np.int64)
        return _packed(out)

    return boxes.select(pack("env_id", "x0", "x1", "y0", "y1", "t0", "t1", "zone").alias("b"))


def decode_envelopes(coded: DataFrame) -> DataFrame:
    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            r = _unpacked(p["b"], _ENVELOPE)
            yield pd.DataFrame({n: r[n] for n in ("env_id", "x0", "x1", "y0", "y1", "t0", "t1")} | {"zone": pd.Series(r["zone"]).astype("Int32").mask(r["zone"] == NO_ZONE)})

    return coded.mapInPandas(run, "env_id int, x0 double, x1 double, y0 double, y1 double, t0 long, t1 long, zone int")


def encode_index(tree: BoxTree) -> bytes:
    """Class id, capacity, then nodes depth first: a leaf with its items, or children."""
    out = [struct.pack("<BiiI", RTREE, tree.capacity, tree.height, len(tree.order))]

    def put(k: int) -> None:
        out.append(np.concatenate([tree.lo[k], tree.hi[k]]).astype("<f8").tobytes())
        a, b = int(tree.first[k]), int(tree.last[k])
        out.append(struct.pack("<?I", bool(tree.leaf[k]), b - a))
        if tree.leaf[k]:
            out.append(tree.order[a:b].astype("<i8").tobytes())
        else:
            for child in range(a, b):
                put(child)

    put(0)
    return b"".join(out)


def decode_index(data: bytes) -> BoxTree:
    cls, capacity, height, items = struct.unpack_from("<BiiI", data)
    if cls != RTREE:
        raise ValueError(f"class id {cls} is not an index")
    at = struct.calcsize("<BiiI")
    levels: list[list[tuple]] = [[]]

    def take(depth: int) -> None:
        nonlocal at
        box = np.frombuffer(data, "<f8", 6, at)
        leaf, n = struct.unpack_from("<?I", data, at + 48)
        at += 48 + struct.calcsize("<?I")
        while len(levels) <= depth:
            levels.append([])
        if leaf:
            rows = np.frombuffer(data, "<i8", n, at)
            at += 8 * n
            levels[depth].append((box, True, rows, n))
        else:
            levels[depth].append((box, False, None, n))
            for _ in range(n):
                take(depth + 1)

    take(0)
    base = np.cumsum([0, *map(len, levels)])
    lo, hi, first, last, leaf, order, seat = [], [], [], [], [], [], 0
    for depth, nodes in enumerate(levels):
        child = int(base[depth + 1])
        for box, is_leaf, rows, n in nodes:
            lo.append(box[:3])
            hi.append(box[3:])
            leaf.append(is_leaf)
            if is_leaf:
                first.append(seat)
                seat += n
                last.append(seat)
                order.append(rows)
            else:
                first.append(child)
                child += n
                last.append(child)
    return BoxTree(np.array(lo), np.array(hi), np.array(first), np.array(last), np.array(leaf), np.concatenate(order) if items else np.zeros(0, int), capacity, height)


@F.pandas_udf(BinaryType())
def pickle_point(id: pd.Series, x: pd.Series, y: pd.Series, mult: pd.Series, t0: pd.Series, t1: pd.Series, zone: pd.Series) -> pd.Series:
    rows = zip(id, x, y, mult, t0, t1, zone)
    names = ("id", "x", "y", "mult", "t0", "t1", "zone")
    return pd.Series([pickle.dumps(dict(zip(names, r))) for r in rows], dtype=object)


def encode_default(points: DataFrame) -> DataFrame:
    return points.select(pickle_point("id", "x", "y", "mult", "t0", "t1", "zone").alias("b"))


def codec_sizes(points: DataFrame) -> DataFrame:
    """n, bytes of both forms and their ratio."""
    both = points.select(F.length(pack_point("id", "x", "y", "mult", "t0", "t1", "zone")).alias("c"), F.length(pickle_point("id", "x", "y", "mult", "t0", "t1", "zone")).alias("d"))
    return both.agg(F.count("*").alias("n"), F.sum("d").alias("size_d"), F.sum("c").alias("size_c")).withColumn("cr", F.col("size_d") / F.col("size_c"))


def codec_stats(points: DataFrame) -> DataFrame:
    """Sizes, times and ratios of both forms, timed over the same cached rows on the workers."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            clock = time.perf_counter
            a = clock()
            c = _packed(_point_rows(*(p[n] for n in ("id", "x", "y", "mult", "t0", "t1", "zone"))))
            b = clock()
            _unpacked(c, _POINT)
            ser_c, de_c = b - a, clock() - b
            names = ("id", "x", "y", "mult", "t0", "t1", "zone")
            a = clock()
            d = [pickle.dumps(dict(zip(names, r))) for r in p[list(names)].itertuples(index=False)]
            b = clock()
            for x in d:
                pickle.loads(x)
            yield pd.DataFrame({"n": [len(p)], "size_d": [sum(map(len, d))], "size_c": [_POINT.itemsize * len(p)], "ser_d": [b - a], "ser_c": [ser_c], "de_d": [clock() - b], "de_c": [de_c]})

    got = points.select("id", "x", "y", "mult", "t0", "t1", "zone").mapInPandas(run, "n long, size_d long, size_c long, ser_d double, ser_c double, de_d double, de_c double")
    one = got.agg(*[F.sum(c).alias(c) for c in ("n", "size_d", "size_c", "ser_d", "ser_c", "de_d", "de_c")])
    return one.withColumns({"cr": F.col("size_d") / F.col("size_c"), "sr_s": F.col("ser_d") / F.col("ser_c"), "sr_d": F.col("de_d") / F.col("de_c")})
