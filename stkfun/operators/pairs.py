"""Ordered pairs (i, j, d, u) of distinct points within s in space and t in time.

All variants return the same rows: the centre's columns, the neighbour's id,
the distance ``d``, the time gap ``u`` (µs), and with ``carry`` further columns
of both sides (prefixes c_ and q_). Columns named in ``keys`` must agree on both
sides (a simulation's number, a group).
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stkfun.functions.geometry import space_distance, time_distance
from stkfun.functions.shared import settle


def sides(points: DataFrame, keys: tuple[str, ...] = (), carry: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """The centre side (c_...) and the neighbour side (q_...)."""
    names = ["id", "x", "y", "t0", "t1", *carry]
    have = [n for n in dict.fromkeys(names)]
    c = points.select(*[F.col(k).alias(f"c_{k}") for k in keys], *[F.col(n).alias(f"c_{n}") for n in have])
    q = points.select(*[F.col(k).alias(f"q_{k}") for k in keys], *[F.col(n).alias(f"q_{n}") for n in have])
    return c, q


def near(s: float, t: int, mode: str = "start") -> Column:
    """Both thresholds (closed), identical rows excluded."""
    return (distance() <= s) & (gap(mode) <= t) & (F.col("c_id") != F.col("q_id"))


def distance() -> Column:
    return space_distance(F.col("c_x"), F.col("c_y"), F.col("q_x"), F.col("q_y"))


def gap(mode: str = "start") -> Column:
    return time_distance(F.col("c_t0"), F.col("c_t1"), F.col("q_t0"), F.col("q_t1"), mode)


def finished(joined: DataFrame, keys: tuple[str, ...] = (), carry: tuple[str, ...] = (), mode: str = "start", both: bool = False, brought: tuple[str, ...] = ()) -> DataFrame:
    """The common pair columns; ``both`` adds the neighbour's place and time as x2, y2, t2."""
    base = [F.col(f"c_{k}").alias(k) for k in keys]
    extra = [F.col(f"{p}_{n}") for n in carry for p in ("c", "q")] + [F.col(f"c_{n}") for n in brought]
    extra += [F.col(f"q_{n}").alias(a) for n, a in (("x", "x2"), ("y", "y2"), ("t0", "t2"))] if both else []
    return joined.select(*base, F.col("c_id").alias("i"), F.col("q_id").alias("j"), F.col("c_x").alias("x"), F.col("c_y").alias("y"), F.col("c_t0").alias("t0"), distance().alias("d"), gap(mode).alias("u"), (F.col("q_x") - F.col("c_x")).alias("dx"), (F.col("q_y") - F.col("c_y")).alias("dy"), *extra)


def same(keys: tuple[str, ...]) -> Column:
    out = F.lit(True)
    for k in keys:
        out = out & (F.col(f"c_{k}") == F.col(f"q_{k}"))
    return out


def dealt(c: DataFrame, q: DataFrame, on: Column) -> DataFrame:
    """Both sides sorted and merged: the planner takes a side that visits its neighbour
    cells for as small as the points' files, and would broadcast it through the driver."""
    return c.join(q.hint("merge"), on)


def pairs_bruteforce(points: DataFrame, s: float, t: int, keys=(), carry=(), mode="start") -> DataFrame:
    """Every ordered pair is compared (baseline)."""
    c, q = sides(points, keys, carry)
    return finished(c.crossJoin(q).where(same(keys) & near(s, t, mode)), keys, carry, mode)


def cell(v: Column, size: float) -> Column:
    return F.floor(v / size)


def time_cell(t: Column, size: int, origin: int) -> Column:
    return F.floor((t - F.lit(origin)) / F.lit(size)).cast("long")


def _origin(window) -> int:
    return window.t_start if window is not None else 0


def _steps(half: bool) -> Column:
    """Offsets to the 27 cells around a cell; of each opposite two only one for ``half``."""
    some = [o for o in product((-1, 0, 1), repeat=3) if not half or o >= (0, 0, 0)]
    return F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip(o, "abe")]) for o in some])


def pairs_cells(points: DataFrame, s: float, t: int, keys=(), carry=(), window=None, salt: int = 1, half: bool = False, both: bool = False, centres: DataFrame | None = None, brought: tuple[str, ...] = ()) -> DataFrame:
    """Equi-join on cells of side (s, t): a centre visits its 27 neighbour cells.

    ``salt`` deals the neighbours of a cell to so many buckets and repeats the
    centres, for hot cells; ``half`` finds each unordered pair once, from 14 cells
    (the smaller id first within a cell); ``both`` adds the neighbour's place and
    time; ``centres``: other rows than the points themselves; ``brought``: further
    columns of these only (as c_...), wide ones: the neighbours visit the cells then."""
    c, q = sides(points, keys, carry)
    if centres is not None:
        c = sides(centres, keys, (*carry, *brought))[0]
    t = max(int(t), 1)
    place = lambda p: F.struct(cell(F.col(f"{p}_x"), s).alias("a"), cell(F.col(f"{p}_y"), s).alias("b"), time_cell(F.col(f"{p}_t0"), t, _origin(window)).alias("e"))
    own = (F.col("o.a") == 0) & (F.col("o.b") == 0) & (F.col("o.e") == 0)

    def visiting(p: DataFrame, name: str) -> DataFrame:
        p = p.withColumn("cell", place(name)).withColumn("o", F.explode(_steps(half)))
        return p.withColumn("k", F.struct(*[(F.col(f"cell.{n}") + F.col(f"o.{n}")).alias(n) for n in "abe"])).withColumn("own", own).drop("cell", "o")

    c, q = (c.withColumn("k", place("c")), visiting(q, "q")) if brought else (visiting(c, "c"), q.withColumn("k", place("q")))
    if salt > 1:
        q = q.withColumn("salt", F.pmod(F.xxhash64("q_id"), F.lit(salt)).cast("int"))
        c = c.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))))
    on = [c.k == q.k] + ([c.salt == q.salt] if salt > 1 else []) + [c[f"c_{k}"] == q[f"q_{k}"] for k in keys]
    test = near(s, t) & (~F.col("own") | (F.col("c_id") < F.col("q_id")) if half else F.lit(True))
    cond = on[0]
    for o in on[1:]:
        cond = cond & o
    joined = dealt(c, q, cond & test)
    return finished(joined, keys, carry, both=both, brought=brought)


def pairs_intervals(points: DataFrame, s: float, t: int, keys=(), carry=(), window=None) -> DataFrame:
    """Pairs of things that last from t0 to t1: u is the gap of the intervals, 0 where they overlap.

    A neighbour lies in every time cell that it touches, a centre looks into every
    cell within t of its interval; the first cell that both have gives the pair."""
    c, q = sides(points, keys, carry)
    size = max(int(t), 1)
    around = F.array(*[F.struct(F.lit(i).cast("long").alias("a"), F.lit(j).cast("long").alias("b")) for i, j in product((-1, 0, 1), repeat=2)])
    slice_ = lambda v: time_cell(v, size, _origin(window))
    c = c.withColumn("c_first", slice_(F.col("c_t0") - t)).withColumn("e", F.explode(F.sequence("c_first", slice_(F.col("c_t1") + t)))).withColumn("o", F.explode(around))
    c = c.withColumn("k", F.struct((cell(F.col("c_x"), s) + F.col("o.a")).alias("a"), (cell(F.col("c_y"), s) + F.col("o.b")).alias("b"), "e")).drop("o", "e")
    q = q.withColumn("q_first", slice_(F.col("q_t0"))).withColumn("e", F.explode(F.sequence("q_first", slice_(F.col("q_t1")))))
    q = q.withColumn("k", F.struct(cell(F.col("q_x"), s).alias("a"), cell(F.col("q_y"), s).alias("b"), "e")).drop("e")
    once = F.col("k.e") == F.greatest("c_first", "q_first")
    joined = dealt(c, q.withColumnRenamed("k", "k2"), (F.col("k") == F.col("k2")) & same(keys) & near(s, t, "interval") & once)
    return finished(joined, keys, carry, "interval")


def spread_bits(v: Column) -> Column:
    """The low 16 bits with a zero between each two."""
    for shift, mask in ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555)):
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask).cast("long"))
    return v


def interleaved(a: Column, b: Column) -> Column:
    """Bits of two cells of up to 16 bits woven into one code."""
    return spread_bits(a).bitwiseOR(F.shiftleft(spread_bits(b), 1))


def cell_code(a: Column, b: Column, e: Column) -> Column:
    """Time slice in front, woven space cell behind."""
    return F.shiftleft(e.cast("long"), 32).bitwiseOR(interleaved(a.cast("long"), b.cast("long")))


def pairs_cellcode(points: DataFrame, s: float, t: int, window, keys=(), carry=()) -> DataFrame:
    """Space-filling code with time slices; neighbour codes are probed and distances verified."""
    c, q = sides(points, keys, carry)
    cells = lambda p: [F.floor((F.col(f"{p}_x") - window.x0) / s) + 1, F.floor((F.col(f"{p}_y") - window.y0) / s) + 1, time_cell(F.col(f"{p}_t0"), t, window.t_start) + 1]
    steps = F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip(o, "abe")]) for o in product((-1, 0, 1), repeat=3)])
    c = c.withColumn("o", F.explode(steps))
    c = c.withColumn("code", cell_code(*[v + F.col(f"o.{n}") for v, n in zip(cells("c"), "abe")])).drop("o")
    q = q.withColumn("code", cell_code(*cells("q")))
    return finished(dealt(c, q, (c.code == q.code) & same(keys) & near(s, t)), keys, carry)


def pairs_sweep(points: DataFrame, s: float, t: int, keys=(), carry=(), window=None) -> DataFrame:
    """Range join in time only, as an equi-join of time slices; space is a residual test."""
    c, q = sides(points, keys, carry)
    c = c.withColumn("slice", F.explode(F.array(*[time_cell(F.col("c_t0"), t, _origin(window)) + o for o in (-1, 0, 1)])))
    q = q.withColumn("slice", time_cell(F.col("q_t0"), t, _origin(window)))
    return finished(dealt(c, q, (c["slice"] == q["slice"]) & same(keys) & near(s, t)), keys, carry)


def neighbours(points: DataFrame, centres: DataFrame, s: float, t: int, window=None) -> DataFrame:
    """(i, j, d, u): points within (s, t) of given centres, other ids than the centre's."""
    return pairs_cells(points, s, t, window=window, centres=centres).select("i", "j", "d", "u")


def neighbour_count(points: DataFrame, s: float, t: int, window=None) -> DataFrame:
    """(id, n): neighbours of every point, 0 included."""
    got = pairs_cells(points, s, t, window=window).groupBy("i").agg(F.count("*").alias("n"))
    return points.select("id").join(got, F.col("id") == F.col("i"), "left").select("id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def first_radius(points: DataFrame, k: int, speed: float, start: float) -> float:
    """``start``, halved while its cells hold many more points than are asked for, as
    long as eight halvings tell some of them apart: where points are dense, fewer pairs
    are ranked."""
    hour, radius, best, most, idle = 3_600_000_000, float(start), float(start), None, 0
    while idle < 8:
        at = (cell(F.col("x"), radius), cell(F.col("y"), radius), time_cell(F.col("t0"), max(1, int(radius / speed * hour) + 1), 0))
        held = points.groupBy(*[c.alias(n) for c, n in zip(at, "abe")]).agg(F.count("*").alias("m")).agg(F.sum("m").alias("n"), F.sum(F.col("m") * F.col("m")).alias("pairs")).first()
        if most is None or held.pairs < 0.9 * most:
            best, most, idle = radius, held.pairs or 0, 0
        else:
            idle += 1
        if most <= 2 * (k + 1) * (held.n or 0):
            break
        radius /= 2
    return best


def knn(points: DataFrame, k: int, speed: float, start: float) -> DataFrame:
    """(i, j, r, rank): the k nearest in r = sqrt(d^2 + (speed * hours)^2), ties by id.

    Searches a radius (``start``, less where points are dense), doubles it for points
    that have not k neighbours inside it, until it covers all points: only then do
    points have fewer than k."""
    hour = 3_600_000_000
    cols = ["id", "x", "y", "t0", "t1"]
    points = settle(points.select(*cols), "points")
    far = points.agg(*[(F.max(c) - F.min(c)).alias(c) for c in ("x", "y", "t0")]).first()
    whole = ((far.x or 0) ** 2 + (far.y or 0) ** 2 + (speed * (far.t0 or 0) / hour) ** 2) ** 0.5 * (1 + 1e-9)
    todo, parts, radius = points, [], first_radius(points, k, speed, start)
    while True:
        last = radius >= whole
        got = pairs_cells(points, radius, max(1, int(radius / speed * hour) + 1), centres=todo)
        r = F.sqrt(F.col("d") * F.col("d") + F.pow(F.lit(speed) * F.col("u") / float(hour), F.lit(2)))
        got = got.select("i", "j", r.alias("r")).where(F.col("r") <= radius)
        ranked = settle(got.withColumn("rank", F.row_number().over(Window.partitionBy("i").orderBy("r", "j"))).where(F.col("rank") <= k), "ranked")
        if last:
            parts.append(ranked)
            break
        done = ranked.where(F.col("rank") == k).select(F.col("i").alias("id"))
        parts.append(ranked.join(done.withColumnRenamed("id", "i"), "i", "left_semi"))
        todo = settle(todo.join(done, "id", "left_anti").select(*cols), "unmet")
        if todo.limit(1).count() == 0:
            break
        radius = min(radius * 2, max(whole, radius))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
