"""Point sets: projections of tables to (id, x, y, t0, t1, mult, zone, mark)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stkfun.config import W_EVENTS, StudyWindow
from stkfun.functions.geometry import hash_uniform, inside_ring

SCHEMA = "id long, x double, y double, t0 long, t1 long, mult int, zone int, mark string"
COLUMNS = ["id", "x", "y", "t0", "t1", "mult", "zone", "mark"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ticks(ts: Column) -> Column:
    """µs since the epoch of a date or timestamp, with or without a zone."""
    return F.unix_micros(ts.cast("timestamp"))


def point_set(df: DataFrame, id: Column, x: Column, y: Column, t0: Column, t1: Column | None = None, mult: Column | None = None, zone: Column | None = None, mark: Column | None = None) -> DataFrame:
    """The common point schema; rows without a place or a time are dropped."""
    out = df.select(
        id.cast("long").alias("id"), x.cast("double").alias("x"), y.cast("double").alias("y"), t0.cast("long").alias("t0"),
        (t0 if t1 is None else t1).cast("long").alias("t1"), (F.lit(1) if mult is None else mult).cast("int").alias("mult"),
        (F.lit(None) if zone is None else zone).cast("int").alias("zone"), (F.lit(None) if mark is None else mark).cast("string").alias("mark"),
    )
    return out.na.drop(subset=["x", "y", "t0"])


def clip(points: DataFrame, window: StudyWindow) -> DataFrame:
    """Points inside the window: bounding box first, then the ring."""
    out = points.where(F.col("x").between(window.x0, window.x1) & F.col("y").between(window.y0, window.y1))
    if window.period:
        out = out.where((F.col("t0") >= window.t_start) & (F.col("t0") < window.t_end))
    return out.where(inside_ring(F.col("x"), F.col("y"), window.ring)) if window.ring else out


def events_skewed(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return point_set(e, F.col("event_id"), F.col("value"), F.get_json_object("props", "$.k").cast("double"), ticks(F.col("ts")), mark=F.col("event_type"))


def uniform_over(ids: DataFrame, window: StudyWindow, prefix: str = "", mark: Column | None = None) -> DataFrame:
    """One md5-uniform point in the window's box for each id."""
    u = lambda tag: hash_uniform(prefix + tag, F.col("id"))
    x = F.lit(window.x0) + (window.x1 - window.x0) * u("x")
    y = F.lit(window.y0) + (window.y1 - window.y0) * u("y")
    t = F.lit(window.t_start) + F.floor(float(window.period) * u("t"))
    return point_set(ids, F.col("id"), x, y, t, mark=mark)


def events_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "event_type")
    return uniform_over(e, W_EVENTS, mark=F.col("event_type"))


def generated(spark: SparkSession, n: int, window: StudyWindow) -> DataFrame:
    """``n`` uniform points without any table."""
    return clip(uniform_over(spark.range(n), window), window)


def orders_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    both = o.join(c, o.o_custkey == c.c_custkey).select("o_orderkey", "o_totalprice", "c_acctbal", "o_orderdate", "c_nationkey", "o_orderpriority")
    return point_set(both, F.col("o_orderkey"), F.col("o_totalprice").cast("double") / 5000, (F.col("c_acctbal").cast("double") + 1000) / 110, ticks(F.col("o_orderdate")), zone=F.col("c_nationkey"), mark=F.col("o_orderpriority"))


def lineitem_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Coincident lines collapsed to one point with a count; the id is the place and time."""
    x, y = F.col("l_quantity").cast("double"), F.round(F.col("l_discount").cast("double") * 100)
    lines = table(spark, sf_dir, "lineitem").select(x.alias("x"), y.alias("y"), ticks(F.col("l_shipdate")).alias("t0"))
    one = lines.groupBy("x", "y", "t0").agg(F.count("*").alias("mult"))
    key = ((F.col("t0") / 86_400_000_000).cast("long") * 1000 + F.col("x").cast("long")) * 100 + F.col("y").cast("long")
    return point_set(one, key, F.col("x"), F.col("y"), F.col("t0"), mult=F.col("mult"))


def embedding_plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings")
    return point_set(e, F.col("vec_id"), F.col("embedding")[0], F.col("embedding")[1], F.lit(0), mark=F.col("label"))


def read_points(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """Points from CSV, JSON or Parquet in the common schema."""
    reader = spark.read.schema(SCHEMA)
    return reader.csv(path, header=True) if fmt == "csv" else reader.format(fmt).load(path)


def cleaned(df: DataFrame, fill_by: str | None = None, x: str = "x", y: str = "y") -> DataFrame:
    """Missing coordinates filled with their group's mean (all rows' without a group), the rest dropped."""
    group = [fill_by] if fill_by else []
    means = df.groupBy(*group).agg(F.avg(x).alias("__x"), F.avg(y).alias("__y"))
    out = df.join(means, group, "left") if group else df.crossJoin(F.broadcast(means))
    return out.withColumn(x, F.coalesce(x, "__x")).withColumn(y, F.coalesce(y, "__y")).drop("__x", "__y").na.drop(subset=[x, y])


def projected(lon: Column, lat: Column, kind: str = "equirectangular", lat0: float = 0.0, radius: float = 6_371_008.8) -> tuple[Column, Column]:
    """Planar coordinates in metres."""
    if kind == "equirectangular":
        return F.radians(lon) * F.cos(F.radians(F.lit(lat0))) * radius, F.radians(lat) * radius
    if kind == "mercator":
        return F.radians(lon) * radius, F.log(F.tan(F.lit(0.7853981633974483) + F.radians(lat) / 2)) * radius
    raise ValueError(f"unknown projection {kind}")


def ring_from_wkt(text: str) -> tuple[tuple[float, float], ...]:
    """The outer ring of a WKT polygon."""
    body = text.strip()
    if not body.upper().startswith("POLYGON"):
        raise ValueError("not a polygon")
    outer = body[body.index("((") + 2 : body.index(")", body.index("(("))]
    ring = [tuple(float(v) for v in pair.split()[:2]) for pair in outer.split(",")]
    return tuple(ring[:-1] if ring[0] == ring[-1] else ring)
