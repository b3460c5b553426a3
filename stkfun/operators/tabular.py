"""Filters, counts, maps and simple point statistics around the K function."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.config import HOUR, StudyWindow
from stkfun.operators.pairs import knn, neighbours


def filter_points(points: DataFrame, zone: int | list[int] | None = None, mark: str | list[str] | None = None, since: int | None = None, until: int | None = None, box: tuple[float, float, float, float] | None = None) -> DataFrame:
    """Area level, category and time filters; each is pushed to the scan where it can be."""
    out = points
    if zone is not None:
        out = out.where(F.col("zone").isin(zone if isinstance(zone, list) else [zone]))
    if mark is not None:
        out = out.where(F.col("mark").isin(mark if isinstance(mark, list) else [mark]))
    if since is not None:
        out = out.where(F.col("t0") >= since)
    if until is not None:
        out = out.where(F.col("t0") < until)
    if box is not None:
        out = out.where(F.col("x").between(box[0], box[1]) & F.col("y").between(box[2], box[3]))
    return out


def counts_cube(df: DataFrame, dims: list[str], kind: str = "cube") -> DataFrame:
    """Precomputed counts over all combinations (cube) or along a hierarchy (rollup)."""
    grouped = df.cube(*dims) if kind == "cube" else df.rollup(*dims)
    return grouped.agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def heat_map(points: DataFrame, window: StudyWindow, nx: int, ny: int) -> DataFrame:
    """Counts by cell; empty cells are left out."""
    gx = F.least(F.floor((F.col("x") - window.x0) / ((window.x1 - window.x0) / nx)), F.lit(nx - 1)).cast("int")
    gy = F.least(F.floor((F.col("y") - window.y0) / ((window.y1 - window.y0) / ny)), F.lit(ny - 1)).cast("int")
    return points.select(gx.alias("gx"), gy.alias("gy")).groupBy("gx", "gy").agg(F.count("*").alias("n"))


def surface_matrix(surface: DataFrame, t_steps: int, value: str = "l") -> DataFrame:
    """One row for each s, one column for each ti."""
    return surface.groupBy("si").pivot("ti", list(range(1, t_steps + 1))).agg(F.first(value))


def export_surface(df: DataFrame, path: str, fmt: str = "json") -> None:
    """Small result tables as JSON, CSV or Parquet."""
    writer = df.coalesce(1).write.mode("overwrite")
    writer.option("header", True).csv(path) if fmt == "csv" else writer.format(fmt).save(path)


def quadrat_test(points: DataFrame, window: StudyWindow, nx: int, ny: int, nt: int) -> DataFrame:
    """Variance over mean of cell counts, empty cells included, and its chi-square."""
    cell = [F.least(F.floor((F.col(c) - o) / z), F.lit(n - 1)) for c, o, z, n in (("x", window.x0, (window.x1 - window.x0) / nx, nx), ("y", window.y0, (window.y1 - window.y0) / ny, ny), ("t0", window.t_start, window.period / nt, nt))]
    counts = points.groupBy(*[c.alias(k) for c, k in zip(cell, "xyt")]).agg(F.count("*").alias("m"))
    cells = nx * ny * nt
    one = counts.agg(F.sum("m").alias("n"), F.sum(F.col("m") * F.col("m")).alias("sq"), F.count("*").alias("used"))
    mean = F.col("n") / cells
    var = (F.col("sq") - F.col("n") * mean) / (cells - 1)
    return one.select("n", F.lit(cells).alias("cells"), "used", mean.alias("mean"), var.alias("variance"), (var / mean).alias("ratio"), (var / mean * (cells - 1)).alias("chi2"))


def nearest_neighbour_index(points: DataFrame, window: StudyWindow, start: float) -> DataFrame:
    """Mean distance to the nearest other place over that of a random pattern, 0.5 / sqrt(density)."""
    flat = points.withColumns({"t0": F.lit(0).cast("long"), "t1": F.lit(0).cast("long")})
    near = knn(flat, 1, 1.0, start)
    n = points.agg(F.count("*").alias("n"))
    got = near.agg(F.avg("r").alias("mean"), F.count("*").alias("found")).crossJoin(F.broadcast(n))
    return got.select("n", "mean", (F.lit(0.5) / F.sqrt(F.col("n") / window.area)).alias("expected")).withColumn("index", F.col("mean") / F.col("expected"))


def kde(points: DataFrame, window: StudyWindow, nx: int, ny: int, nt: int, hs: float, ht: int) -> DataFrame:
    """Space-time density at grid centres: Epanechnikov kernels of bandwidth hs and ht (µs)."""
    spark = points.sparkSession
    step = [(window.x1 - window.x0) / nx, (window.y1 - window.y0) / ny, window.period / nt]
    grid = spark.range(nx * ny * nt).select(
        F.col("id"), (F.lit(window.x0) + (F.col("id") % nx + 0.5) * step[0]).alias("x"), (F.lit(window.y0) + (F.floor(F.col("id") / nx) % ny + 0.5) * step[1]).alias("y"),
        (F.lit(window.t_start) + F.floor((F.floor(F.col("id") / (nx * ny)) + 0.5) * step[2])).cast("long").alias("t0"),
    ).withColumn("t1", F.col("t0"))
    asked = grid.withColumn("id", -1 - F.col("id"))
    got = neighbours(points, asked, hs, ht)
    space = (2 / math.pi / hs**2) * (1 - F.col("d") * F.col("d") / hs**2)
    time = (0.75 / (ht / HOUR)) * (1 - F.pow(F.col("u") / float(ht), F.lit(2)))
    dens = got.groupBy((-1 - F.col("i")).alias("id")).agg(F.sum(space * time).alias("density"), F.count("*").alias("n"))
    return grid.join(dens, "id", "left").select("id", "x", "y", "t0", F.coalesce("density", F.lit(0.0)).alias("density"), F.coalesce("n", F.lit(0)).alias("n"))
