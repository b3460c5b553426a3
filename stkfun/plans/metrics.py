"""Cost measures: times without input and output, ratios, and comparison counts."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import asdict, dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.operators.local_index import BUILDERS


@dataclass
class Run:
    """One timed run; fields of the ``runs`` table."""

    workload: str
    variant: str
    n: int
    v: int = 4
    m: int = 0
    s_max: float = 0.0
    t_max: int = 0
    p: int = 0
    cores: int = 0
    seconds: float = 0.0
    sf: float | None = None
    af: float | None = None
    comparisons: int | None = None
    pairs: int | None = None
    hits: int | None = None

    def row(self) -> dict:
        return asdict(self)


def ready(df: DataFrame) -> DataFrame:
    """Cached and materialised, so that a timing has no input."""
    df = df.persist()
    df.count()
    return df


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds until all rows of the result are made (they are not written)."""
    begin = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - begin


def measured(spark, run: Callable[[], DataFrame]) -> dict:
    """``timed``, with what its stages shuffled, spilled and held at once (MB)."""
    sc, group = spark.sparkContext, uuid.uuid4().hex
    sc.setJobGroup(group, "measured")
    try:
        seconds = timed(run)
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    stages = {i for j in tracker.getJobIdsForGroup(group) for i in tracker.getJobInfo(j).stageIds}
    ran = [x for x in (store.lastStageAttempt(i) for i in stages) if x.numCompleteTasks()]
    total = lambda name: sum(getattr(x, name)() for x in ran) / 1e6
    return {
        "seconds": seconds, "stages": len(ran), "shuffle_write_mb": total("shuffleWriteBytes"), "shuffle_read_mb": total("shuffleReadBytes"),
        "spill_mb": total("diskBytesSpilled"), "peak_execution_mb": max((x.peakExecutionMemory() for x in ran), default=0) / 1e6,
    }


def speedup(original: float, optimised: float) -> float:
    return original / optimised


def acceleration(standalone: float, distributed: float) -> float:
    return standalone / distributed


def index_stats(points: DataFrame, kind: str, s: float, t: int, capacity: int = 32) -> DataFrame:
    """Shape of an index over each partition, its build time, and what queries of all its
    points visit and compare."""

    def run(parts):
        rows = [p for p in parts if len(p)]
        if not rows:
            return
        xyz = pd.concat(rows)[["x", "y", "t0"]].to_numpy(float)
        begin = time.perf_counter()
        tree = BUILDERS[kind](xyz, 1 if kind == "kdtree" else capacity)
        built = time.perf_counter() - begin
        hits = sum(len(a) for a, _ in tree.query(xyz, xyz, s, float(t)))
        yield pd.DataFrame([tree.stats() | {"kind": kind, "n": len(xyz), "pairs": hits - len(xyz), "build_s": built}])

    got = points.select("x", "y", "t0").mapInPandas(run, "nodes long, leaves long, height int, largest_leaf long, visited long, compared long, kind string, n long, pairs long, build_s double")
    return got.groupBy("kind").agg(*[F.sum(c).alias(c) for c in ("n", "nodes", "leaves", "visited", "compared", "pairs")], F.max("height").alias("height"), F.max("largest_leaf").alias("largest_leaf"), F.sum("build_s").alias("build_s"))


def pair_stats(points: DataFrame, s: float, t: int) -> DataFrame:
    """Comparisons of all pairs, of the threshold cells, and pairs kept."""
    from stkfun.operators.pairs import pairs_cells

    n = points.agg(F.count("*").alias("n"))
    cells = points.groupBy(F.floor(F.col("x") / s).alias("a"), F.floor(F.col("y") / s).alias("b"), F.floor(F.col("t0") / t).alias("e")).agg(F.count("*").alias("m"))
    around = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.lit(k).alias("k")) for i in (-1, 0, 1) for j in (-1, 0, 1) for k in (-1, 0, 1)]))
    moved = cells.select("m", "a", "b", "e", around.alias("o")).select(F.col("m").alias("mc"), (F.col("a") + F.col("o.i")).alias("a"), (F.col("b") + F.col("o.j")).alias("b"), (F.col("e") + F.col("o.k")).alias("e"))
    compared = moved.join(cells, ["a", "b", "e"]).agg(F.sum(F.col("m") * F.col("mc")).alias("compared_cells"))
    kept = pairs_cells(points, s, t).agg(F.count("*").alias("pairs"))
    return n.crossJoin(compared).crossJoin(kept).select("n", (F.col("n") * (F.col("n") - 1)).alias("compared_all"), (F.col("compared_cells") - F.col("n")).alias("compared_cells"), "pairs")


def runs_table(spark, runs: list[Run]) -> DataFrame:
    return spark.createDataFrame(pd.DataFrame([r.row() for r in runs]).astype({"sf": float, "af": float, "comparisons": "Int64", "pairs": "Int64", "hits": "Int64"}).replace({np.nan: None}), "workload string, variant string, n long, v int, m int, s_max double, t_max long, p int, cores int, seconds double, sf double, af double, comparisons long, pairs long, hits long")
