"""Point streams: windowed counts, pairs by interval joins, incremental bins."""

from __future__ import annotations

from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stkfun.config import DistanceGrid
from stkfun.functions.shared import scratch


def event_stream(spark: SparkSession, sf_dir: str, delay: str = "1 day", name: str = "events") -> DataFrame:
    """Events as a file stream of points with a watermark."""
    like = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    raw = spark.readStream.schema(like).option("pathGlobFilter", f"*{name}*.parquet").parquet(sf_dir)
    y = F.get_json_object("props", "$.k").cast("double")
    return raw.select(F.col("event_id").alias("id"), F.col("value").alias("x"), y.alias("y"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("mark")).withWatermark("ts", delay)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end of what is there and return the result as a table."""
    spark = stream.sparkSession
    out = scratch(spark, "stream")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{out}-log").trigger(availableNow=True).start()
    else:
        q = stream.writeStream.outputMode(mode).foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(out)).option("checkpointLocation", f"{out}-log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def window_counts(points: DataFrame, size: str = "6 hours", slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return points.groupBy(w.alias("w"), "mark").agg(F.count("*").alias("n"), F.sum("x").alias("sum_x")).select(F.unix_micros("w.start").alias("start"), "mark", "n", "sum_x")


def session_counts(points: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return points.groupBy(F.session_window("ts", gap).alias("w"), "mark").agg(F.count("*").alias("n")).select(F.unix_micros("w.start").alias("start"), "mark", "n")


def stream_pairs(points: DataFrame, s: float, hours: int) -> DataFrame:
    """Ordered pairs within s and the time bound, as a stream-stream join on cells."""
    cell = lambda c: F.floor(F.col(c) / s)
    steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in product((-1, 0, 1), repeat=2)])
    c = points.select(F.col("id").alias("ci"), F.col("x").alias("cx"), F.col("y").alias("cy"), F.col("ts").alias("ct"), F.explode(steps).alias("o")).withColumns({"ka": F.floor(F.col("cx") / s) + F.col("o.i"), "kb": F.floor(F.col("cy") / s) + F.col("o.j")}).drop("o")
    q = points.select(F.col("id").alias("qi"), F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("ts").alias("qt"), cell("x").alias("qa"), cell("y").alias("qb"))
    close = F.sqrt((F.col("cx") - F.col("qx")) * (F.col("cx") - F.col("qx")) + (F.col("cy") - F.col("qy")) * (F.col("cy") - F.col("qy"))) <= s
    bound = F.expr(f"qt between ct - interval {hours} hours and ct + interval {hours} hours")
    return c.join(q, (F.col("ka") == F.col("qa")) & (F.col("kb") == F.col("qb")) & bound & close & (F.col("ci") != F.col("qi"))).select(F.col("ci").alias("i"), F.col("qi").alias("j"))


def incremental_bins(points: DataFrame, grid: DistanceGrid) -> DataFrame:
    """Pair-bin deltas: the last t_max of points is state by cell; an arrival is compared
    with stored points of its neighbour cells. Deltas add up to the batch histogram.

    Each arrival goes to its 9 neighbour cells, is stored at home only, and compared at
    all; arrivals of a batch are taken in (time, id) order, each pair once, counted as
    two ordered pairs."""
    s, tmax, tstep, sstep, cs, ct = grid.s_max, grid.t_max, grid.t_step, grid.s_step, grid.s_steps, grid.t_steps
    steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in product((-1, 0, 1), repeat=2)])
    spread = points.select("id", "x", "y", F.unix_micros("ts").alias("t"), "ts", F.explode(steps).alias("o"))
    spread = spread.select("id", "x", "y", "t", "ts", (F.floor(F.col("x") / s) + F.col("o.i")).alias("a"), (F.floor(F.col("y") / s) + F.col("o.j")).alias("b"), ((F.col("o.i") == 0) & (F.col("o.j") == 0)).alias("home"))

    def step(key, batches, state):
        old = [np.array(v, dtype=k) for v, k in zip(state.get, ("i8", "f8", "f8", "i8"))] if state.exists else [np.zeros(0, k) for k in ("i8", "f8", "f8", "i8")]
        new = pd.concat(list(batches)).sort_values(["t", "id"])
        home = new["home"].to_numpy(bool)
        come = [new[c].to_numpy() for c in ("id", "x", "y", "t")]
        # What an arrival meets: the state, and arrivals before it whose home is here.
        ids, xs, ys, ts = (np.concatenate([o, c[home]]) for o, c in zip(old, come))
        until = len(old[0]) + np.cumsum(home) - home
        found = np.zeros((cs + 1, ct + 1), np.int64)
        for a in range(0, len(new), max(1, 2_000_000 // max(1, len(ids)))):
            i, x, y, t = (c[a : a + max(1, 2_000_000 // max(1, len(ids)))][:, None] for c in come)
            d, u = np.sqrt((xs - x) ** 2 + (ys - y) ** 2), np.abs(ts - t)
            ok = (np.arange(len(ids)) < until[a : a + len(i), None]) & (ids != i) & (d <= s) & (u <= tmax)
            si, ti = np.ceil(d[ok] / sstep).astype(int), -(-u[ok] // tstep)
            few = (si <= cs) & (ti <= ct)
            np.add.at(found, (si[few], ti[few]), 1)
        live = ts >= state.getCurrentWatermarkMs() * 1000 - tmax
        state.update(tuple(v[live].tolist() for v in (ids, xs, ys, ts)))
        si, ti = np.nonzero(found)
        yield pd.DataFrame({"si": si.astype("int32"), "ti": ti.astype("int32"), "n": found[si, ti]})

    return spread.groupBy("a", "b").applyInPandasWithState(step, "si int, ti int, n long", "ids array<long>, xs array<double>, ys array<double>, ts array<long>", "append", "NoTimeout")
