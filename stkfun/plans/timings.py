"""Timed experiments: seconds, ratios and sizes of the workloads, one JSON line a run.

``python -m stkfun.plans.timings SF_DIR [name ...]`` runs index, cache, partitions,
codec, overall, ring (W2-W6, W8, W9) in this process' session and ``cores`` (W7) in
one process for each number of cores. Times are without input and output: points
are cached before, results are made and not kept. Cores stand in for nodes.
"""

from __future__ import annotations

import json
import subprocess
import sys
import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stkfun.config import G10, G_OVERALL, HOUR, W_EVENTS, DistanceGrid
from stkfun.functions import geometry as geo
from stkfun.operators import codec
from stkfun.operators import estimate as est
from stkfun.operators import pairs as pr
from stkfun.operators import partition as part
from stkfun.plans import job, metrics
from stkfun.plans.metrics import Run, speedup, timed
from stkfun.sources import points as src

W = W_EVENTS


def index(sp, d, fractions=(1 / 128, 1 / 64, 1 / 32, 1 / 16, 1 / 8, 1 / 4), kinds=("rtree", "octree", "kdtree"), n=50_000):
    """Estimation without an index (all pairs of a leaf-less join in time) and with each index; build times."""
    p = metrics.ready(src.events_skewed(sp, d).where(F.col("id") < n))
    for f in fractions:
        g = DistanceGrid.from_fraction(W, f)
        plain = timed(lambda: est.estimate_k(p, W, g, pairs=pr.pairs_sweep(p, g.s_max, g.t_max, window=W)))
        yield Run("index", "sweep", p.count(), s_max=g.s_max, t_max=g.t_max, seconds=plain)
        for kind in kinds:
            fast = timed(lambda: est.estimate_k(p, W, g, pairs=part.pairs_partitioned(p, W, g.s_max, g.t_max, 8, "grid", local=kind)))
            row = metrics.index_stats(p.coalesce(1), kind, g.s_max, g.t_max).first()
            yield Run("index", f"{kind} build {row.build_s:.3f} s", row.n, s_max=g.s_max, t_max=g.t_max, seconds=fast, sf=speedup(plain, fast), comparisons=row.compared, pairs=row.pairs)


def cache(sp, d, vertices=(4, 10, 50, 100, 500, 1000, 5000), n=50_000):
    p = src.events_skewed(sp, d).where(F.col("id") < n)
    found = metrics.ready(pr.pairs_cells(p, 5.0, 20 * HOUR, window=W).select("x", "y", "d"))
    keys = metrics.ready(found.groupBy("x", "y", "d").count())
    for v in vertices:
        weigh = geo.w_space_polygon(geo.rect_ring(W, v), early_exit=False)
        plain = timed(lambda: found.select(weigh("x", "y", "d").alias("w")))
        memo = timed(lambda: keys.select(weigh("x", "y", "d").alias("w")))
        yield Run("cache", "distinct keys", found.count(), v, seconds=memo, sf=speedup(plain, memo), hits=found.count() - keys.count())


def partitions(sp, d, parts=(8, 16, 64, 256, 1024, 2048), schemes=("hash", "grid", "quadtree", "rtree", "domain")):
    p, base = metrics.ready(src.events_skewed(sp, d)), {}
    for n in parts:
        for scheme in schemes:
            if scheme == "hash" and n > 64:
                continue  # every centre goes to nearly every hash leaf
            took = timed(lambda: part.pairs_partitioned(p, W, 5.0, 20 * HOUR, n, scheme).groupBy().count())
            base.setdefault(n if n <= 64 else 64, took if scheme == "hash" else None)
            yield Run("partitions", scheme, p.count(), p=n, s_max=5.0, t_max=20 * HOUR, seconds=took, sf=speedup(base.get(n) or base[64], took))


def codecs(sp, d):
    for name, points in (("events", src.events_skewed), ("orders", src.orders_month), ("lines", src.lineitem_grid)):
        row = codec.codec_stats(points(sp, d)).first()
        yield Run("codec", f"{name} sizes {row.size_d} {row.size_c}, ratios of size {row.cr:.1f}, writing {row.sr_s:.1f}, reading {row.sr_d:.1f}", row.n, seconds=row.ser_c + row.de_c, sf=(row.ser_d + row.de_d) / (row.ser_c + row.de_c))


def overall(sp, d, sizes=(10_000, 20_000, 50_000, 100_000), plain_up_to=20_000):
    """All strategies off and on, and the planner's choice; all pairs up to a size that ends."""
    for n in sizes:
        p = metrics.ready(src.events_skewed(sp, d).where(F.col("id") < n))
        plain = timed(lambda: job.job_surface(p, W, G_OVERALL, "plain")) if n <= plain_up_to else None
        for name, plan in (("none", job.NONE), ("all", job.ALL), ("planned", None), ("index", replace(job.NONE, index=True)), ("partition", replace(job.NONE, partitioner="domain", parts=64))):
            took = timed(lambda: job.job_surface(p, W, G_OVERALL, strategies=plan))
            yield Run("overall", name, p.count(), s_max=G_OVERALL.s_max, t_max=G_OVERALL.t_max, seconds=took, sf=speedup(plain, took) if plain else None)
        if plain:
            yield Run("overall", "plain", p.count(), s_max=G_OVERALL.s_max, t_max=G_OVERALL.t_max, seconds=plain)
        p.unpersist()


def ring(sp, d, sizes=(100_000, 200_000, 300_000, 400_000, 500_000)):
    """Uniform points in an 85-vertex outline."""
    w = W.with_ring(geo.ellipse_ring(85))
    for n in sizes:
        p = metrics.ready(src.clip(src.uniform_over(sp.range(int(n * W.area / w.area)), W), w))
        yield Run("ring", "estimation", p.count(), 85, s_max=G10.s_max, t_max=G10.t_max, seconds=timed(lambda: est.estimate_k(p, w, G10)))
        p.unpersist()


def one(sp, d):
    """A single run of the planned procedure, for ``cores``."""
    p = metrics.ready(src.events_skewed(sp, d))
    timed(lambda: p.groupBy().count())
    yield Run("one", "all", p.count(), seconds=timed(lambda: job.job_surface(p, W, G_OVERALL, strategies=job.ALL)))


EXPERIMENTS = {"index": index, "cache": cache, "partitions": partitions, "codec": codecs, "overall": overall, "ring": ring, "one": one}


def session(cores: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]").appName("stkfun-timings").config("spark.sql.shuffle.partitions", str(max(8, cores))).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def cores(sf_dir: str, numbers=(1, 2, 4, 8)) -> None:
    """The same run on more and more cores: the acceleration over one core."""
    alone = None
    for k in numbers:
        out = subprocess.run([sys.executable, "-m", "stkfun.plans.timings", sf_dir, "one", f"--cores={k}"], capture_output=True, text=True, check=True)
        row = json.loads(out.stdout.strip().splitlines()[-1])
        alone = alone or row["seconds"]
        print(json.dumps(row | {"workload": "cores", "cores": k, "af": metrics.acceleration(alone, row["seconds"])}), flush=True)


def main(args: list[str]) -> None:
    number = next((int(a.split("=")[1]) for a in args if a.startswith("--cores=")), 8)
    sf_dir, *names = [a for a in args if not a.startswith("--")]
    names = names or [*(n for n in EXPERIMENTS if n != "one"), "cores"]
    if names != ["cores"]:
        spark = session(number)
        for name in names:
            if name == "cores":
                continue
            begin = time.perf_counter()
            for run in EXPERIMENTS[name](spark, sf_dir):
                print(json.dumps(run.row() | {"cores": number}), flush=True)
            print(f"{name}: {time.perf_counter() - begin:.0f} s", file=sys.stderr)
            spark.catalog.clearCache()
        spark.stop()
    if "cores" in names:
        cores(sf_dir)


def runs(sp: SparkSession, rows: list[Run]) -> DataFrame:
    return metrics.runs_table(sp, rows)


if __name__ == "__main__":
    main(sys.argv[1:])
