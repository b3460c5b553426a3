"""Tables written once to the folder that the driver and all executors share.

Everything goes to one folder of the application, which is removed when the
driver's process ends, or before by ``discard``.
"""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``; a private one only where none is
    set and driver and executors are one process."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="stkfun-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


_KNOWN: set[str] = set()


def scratch(spark: SparkSession, label: str) -> str:
    """A new path in the application's folder."""
    home = f"{shared_root(spark)}/stkfun/{spark.sparkContext.applicationId}"
    if home not in _KNOWN:
        _KNOWN.add(home)
        atexit.register(_forget, spark.sparkContext._jvm, home)
    return f"{home}/{label}-{uuid.uuid4().hex}"


def _forget(jvm, home: str) -> None:
    with contextlib.suppress(Exception):  # the JVM may have ended before
        path = jvm.org.apache.hadoop.fs.Path(home)
        path.getFileSystem(jvm.org.apache.hadoop.conf.Configuration()).delete(path, True)


def discard(spark: SparkSession) -> None:
    """Remove all that this application has written so far; its results must have been read."""
    home = f"{shared_root(spark)}/stkfun/{spark.sparkContext.applicationId}"
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(home)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def settle_counted(df: DataFrame, label: str, **sums: Column) -> tuple[DataFrame, dict]:
    """``settle`` with sums over the rows taken while they are written (null without rows)."""
    seen = Observation()
    return settle(df.observe(seen, *[s.alias(n) for n, s in sums.items()]), label), seen.get


def settle(df: DataFrame, label: str = "table") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there,
    a lost executor costs no recomputation, later readers share one result."""
    spark = df.sparkSession
    path = scratch(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
