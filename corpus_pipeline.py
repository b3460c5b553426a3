"""The corpus pipeline: stages that each filter, mix or place documents.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes
each result and reads it back as the next stage's documents. Each stage keeps
the defined cases of its operator, stated in that operator's module.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stkfun.functions.shared import settle
from stkfun.llm import ftrl_quality, simhash_pivots, slot_sharding, source_mix, tiling_decontam


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the trained classifier rejects go."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = ftrl_quality.fit(docs, labels, training=ftrl_quality.in_training(F.col("doc_id")))
    return ftrl_quality.keep_good(docs, model)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays."""
    return simhash_pivots.keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak a benchmark item go."""
    return tiling_decontam.keep_clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mixture takes them."""
    return source_mix.mixed(docs)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its slot and shard."""
    return slot_sharding.sharded(docs)


STAGES = [
    ("quality classifier", quality_filter),
    ("simhash near-dedup", near_dedup),
    ("benchmark decontamination", decontaminate),
    ("mixing to target weights", mix_sources),
    ("sharding", shard),
]

#: Fingerprints and the trained classifier have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = settle(stage(spark, docs, sf_dir), f"stage{k}")
    return docs
