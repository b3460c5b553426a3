"""Sharding by a permutation-filled lookup table.

Every shard has a preference order over the slots of a prime-sized table (an
offset and a stride from its name's hash). Shards take turns; each claims its
next preferred slot that is still free, until the table is full. Shards thus
hold equal numbers of slots within one, and removing a shard moves few keys
beside its own. A document's slot is its id's hash modulo the table size; the
broadcast table gives the shard in constant time, without a shuffle.

Defined cases: a null id counts as the text "null"; repeated rows share a shard;
texts are not read; an empty table gives an empty result; other columns are
carried, and replaced where they are called slot or shard.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SHARDS = 32
SLOTS = 2053


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def name_hash(kind: str, name: str) -> int:
    return int(hashlib.md5(f"{kind}:{name}".encode()).hexdigest()[:8], 16)


def fill_slots(names: list[str], slots: int = SLOTS) -> list[int]:
    """Index of the shard that holds each slot."""
    if not is_prime(slots) or slots < len(names) or not names:
        raise ValueError("slots must be a prime that is not below the number of shards")
    start = [name_hash("offset", n) % slots for n in names]
    step = [name_hash("stride", n) % (slots - 1) + 1 for n in names]
    turn, owner, left = [0] * len(names), [-1] * slots, slots
    while left:
        for i in range(len(names)):
            while owner[at := (start[i] + turn[i] * step[i]) % slots] >= 0:
                turn[i] += 1
            owner[at] = i
            left -= 1
            if not left:
                break
    return owner


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    head = F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("null"))), 1, 8)
    return (F.conv(head, 16, 10).cast("long") % slots).cast("int")


def slot_table(spark: SparkSession, names: list[str], slots: int = SLOTS) -> DataFrame:
    """slot, shard: one row a slot; its size is the parameter ``slots``."""
    line = ",".join(map(str, fill_slots(names, slots)))
    return spark.range(1).select(F.posexplode(F.split(F.lit(line), ",").cast("array<int>")).alias("slot", "shard"))


def sharded(docs: DataFrame, shards: int = SHARDS, slots: int = SLOTS, id_col: str = "doc_id") -> DataFrame:
    """``docs`` with slot and shard."""
    table = slot_table(docs.sparkSession, [f"shard-{i}" for i in range(shards)], slots)
    carried = docs.drop("slot", "shard") if id_col not in ("slot", "shard") else docs
    placed = carried.withColumn("slot", slot_of(F.col(id_col), slots))
    return placed.join(F.broadcast(table), "slot").select(*[c for c in carried.columns], "slot", "shard")


def write_sharded(docs: DataFrame, path: str, **params) -> None:
    """Parquet folders, one for each shard."""
    sharded(docs, **params).drop("slot").write.partitionBy("shard").parquet(path)


def op3_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return sharded(docs.select("doc_id", "n_chars")).select("doc_id", "n_chars", "slot", "shard")


OP3_SQL = f"""
WITH RECURSIVE shard AS (
  SELECT i, CAST(('0x' || substr(md5('offset:shard-' || i), 1, 8)) AS BIGINT) % {SLOTS} AS o,
         CAST(('0x' || substr(md5('stride:shard-' || i), 1, 8)) AS BIGINT) % ({SLOTS} - 1) + 1 AS s
  FROM range({SHARDS}) t(i)),
pref AS (SELECT i, list((o + k * s) % {SLOTS} ORDER BY k) AS wish FROM shard, range({SLOTS}) r(k) GROUP BY i),
fill(step, owner, slot) AS (
  SELECT 0, list_transform(range({SLOTS}), lambda x: -1), CAST(-1 AS BIGINT)
  UNION ALL
  SELECT step + 1, list_transform(owner, lambda x, p: CASE WHEN p = pick + 1 THEN i ELSE x END), pick
  FROM (SELECT f.step, f.owner, p.i, list_filter(p.wish, lambda x: f.owner[x + 1] < 0)[1] AS pick
        FROM fill f JOIN pref p ON p.i = f.step % {SHARDS} WHERE f.step < {SLOTS})),
lookup AS (SELECT slot, (step - 1) % {SHARDS} AS shard FROM fill WHERE slot >= 0),
d AS (SELECT doc_id, n_chars, CAST(('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 8)) AS BIGINT) % {SLOTS} AS slot FROM documents)
SELECT doc_id, n_chars, CAST(d.slot AS INTEGER) AS slot, CAST(shard AS INTEGER) AS shard FROM d JOIN lookup USING (slot)
"""
