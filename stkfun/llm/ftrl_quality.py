"""Quality classifier: hashed word n-gram logistic regression trained by
follow-the-regularised-leader, scored as sparse dot products.

Features are lower-cased words, pairs of neighbouring words, and the same two
over word shapes (letters, digits and marks with repeats folded), hashed into a
fixed number of slots; each family is averaged over its tokens. The model is
fitted in one task from a bounded sample of labelled ids (the ``max_rows`` with
the smallest id hashes, in that order as far as ``max_features`` features reach);
scoring covers whole texts of all rows with a weight vector of fixed size, which
is all that the driver sees.

Defined cases: null, empty and wordless texts score by the intercept; rows are
kept one to one; null ids count as the empty text in the split and are never
trained on; several labels of one id count as their smallest, several texts of
one id as the one with the smallest hash; without any usable label of both kinds every score is the share of label 1 (0.5 if none);
extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.llm.batches import gram_hashes, lowered, small_batches, text_bytes, word_hashes, word_spans

SLOTS = 1 << 18
MAX_ROWS = 3000
MAX_FEATURES = 6_000_000
THRESHOLD = 0.7

_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[97:123] = 97
_SHAPE[128:] = 97
_SHAPE[65:91] = 65
_SHAPE[48:58] = 48


def shape_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each word's shape: classes of its characters, runs folded."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    kind = _SHAPE[raw]
    keep = np.ones(len(raw), bool)
    keep[1:] = kind[1:] != kind[:-1]
    keep[starts] = True
    place = np.concatenate([[0], np.cumsum(keep)])
    return word_hashes(kind[keep], place[starts], place[ends], seed=7)


def hashed_features(raw: np.ndarray, off: np.ndarray, slots: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """document, slot and value of each feature occurrence of a batch."""
    starts, ends, first = word_spans(raw, off)
    counts = np.diff(first)
    owner = np.repeat(np.arange(len(counts)), counts)
    docs, where, value = [], [], []
    for family, h in enumerate((word_hashes(lowered(raw), starts, ends), shape_hashes(raw, starts, ends))):
        for n in (1, 2):
            g = gram_hashes(h, n)
            inside = owner[: len(g)] == owner[n - 1 :] if len(g) else np.zeros(0, bool)
            o = owner[: len(g)][inside]
            docs.append(o)
            where.append(((g[inside] >> np.uint64(11 * family + 3 * n)) % np.uint64(slots)).astype(np.int64))
            value.append(1.0 / np.maximum(counts - n + 1, 1)[o])
    return np.concatenate(docs), np.concatenate(where), np.concatenate(value)


def split_of(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % parts


def _featurizer(slots: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 2 << 20):
            raw, off = text_bytes(batch.column("text"))
            doc, slot, value = hashed_features(raw, off, slots)
            cell, back = np.unique(doc * slots + slot, return_inverse=True)
            total = np.bincount(back, value, len(cell)).astype(np.float32)
            cuts = np.searchsorted(cell // slots, np.arange(batch.num_rows + 1))
            where = (cell % slots).astype(np.int32)
            slots_out = [where[a:b].tobytes() for a, b in zip(cuts, cuts[1:])]
            values_out = [total[a:b].tobytes() for a, b in zip(cuts, cuts[1:])]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("label"), batch.column("th"), pa.array(slots_out, pa.binary()), pa.array(values_out, pa.binary())], ["doc_id", "label", "th", "slots", "values"])

    return run


def ftrl_fit(rows: list[tuple[int, np.ndarray, np.ndarray]], slots: int = SLOTS, alpha: float = 2.0, beta: float = 1.0, l1: float = 1e-4, l2: float = 1e-4, epochs: int = 4) -> tuple[np.ndarray, float]:
    """Weights and intercept from (label, slots, values) rows, in their order."""
    z, n = np.zeros(slots + 1), np.zeros(slots + 1)

    def weight(at):
        zi = z[at]
        return np.where(np.abs(zi) <= l1, 0.0, (np.sign(zi) * l1 - zi) / ((beta + np.sqrt(n[at])) / alpha + l2))

    for _ in range(epochs):
        for label, slot, value in rows:
            at, x = np.append(slot, slots), np.append(value * 10.0, 1.0)
            w = weight(at)
            p = 1.0 / (1.0 + np.exp(-np.clip(w @ x, -35, 35)))
            g = (p - label) * x
            g2 = g * g
            z[at] += g - (np.sqrt(n[at] + g2) - np.sqrt(n[at])) / alpha * w
            n[at] += g2
    w = weight(np.arange(slots + 1))
    return (w[:-1] * 10.0).astype(np.float32), float(w[-1])


def _fitter(slots: int, max_features: int):
    """One row of weights and intercept from the feature rows of one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        for batch in batches:
            for label, where, value in zip(batch.column("label").to_pylist(), batch.column("slots"), batch.column("values")):
                held += len(where.as_buffer()) // 4
                if not rows or held <= max_features:
                    rows.append((label, np.frombuffer(where.as_py(), np.int32), np.frombuffer(value.as_py(), np.float32)))
        ones = sum(r[0] for r in rows)
        if ones in (0, len(rows)):
            share = ones / len(rows) if rows else 0.5
            weights, bias = np.zeros(slots, np.float32), float(np.log(max(share, 1e-6) / max(1 - share, 1e-6)))
        else:
            weights, bias = ftrl_fit(rows, slots)
        yield pa.RecordBatch.from_arrays([pa.array([weights.tobytes()], pa.binary()), pa.array([bias])], ["weights", "bias"])

    return run


def fit(docs: DataFrame, labels: DataFrame, slots: int = SLOTS, max_rows: int = MAX_ROWS, max_features: int = MAX_FEATURES, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", training: Column | None = None) -> tuple[np.ndarray, float]:
    """Train on at most ``max_rows`` labelled ids; ``training`` restricts the ids."""
    lab = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label")).where("doc_id is not null and label in (0, 1)")
    if training is not None:
        lab = lab.where(training)
    lab = lab.groupBy("doc_id").agg(F.min("label").alias("label"))
    chosen = lab.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).where("doc_id is not null")
    src = src.join(F.broadcast(chosen), "doc_id").select("doc_id", "label", F.xxhash64("text").alias("th"), "text")
    got = src.mapInArrow(_featurizer(slots), "doc_id long, label int, th long, slots binary, values binary")
    one = got.groupBy("doc_id").agg(F.min(F.struct("th", "label", "slots", "values")).alias("r")).select("doc_id", "r.label", "r.slots", "r.values")
    row = one.repartition(1).sortWithinPartitions(F.xxhash64("doc_id"), "doc_id").select("label", "slots", "values").mapInArrow(_fitter(slots, max_features), "weights binary, bias double").first()
    if row is None:  # no labelled row at all
        return np.zeros(slots, np.float32), 0.0
    return np.frombuffer(row.weights, np.float32), row.bias


def _scorer(weights: np.ndarray, bias: float):
    slots = len(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 2 << 20):
            raw, off = text_bytes(batch.column("text"))
            doc, slot, value = hashed_features(raw, off, slots)
            dot = np.bincount(doc, weights[slot] * value, batch.num_rows) if len(doc) else np.zeros(batch.num_rows)
            score = 1.0 / (1.0 + np.exp(-np.clip(dot + bias, -35, 35)))
            keep = [n for n in batch.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in keep), pa.array(score)], [*keep, "score"])

    return run


def score(docs: DataFrame, model: tuple[np.ndarray, float], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and score (0 to 1) of every row."""
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(_scorer(*model), "doc_id long, score double")


def _keeper(weights: np.ndarray, bias: float, threshold: float, text_at: int):
    slots = len(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in small_batches([batch], batch.schema.names[text_at], 2 << 20):
                raw, off = text_bytes(part.column(text_at))
                doc, slot, value = hashed_features(raw, off, slots)
                dot = np.bincount(doc, weights[slot] * value, part.num_rows) if len(doc) else np.zeros(part.num_rows)
                ok = 1.0 / (1.0 + np.exp(-np.clip(dot + bias, -35, 35))) >= threshold
                if ok.any():
                    yield part.filter(pa.array(ok))

    return run


def keep_good(docs: DataFrame, model: tuple[np.ndarray, float], threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the model does not reject, all columns as they are."""
    return docs.mapInArrow(_keeper(*model, threshold, docs.columns.index(text_col)), docs.schema)


def in_training(doc_id: Column) -> Column:
    """The split of the quality query: remainder 2 modulo 4 is held out."""
    return split_of(doc_id, 4) != 2


def op9_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = fit(docs, labels, training=in_training(F.col("doc_id")))
    held = ~in_training(F.col("doc_id"))
    return score(docs, model).select("doc_id", held.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
