"""Benchmark decontamination by greedy string tiling.

Benchmark items meet documents by shared seeds (runs of ``min_match`` words);
for each (document, item) whose seeds could cover enough of the item, the
longest common runs are marked first, then shorter ones that do not overlap
them, by running Karp-Rabin hashes of falling length. An item counts as leaked
when the tiles cover at least ``threshold`` of its words, in whatever order.

Items travel to the executors in blocks of at most ``block_words`` words (one
item at least), a fixed size; every document passes all blocks one after the
other in its own row, which carries what was found so far.

Defined cases: null and wordless texts match nothing; items shorter than
``min_match`` words cannot form a tile and are never matched; repeated items and
documents are each judged; ties of coverage name the smallest item id; an empty
benchmark leaves every document clean; only id and text columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.llm.batches import gram_hashes, lowered, small_batches, text_bytes, word_hashes, word_spans

MIN_MATCH = 3
THRESHOLD = 0.5
BLOCK_WORDS = 2_000_000
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_INV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.ones(n, np.uint64)
    if n > 1:
        out[1:] = np.multiply.accumulate(np.full(n - 1, base, np.uint64))
    return out


class RunningHash:
    """Karp-Rabin hashes of all windows of any length of one token sequence."""

    def __init__(self, tokens: np.ndarray):
        n = len(tokens)
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(tokens * _powers(_BASE, n), dtype=np.uint64)])
        self.shift = _powers(_BASE_INV, n)

    def windows(self, size: int) -> np.ndarray:
        k = len(self.sums) - size
        return (self.sums[size:] - self.sums[:k]) * self.shift[:k] if k > 0 else np.zeros(0, np.uint64)


def free_windows(marked: np.ndarray, size: int) -> np.ndarray:
    """Starts of windows without a marked token."""
    if len(marked) < size:
        return np.zeros(0, np.int64)
    upto = np.concatenate([[0], np.cumsum(marked)])
    return np.flatnonzero(upto[size:] == upto[:-size])


def tile(pattern: np.ndarray, text: np.ndarray, min_match: int, blocked: np.ndarray | None = None) -> int:
    """Pattern tokens covered by greedy tiles; ``blocked`` text positions match nothing."""
    p_mark, t_mark = np.zeros(len(pattern), bool), np.zeros(len(text), bool) if blocked is None else blocked.copy()
    p_hash, t_hash = RunningHash(pattern), RunningHash(text)
    size = min(len(pattern), len(text))
    while size >= min_match:
        p_at, t_at = free_windows(p_mark, size), free_windows(t_mark, size)
        found = False
        if len(p_at) and len(t_at):
            ph, th = p_hash.windows(size)[p_at], t_hash.windows(size)[t_at]
            order = np.argsort(ph, kind="stable")
            lo, hi = np.searchsorted(ph[order], th, "left"), np.searchsorted(ph[order], th, "right")
            for k in np.flatnonzero(hi > lo):
                t = t_at[k]
                if t_mark[t : t + size].any():
                    continue
                for p in p_at[order[lo[k] : hi[k]]]:
                    if not p_mark[p : p + size].any() and (pattern[p : p + size] == text[t : t + size]).all():
                        p_mark[p : p + size] = t_mark[t : t + size] = found = True
                        break
        size = size - 1 if found or size <= 8 else max(8, _next_size(p_hash, t_hash, p_mark, t_mark, size))
    return int(p_mark.sum())


def _next_size(p_hash, t_hash, p_mark, t_mark, size: int) -> int:
    """The longest length below ``size`` at which anything matches, by bisection."""
    low, high = 7, size - 1
    while low < high:
        mid = (low + high + 1) // 2
        ph, th = p_hash.windows(mid)[free_windows(p_mark, mid)], t_hash.windows(mid)[free_windows(t_mark, mid)]
        if len(ph) and len(th) and np.isin(ph, th).any():
            low = mid
        else:
            high = mid - 1
    return low


def hashed_words(text: str | None) -> np.ndarray:
    raw = lowered(np.frombuffer((text or "").encode(), np.uint8))
    starts, ends, _ = word_spans(raw, np.array([0, len(raw)]))
    return word_hashes(raw, starts, ends)


class SeedTable:
    """Items of one block, found by the hash of any run of ``min_match`` words."""

    def __init__(self, items: list[tuple[int, np.ndarray]], min_match: int):
        self.items, self.n = items, min_match
        grams = [gram_hashes(t, min_match) for _, t in items]
        keys = np.concatenate(grams) if grams else np.zeros(0, np.uint64)
        owner = np.repeat(np.arange(len(items)), [len(g) for g in grams])
        order = np.argsort(keys, kind="stable")
        self.keys, self.owner = keys[order], owner[order]
        self.at = np.concatenate([np.arange(len(g)) for g in grams])[order] if grams else np.zeros(0, np.int64)
        self.unique = np.unique(self.keys)

    def leaks(self, tokens: np.ndarray, grams: np.ndarray, hits: np.ndarray, threshold: float) -> list[tuple[int, float]]:
        """(item id, coverage) of every item that the document leaks; hits: seed positions."""
        seeds = np.unique(grams[hits])
        lo, hi = np.searchsorted(self.keys, seeds, "left"), np.searchsorted(self.keys, seeds, "right")
        many = hi - lo
        # Each seed once, however often the document has it: no more rows than the block has seeds.
        seed = np.repeat(lo, many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        who, where = self.owner[seed], self.at[seed]
        out = []
        order = np.argsort(who, kind="stable")
        cuts = np.flatnonzero(np.diff(who[order])) + 1
        for group in np.split(order, cuts):
            item_id, pattern = self.items[who[group[0]]]
            need = threshold * len(pattern) - 1e-9
            if not self._could(where[group], len(pattern), need):
                continue
            place = hits[np.isin(grams[hits], self.keys[seed[group]])]
            spots = np.unique((place[:, None] + np.arange(self.n)).ravel())
            gap = np.concatenate([[False], np.diff(spots) > 1])
            slot = np.arange(len(spots)) + np.cumsum(gap)
            text = np.zeros(slot[-1] + 1, np.uint64)
            blocked = np.ones(len(text), bool)
            text[slot], blocked[slot] = tokens[spots], False
            covered = tile(pattern, text, self.n, blocked)
            if covered >= need:
                out.append((item_id, covered / len(pattern)))
        return out

    def _could(self, where: np.ndarray, size: int, need: float) -> bool:
        seen = np.zeros(size, bool)
        for k in range(self.n):
            seen[where + k] = True
        return seen.sum() >= need


_FOUND = ["doc_id", "text", "n_items", "best_item", "coverage", "items"]


def _judge(table: SeedTable, threshold: float, text_col: str, keep: bool):
    """Keep clean rows, or add this block's leaks to the rows' own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, text_col):
            raw, off = text_bytes(batch.column(text_col))
            raw = lowered(raw)
            starts, ends, first = word_spans(raw, off)
            tokens = word_hashes(raw, starts, ends)
            grams = gram_hashes(tokens, table.n)
            pos = np.searchsorted(table.unique, grams)
            hit = np.zeros(len(grams), bool)
            inside = pos < len(table.unique)
            hit[inside] = table.unique[pos[inside]] == grams[inside]
            at = np.flatnonzero(hit)
            cuts = np.searchsorted(at, first)
            found = []
            for d in range(batch.num_rows):
                here = at[cuts[d] : cuts[d + 1]]
                here = here[here + table.n <= first[d + 1]]
                base = first[d]
                leaks = table.leaks(tokens[base : first[d + 1]], grams[base:], here - base, threshold) if len(here) else []
                found.append(sorted(leaks, key=lambda x: (-x[1], x[0] is None, x[0])))
            if keep:
                clean = pa.array([not f for f in found])
                yield batch.filter(clean)
            else:
                items = [[*(had or []), *(i for i, _ in f)] for had, f in zip(batch.column("items").to_pylist(), found)]
                before = zip(batch.column("coverage").to_pylist(), batch.column("best_item").to_pylist())
                best = [min([(-c, i)] * (c > 0) + [(-x, k) for k, x in f[:1]], key=lambda v: (v[0], v[1] is None, v[1]), default=(0.0, None)) for (c, i), f in zip(before, found)]
                columns = [batch.column("doc_id"), batch.column("text"), pa.array([len(x) for x in items], pa.int64()), pa.array([i for _, i in best], pa.int64()), pa.array([abs(c) for c, _ in best], pa.float64()), pa.array(items, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(columns, _FOUND)

    return run


def seed_blocks(benchmark: DataFrame, min_match: int = MIN_MATCH, block_words: int = BLOCK_WORDS, item_col: str = "item_id", text_col: str = "text") -> Iterator[SeedTable]:
    """The benchmark in blocks of bounded size; one empty block if it has no items."""
    held, words, any_block = [], 0, False
    for row in benchmark.select(F.col(item_col).cast("long").alias("i"), F.col(text_col).cast("string").alias("t")).orderBy("i").toLocalIterator():
        tokens = hashed_words(row.t)
        if len(tokens) < min_match:
            continue
        held.append((row.i, tokens))
        words += len(tokens)
        if words >= block_words:
            yield SeedTable(held, min_match)
            held, words, any_block = [], 0, True
    if held or not any_block:
        yield SeedTable(held, min_match)


def contamination(docs: DataFrame, benchmark: DataFrame, min_match: int = MIN_MATCH, threshold: float = THRESHOLD, block_words: int = BLOCK_WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_items, best_item, coverage, items of every row."""
    schema = "doc_id long, text string, n_items long, best_item long, coverage double, items array<long>"
    none = [F.lit(0).cast("long").alias("n_items"), F.lit(None).cast("long").alias("best_item"), F.lit(0.0).alias("coverage"), F.array().cast("array<long>").alias("items")]
    out = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), *none)
    for table in seed_blocks(benchmark, min_match, block_words):
        out = out.mapInArrow(_judge(table, threshold, "text", False), schema)
    return out.drop("text")


def keep_clean(docs: DataFrame, benchmark: DataFrame, min_match: int = MIN_MATCH, threshold: float = THRESHOLD, block_words: int = BLOCK_WORDS, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that leak no item, all columns as they are."""
    for table in seed_blocks(benchmark, min_match, block_words):
        docs = docs.mapInArrow(_judge(table, threshold, text_col, True), docs.schema)
    return docs


def op10_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.select("doc_id", (F.col("n_items") > 0).alias("contaminated"), "n_items", "best_item", "coverage", "items")
