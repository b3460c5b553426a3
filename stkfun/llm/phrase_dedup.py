"""Substring deduplication with repeated-phrase automata.

A word goes if some window of ``window`` words over it has a word sequence that
also starts anywhere else. Every window has a key phrase: the run of ``phrase``
words in it with the smallest hash, which depends on the window's words alone,
so equal windows meet at equal phrases.

1. All texts list their key phrases (as hashes) with the stretch of windows that
   each one rules; phrases that occur once cannot belong to a repeated window.
2. Passages are confirmed. A stretch is a passage of one key phrase; equal ones
   (by key phrase and a hash of all words) are counted, and those that start at
   least twice are confirmed with all their windows. The windows of all different
   stretches are counted in the same way, weighed by their stretches' numbers: that
   confirms what stretches that occur once share with others.
3. Texts are dealt in blocks of bounded size. A block's shard is an Aho-Corasick
   automaton of its texts' confirmed key phrases, with the passages and windows
   that each of them stands for. All texts of the block stream through it; around
   every located phrase the words are held against those passages and windows, and
   what agrees goes.

Counting aggregates before it shuffles, a join with counts has one row for each
(block, stretch) or each window of a stretch that occurs once, and a block is all
that a task holds, so no phrase, passage or group of copies gathers anywhere,
however many texts share it.

Whole texts that occur more than once are settled by their count, one of them
takes part in the search.

Defined cases: null, empty and short texts lose nothing; rows are kept one to
one, repeated rows (copies of each other, so they lose all words from
``window`` words on) and null ids included; a periodic text loses the windows
that recur inside it; an empty table gives an empty result; only the id and
text columns are read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import islice

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.functions.shared import settle
from stkfun.llm.batches import gram_hashes, mixed, sliding, small_batches, span_hashes, text_bytes, word_hashes, word_spans

WINDOW = 35
PHRASE = 8
BLOCK_BYTES = 1 << 20
_SALTS = 64
_HITS = 20_000


def key_phrases(hashes: np.ndarray, first: np.ndarray, window: int, phrase: int) -> tuple[np.ndarray, ...]:
    """For the texts whose words start at ``first``: owner, start, number of
    windows, key hash, offset of the phrase and weight of each stretch of
    windows with one key phrase. Weight 2: the phrase occurs in it twice."""
    span = window - phrase + 1
    counts = np.diff(first)
    owner = np.repeat(np.arange(len(counts)), counts)
    if len(hashes) < window:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.int64, np.int64))
    grams = gram_hashes(hashes, phrase)
    low = sliding(grams, span)
    at = np.flatnonzero(owner[: len(low)] == owner[window - 1 :])
    if not len(at):
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.int64, np.int64))
    value = low[at]
    begin = np.flatnonzero(np.concatenate([[True], (value[1:] != value[:-1]) | (at[1:] != at[:-1] + 1) | (owner[at[1:]] != owner[at[:-1]])]))
    many = np.diff(np.append(begin, len(at)))
    start, key = at[begin], value[begin]
    around = np.arange(span)
    head = (grams[start[:, None] + around] == key[:, None]).argmax(1)
    tail = span - 1 - (grams[(start + many - 1)[:, None] + around] == key[:, None])[:, ::-1].argmax(1)
    return owner[start], start - first[owner[start]], many, key, head, np.where(head == tail + many - 1, 1, 2)


def _surveyor(window: int, phrase: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            raw, off = text_bytes(batch.column("text"))
            starts, ends, first = word_spans(raw, off)
            owner, start, many, key, _, weight = key_phrases(word_hashes(raw, starts, ends), first, window, phrase)
            hi, lo, sha = [], [], []
            for a, b in zip(off, off[1:]):
                words = b" ".join(raw[a:b].tobytes().split())
                digest = np.frombuffer(xxhash.xxh3_128_digest(words), np.int64)
                hi.append(digest[0])
                lo.append(digest[1])
                sha.append(hashlib.sha256(words).hexdigest())
            cuts = pa.array(np.searchsorted(owner, np.arange(batch.num_rows + 1)).astype(np.int32))
            lists = [pa.ListArray.from_arrays(cuts, pa.array(x)) for x in (key.view(np.int64), start.astype(np.int32), many.astype(np.int32), weight.astype(np.int32))]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("th"), pa.array(hi, pa.int64()), pa.array(lo, pa.int64()), pa.array(np.diff(first)), pa.array(sha, pa.string()), *lists],
                ["doc_id", "th", "hi", "lo", "n_words", "sha", "key", "start", "many", "weight"],
            )

    return run


def _blocks(limit: int):
    """Number the texts' blocks: runs of rows of about ``limit`` bytes (one row at least)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = TaskContext.get().partitionId() << 32
        for batch in small_batches(batches, "text", limit):
            block += 1
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(batch.num_rows, block, np.int64))], [*batch.schema.names, "block"])

    return run


def spread(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """starts[0], starts[0] + 1, ... counts[0] of them, and so on."""
    return np.repeat(starts - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())


_MARK = pa.schema([("block", pa.int64()), ("key", pa.int64()), ("d", pa.int64()), ("off", pa.int32()), ("many", pa.int32()), ("n", pa.int64()), ("hs", pa.list_(pa.int64())), ("phrase", pa.string())])


def passage_hashes(words: np.ndarray, starts: np.ndarray, many: np.ndarray, off: np.ndarray, window: int) -> np.ndarray:
    """Stands for the words of stretches of ``many`` windows and the place of the phrase in them."""
    return mixed(span_hashes(words, starts, many + window - 1) + off.astype(np.uint64))


def _marker(window: int, phrase: int):
    """Stretches of recurring phrases (block, key, d, off, many, n, hs) and the phrases (block, key, phrase)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", BLOCK_BYTES):
            raw, off = text_bytes(batch.column("text"))
            starts, ends, first = word_spans(raw, off)
            words = word_hashes(raw, starts, ends)
            runs = batch.column("runs")
            flat = runs.flatten()
            key, s0, many = (flat.field(k).to_numpy(zero_copy_only=False) for k in range(3))
            owner = np.repeat(np.arange(batch.num_rows), runs.value_lengths().to_numpy(zero_copy_only=False))
            head, many = first[owner] + s0, many.astype(np.int64)
            # The phrase of a stretch lies in its first window, where its hash is.
            grams, span = gram_hashes(words, phrase).view(np.int64), np.arange(window - phrase + 1)
            place = (grams[head[:, None] + span] == key[:, None]).argmax(1)
            d = passage_hashes(words, head, many, place, window).view(np.int64)
            block, copies = batch.column("block").to_numpy()[owner], batch.column("copies").to_numpy()[owner]
            order = np.lexsort((block, d, key))
            new = np.concatenate([[True], (key[order][1:] != key[order][:-1]) | (d[order][1:] != d[order][:-1]) | (block[order][1:] != block[order][:-1])]) if len(order) else np.zeros(0, bool)
            at, n = order[new], np.add.reduceat(copies[order], np.flatnonzero(new)) if len(order) else np.zeros(0, np.int64)
            hashed = span_hashes(words, spread(head[at], many[at]), np.full(many[at].sum(), window)).view(np.int64)
            cuts = np.concatenate([[0], np.cumsum(many[at])]).astype(np.int32)
            columns = [pa.array(block[at]), pa.array(key[at]), pa.array(d[at]), pa.array(place[at].astype(np.int32)), pa.array(many[at].astype(np.int32)), pa.array(n), pa.ListArray.from_arrays(pa.array(cuts), pa.array(hashed))]
            yield pa.RecordBatch.from_arrays([*columns, pa.nulls(len(at), pa.string())], schema=_MARK)
            seen, text = {}, raw.tobytes()
            for b, k, p in zip(block[at].tolist(), key[at].tolist(), (head + place)[at].tolist()):
                if (b, k) not in seen:
                    seen[b, k] = b" ".join(text[i:j] for i, j in zip(starts[p : p + phrase], ends[p : p + phrase])).decode()
            rest = [pa.nulls(len(seen), f.type) for f in _MARK][2:-1]
            yield pa.RecordBatch.from_arrays([pa.array([b for b, _ in seen], pa.int64()), pa.array([k for _, k in seen], pa.int64()), *rest, pa.array(list(seen.values()), pa.string())], schema=_MARK)

    return run


class Found:
    """Distinct rows of integers, looked up by the first of them for many values together."""

    def __init__(self, *columns: np.ndarray):
        rows = np.unique(np.stack(columns, 1), axis=0) if len(columns[0]) else np.zeros((0, len(columns)), np.int64)
        self.columns = [np.ascontiguousarray(c) for c in rows.T]

    def pairs(self, asked: np.ndarray, most: int = 500_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(index asked, row here) of all equal values, about ``most`` at a time."""
        low, high = np.searchsorted(self.columns[0], asked, "left"), np.searchsorted(self.columns[0], asked, "right")
        upto, at = np.cumsum(high - low), 0
        while at < len(asked):
            to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + most, "right")))
            many = high[at:to] - low[at:to]
            yield np.repeat(np.arange(at, to), many), spread(low[at:to], many)
            at = to


class Shard:
    """The automaton of one block's confirmed phrases, and what they stand for.

    ``windows``: key, hash; ``passages``: key, hash, off, many (windows)."""

    def __init__(self, windows: tuple, passages: tuple, phrases: list[tuple[int, str]], window: int, phrase: int):
        self.windows, self.passages, self.window, self.phrase = Found(windows[1], windows[0]), Found(*passages), window, phrase
        wanted = set(windows[0].tolist()) | set(passages[0].tolist())
        self.loose = np.unique(windows[0])
        # One character for each byte, so that places are byte offsets.
        needles = {" " + p.encode().decode("latin-1") + " ": k for k, p in phrases if k in wanted}
        self.machine = ahocorasick.Automaton()
        for needle, key in needles.items():
            self.machine.add_word(needle, key)
        if needles:
            self.machine.make_automaton()

    def confirmed(self, words: list[bytes]) -> np.ndarray:
        """Whether each word of a text is covered, as phrases are located in it."""
        edge = np.zeros(len(words) + 1, np.int64)
        last = len(words) - self.window
        if last >= 0 and len(self.machine):
            flat = b" ".join(words)
            hits, h = self.machine.iter(" " + flat.decode("latin-1") + " "), None
            while found := list(islice(hits, _HITS)):
                if h is None:
                    raw = np.frombuffer(flat, np.uint8)
                    starts, ends, _ = word_spans(raw, np.array([0, len(raw)]))
                    h = word_hashes(raw, starts, ends)
                    each = span_hashes(h, np.arange(last + 1), np.full(last + 1, self.window)).view(np.int64) if len(self.loose) else None
                place = np.searchsorted(ends, np.array([e for e, _ in found]) - 1, "right") - self.phrase
                key = np.array([k for _, k in found], np.int64)
                self._passages(h, place, key, edge)
                if each is not None:
                    self._windows(each, place, key, edge)
        return np.cumsum(edge)[:-1] > 0

    def _passages(self, h: np.ndarray, place: np.ndarray, key: np.ndarray, edge: np.ndarray) -> None:
        for i, j in self.passages.pairs(key):
            d, off, many = (c[j] for c in self.passages.columns[1:])
            a, size = place[i] - off, many + self.window - 1
            fits = (a >= 0) & (a + size <= len(h))
            a, size, d, off, many = a[fits], size[fits], d[fits], off[fits], many[fits]
            same = passage_hashes(h, a, many, off, self.window).view(np.int64) == d
            np.add.at(edge, a[same], 1)
            np.add.at(edge, (a + size)[same], -1)

    def _windows(self, each: np.ndarray, place: np.ndarray, key: np.ndarray, edge: np.ndarray) -> None:
        some = np.isin(key, self.loose)
        place, key = place[some], key[some]
        low = np.maximum(place - self.window + self.phrase, 0)
        many = np.maximum(np.minimum(place, len(each) - 1) - low + 1, 0)
        at, key = spread(low, many), np.repeat(key, many)
        for i, j in self.windows.pairs(each[at]):
            a = np.unique(at[i[self.windows.columns[1][j] == key[i]]])
            edge[a] += 1
            edge[a + self.window] -= 1


def _streamer(window: int, phrase: int):
    """By block: confirmed windows, passages and phrases, then texts, which are streamed."""

    def gathered(parts: list[tuple], width: int) -> tuple:
        return tuple(np.concatenate([p[k] for p in parts]) if parts else np.zeros(0, np.int64) for k in range(width))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, shard, windows, passages, phrases = None, None, [], [], []
        for batch in batches:
            blocks, kinds = batch.column("block").to_numpy(), batch.column("kind").to_numpy()
            cuts = [0, *(np.flatnonzero((np.diff(blocks) != 0) | (np.diff(kinds) != 0)) + 1).tolist(), len(blocks)] if len(blocks) else []
            uids, gone, kept = [], [], []
            for a, b in zip(cuts, cuts[1:]):
                if blocks[a] != block:
                    block, shard, windows, passages, phrases = blocks[a], None, [], [], []
                part = batch.slice(a, b - a)
                numbers = lambda *names: tuple(part.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in names)  # noqa: B023, E731
                if kinds[a] == 0:
                    windows.append(numbers("key", "h"))
                elif kinds[a] == 1:
                    passages.append(numbers("key", "h", "off", "many"))
                elif kinds[a] == 2:
                    phrases += zip(part.column("key").to_pylist(), part.column("text").to_pylist())
                else:
                    if shard is None:
                        shard = Shard(gathered(windows, 2), gathered(passages, 4), phrases, window, phrase)
                    for uid, text in zip(part.column("key").to_pylist(), part.column("text").to_pylist()):
                        words = text.encode().split()
                        out = shard.confirmed(words)
                        if out.any():
                            uids.append(uid)
                            gone.append(int(out.sum()))
                            kept.append(hashlib.sha256(b" ".join(w for w, g in zip(words, out.tolist()) if not g)).hexdigest())
            yield pa.RecordBatch.from_arrays([pa.array(uids, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.string())], ["uid", "gone", "kept"])

    return run


_BUCKETS, _BITS = 512, 32_768


def maybe_in(rows: DataFrame, wanted: DataFrame, key: str = "th") -> DataFrame:
    """``rows`` whose key may be among those of ``wanted``: a bitmap of fixed size
    (2 MB) spares most other rows a shuffle; the join that follows is exact."""
    bucket, bit = F.pmod(F.col(key), F.lit(_BUCKETS)), F.pmod(F.shiftright(key, 20), F.lit(_BITS))
    maps = wanted.select(bucket.alias("bucket"), bit.alias("bit")).groupBy("bucket").agg(F.bitmap_construct_agg("bit").alias("bits"))
    byte = F.conv(F.hex(F.substring(F.col("bits"), (F.floor(bit / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    joined = rows.withColumn("bucket", bucket).join(F.broadcast(maps), "bucket")
    return joined.where(F.floor(byte / F.pow(F.lit(2), bit % 8)) % 2 == 1).select(*rows.columns)


def surveyed(docs: DataFrame, window: int, phrase: int) -> tuple[DataFrame, DataFrame]:
    """(all rows with their key phrases; uid, doc_id, th, n_words, sha, copies, rep)."""
    schema = "doc_id long, th long, hi long, lo long, n_words long, sha string, key array<long>, start array<int>, many array<int>, weight array<int>"
    survey = settle(docs.mapInArrow(_surveyor(window, phrase), schema).withColumn("uid", F.monotonically_increasing_id()), "phrases")
    copies = survey.groupBy("hi", "lo").agg(F.count("*").alias("copies"), F.min("uid").alias("rep")).where("copies > 1")
    # A large group of copies is dealt over salts.
    copies = copies.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))))
    rows = survey.select("uid", "doc_id", "th", "hi", "lo", "n_words", "sha", F.pmod(F.xxhash64("uid"), F.lit(_SALTS)).cast("int").alias("salt"))
    texts = rows.join(copies, ["hi", "lo", "salt"], "left").select("uid", "doc_id", "th", "n_words", "sha", F.coalesce("copies", F.lit(1).cast("long")).alias("copies"), F.coalesce("rep", "uid").alias("rep"))
    return survey, settle(texts, "texts")


def candidates(src: DataFrame, survey: DataFrame, texts: DataFrame, window: int) -> DataFrame:
    """uid, copies, runs (key, start, many), text, block: texts with recurring key phrases."""
    marks = survey.where(F.col("n_words") >= window)
    recurring = marks.select(F.explode(F.arrays_zip("key", "weight")).alias("z")).groupBy(F.col("z.key").alias("key")).agg(F.sum("z.weight").alias("n")).where("n > 1")
    runs = marks.select("uid", F.explode(F.arrays_zip("key", "start", "many", "weight")).alias("z")).select("uid", "z.*")
    runs = runs.join(recurring, "key").select("uid", "n", "weight", F.struct("key", "start", "many").alias("run"))
    searched = texts.where("uid = rep").select("uid", F.coalesce("doc_id", "th").alias("rk"), "th", "copies")
    # A copied text is settled; its stretches matter where another text has the phrase too.
    shared = runs.join(searched, "uid").where((F.col("copies") == 1) | (F.col("n") > F.col("copies") * F.col("weight")))
    wanted = settle(shared.groupBy("uid", "rk", "th", "copies").agg(F.collect_list("run").alias("runs")), "wanted")
    sources = src.where("text is not null").select(F.coalesce("doc_id", "th").alias("rk"), "th", "text")
    hits = maybe_in(sources, wanted).join(wanted, ["rk", "th"]).select("uid", "copies", "runs", "text")
    return settle(hits.mapInArrow(_blocks(BLOCK_BYTES), "uid long, copies long, runs array<struct<key:long,start:int,many:int>>, text string, block long"), "hits")


def covered(hits: DataFrame, window: int, phrase: int) -> DataFrame:
    """uid, gone, kept: what is left of the texts of ``hits`` that have no copy."""
    schema = "block long, key long, d long, off int, many int, n long, hs array<long>, phrase string"
    marks = settle(hits.mapInArrow(_marker(window, phrase), schema), "stretches")
    stretches = marks.where("phrase is null")
    counts = settle(stretches.groupBy("key", "d").agg(F.sum("n").alias("n"), F.min("block").alias("block")), "passages")
    # Each different stretch's windows once: those of one that occurs once carry its block.
    one = stretches.join(counts.withColumnRenamed("n", "total"), ["key", "d", "block"]).select("block", "key", "total", F.explode("hs").alias("h"))
    one = settle(one, "windows")
    # Written, so that the join shuffles both sides anew and a hot window's rows can be split.
    again = settle(one.groupBy("key", "h").agg(F.sum("total").alias("total")).where("total > 1").select("key", "h"), "again")
    none, number = F.lit(None).cast("string").alias("text"), lambda n: F.lit(None).cast("int").alias(n)
    row = lambda kind: ["block", F.lit(kind).alias("kind")]
    loose = one.where("total = 1").select("block", "key", "h").join(again, ["key", "h"]).select(*row(0), "key", "h", number("off"), number("many"), none)
    whole = stretches.join(counts.where("n > 1").select("key", "d"), ["key", "d"]).select(*row(1), "key", F.col("d").alias("h"), "off", "many", none)
    phrases = marks.where("phrase is not null").select(*row(2), "key", F.lit(None).cast("long").alias("h"), number("off"), number("many"), F.col("phrase").alias("text"))
    texts = hits.where("copies = 1").select(*row(3), F.col("uid").alias("key"), F.lit(None).cast("long").alias("h"), number("off"), number("many"), "text")
    dealt = loose.unionByName(whole).unionByName(phrases).unionByName(texts).repartition("block").sortWithinPartitions("block", "kind")
    return settle(dealt.mapInArrow(_streamer(window, phrase), "uid long, gone long, kept string"), "removed")


def deduplicated(docs: DataFrame, window: int = WINDOW, phrase: int = PHRASE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every row."""
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    src = src.withColumn("th", F.coalesce(F.xxhash64("text"), F.lit(0)))
    survey, texts = surveyed(src, window, phrase)
    out = texts.join(covered(candidates(src, survey, texts, window), window, phrase), "uid", "left")
    copied = (F.col("copies") > 1) & (F.col("n_words") >= window)
    return out.select(
        "doc_id", "n_words",
        F.when(copied, F.col("n_words")).otherwise(F.coalesce("gone", F.lit(0))).alias("n_removed"),
        F.when(copied, F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("kept", "sha")).alias("kept_sha256"),
    )


def op4_query(spark, sf_dir: str) -> DataFrame:
    return deduplicated(spark.read.parquet(f"{sf_dir}/documents.parquet"))
