"""Language-model scores by a hierarchical Pitman-Yor model.

Four levels of restaurants, each the base of the one above:

* pairs: one restaurant for every preceding word and one for the beginning of a
  text, whatever their number; their dishes are all words. The parent is the
  restaurant of the preceding word's class.
* classes: one restaurant for each of the ``OWN`` most frequent preceding words,
  one for the beginning of a text, and one for each class (a hash) of all other
  preceding words; their dishes are the ``DISHES`` most frequent words and one
  dish for all others. Their customers are the tables of the pairs. They share the
  root restaurant as parent.
* the root, over the same dishes. A word of the shared dish is told apart by the
  lexicon.
* the lexicon, one restaurant over all words, whose base spells a word byte by
  byte (then a stop) from restaurants whose contexts are the two preceding bytes,
  which share the restaurants of one byte and of none as parents, down to uniform
  bytes. A word that no training text has is a spelling of the base.

A text's end is the empty word. Tables are sampled by Gibbs sweeps: the customers
of a dish leave (with their tables, as the parent's customers) and are seated
again one after the other, in growing groups once there are many; the restaurants
of a level are swept side by side against the parent of the last sweep. The first
sweeps are left out; predictive probabilities are averaged over the others. Pairs are
seated first with the lexicon as their parent, for the classes' customers; then, with
the classes' probabilities, once for each sample. A pair of one token has one table.

Word and pair counts come from all training texts. Every pair of every text goes
to a bucket (about a million tokens each), once with the texts that hold it: by its
preceding word, or by both words where that one is frequent. A bucket seats and
scores its pairs; rarer words meet their counts and probabilities there by a join.
Classes have at most (OWN + CLASSES + 1) * (DISHES + 1) cells (8.4 million, whatever
the input), and as many 4-byte probabilities reach the executors; of the lexicon only
byte cells (at most 2 ** 24 by construction) and ``HOT_WORDS`` words reach the driver,
and sums over the pairs of each of these words, which lie in several buckets. Random
numbers are hashes of the words and the sweep, so reruns agree.

Defined cases: null and empty texts hold just the end; a null id counts as the
empty text in the split (held out); rows are kept one to one, repeated rows
count as texts each; without training texts the base measure alone scores; an
empty table gives an empty result; only the id and text columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stkfun.functions.shared import settle
from stkfun.llm.batches import _ODD, distinct, lengths, mixed, small_batches, text_bytes, word_codes, word_hashes
from stkfun.llm.ftrl_quality import split_of

SAMPLES = 3
BURN_IN = 2
HOT_WORDS = 1 << 17
DISHES = 1 << 15
OWN, CLASSES = 192, 63
_CONTEXTS = OWN + CLASSES + 1
STRENGTH = 1.0
BYTE_DISCOUNT = 0.5
BYTE_SWEEPS = 5
BUCKET_TOKENS = 1 << 20
BEGIN = np.uint64(0)  # precedes a text's first token; as a hash it is the end's, which precedes nothing


def uniforms(ids: np.ndarray, salt: int) -> np.ndarray:
    h = mixed(ids ^ mixed(np.full(1, salt * 2 + 1, np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
    return (h >> np.uint64(11)).astype(np.float64) / (1 << 53)


def seat(customers: np.ndarray, pull: np.ndarray, discount: float, ids: np.ndarray, salt: int) -> np.ndarray:
    """Tables for each dish: customers arrive one after the other, in growing
    groups once there are many; ``pull`` is (strength + discount * tables) times
    the parent's probability of the dish."""
    tables = np.minimum(customers, 1).astype(np.float64)
    live, seated = np.flatnonzero(customers > 1), 1
    while len(live):
        group = max(1, seated // 8)
        come = np.minimum(group, customers[live] - seated)
        chance = pull[live] / (pull[live] + np.maximum(seated - discount * tables[live], 1e-9))
        tables[live] = np.minimum(tables[live] + np.floor(come * chance + uniforms(ids[live], salt * 1_000_003 + seated)), customers[live])
        seated += group
        live = live[customers[live] > seated]
    return tables


@dataclass
class Spelling:
    """Byte probabilities: sparse cells (context * 256 + byte) over backed-off lower orders."""

    cells: np.ndarray
    chance: np.ndarray
    back: np.ndarray
    lower: np.ndarray

    def log_words(self, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Natural log probability of each word's spelling and stop."""
        return self.log_spelled(*spelled(raw, off))

    def log_spelled(self, code: np.ndarray, cell: np.ndarray, heads: np.ndarray) -> np.ndarray:
        if not len(heads):
            return np.zeros(0)
        ctx, byte = cell >> 8, cell & 255
        p = self.back[ctx] * self.lower[ctx & 255, byte]
        if len(self.cells):
            at = np.minimum(np.searchsorted(self.cells, cell), len(self.cells) - 1)
            hit = self.cells[at] == cell
            p[hit] = self.chance[at[hit]]
        return np.add.reduceat(np.log(p)[code], heads)


def uniform_spelling() -> Spelling:
    return Spelling(np.zeros(0, np.int64), np.zeros(0), np.ones(1 << 16), np.full((256, 256), 1 / 256))


def spelled(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of all words, a zero after each, with their contexts (two bytes before): as
    places in a list of different cells, that list, word heads."""
    n = len(off) - 1
    seq = np.zeros(len(raw) + n, np.int32)
    seq[np.arange(len(raw)) + np.repeat(np.arange(n), np.diff(off))] = raw
    heads = off[:-1] + np.arange(n)
    one = np.concatenate([np.zeros(1, np.int32), seq[:-1]])
    two = np.concatenate([np.zeros(2, np.int32), seq[:-2]])[: len(seq)]
    one[heads] = two[heads] = 0
    code, cell = distinct((two * 256 + one) * 256 + seq)
    return code, cell.astype(np.int64), heads


def byte_restaurants(cells: np.ndarray, count: np.ndarray, sample: int, sweeps: int = BYTE_SWEEPS, discount: float = BYTE_DISCOUNT, strength: float = STRENGTH) -> Spelling:
    """Seat the customers of the two-byte contexts and of their parents by Gibbs sweeps."""
    ctx, byte = cells >> 8, cells & 255
    tables = np.minimum(count, 1).astype(float)
    parent_cell = (ctx & 255) * 256 + byte
    t1 = None
    for sweep in range(sweeps):
        n1 = np.bincount(parent_cell, tables, 1 << 16).reshape(256, 256)
        t1 = np.minimum(n1, 1) if t1 is None else np.minimum(np.maximum(t1, np.minimum(n1, 1)), n1)
        n0 = t1.sum(0)
        t0 = np.minimum(n0, 1)
        p0 = (n0 - discount * t0 + (strength + discount * t0.sum()) / 256) / (strength + n0.sum())
        pull1 = (strength + discount * t1.sum(1))[:, None] * p0[None, :]
        ids = np.arange(1 << 16, dtype=np.uint64)
        t1 = seat(n1.astype(np.int64).ravel(), pull1.ravel(), discount, ids, 7919 * sample + 2 * sweep).reshape(256, 256)
        n0 = t1.sum(0)
        t0 = np.minimum(n0, 1)
        p0 = (n0 - discount * t0 + (strength + discount * t0.sum()) / 256) / (strength + n0.sum())
        p1 = (n1 - discount * t1 + (strength + discount * t1.sum(1))[:, None] * p0[None, :]) / (strength + n1.sum(1))[:, None]
        open2 = strength + discount * np.bincount(ctx, tables, 1 << 16)
        tables = seat(count, open2[ctx] * p1[ctx & 255, byte], discount, cells.astype(np.uint64), 7919 * sample + 2 * sweep + 1)
    n1 = np.bincount(parent_cell, tables, 1 << 16).reshape(256, 256)
    t1 = np.minimum(np.maximum(t1, np.minimum(n1, 1)), n1)
    p1 = (n1 - discount * t1 + (strength + discount * t1.sum(1))[:, None] * p0[None, :]) / (strength + n1.sum(1))[:, None]
    total = strength + np.bincount(ctx, count, 1 << 16)
    back = (strength + discount * np.bincount(ctx, tables, 1 << 16)) / total
    chance = (count - discount * tables) / total[ctx] + back[ctx] * p1[ctx & 255, byte]
    return Spelling(cells, chance, back, p1)


def _counter():
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            code, words, counts = word_codes(batch.column("text"))
            train = ~batch.column("held").to_numpy(zero_copy_only=False).astype(bool)
            c = np.bincount(code[np.repeat(train, counts)], minlength=len(words))
            some = lengths(words) > 0
            words = pa.concat_arrays([words.cast(pa.string()).filter(pa.array(some)), pa.array([""])])
            yield pa.RecordBatch.from_arrays([words, pa.array(np.append(c[some], train.sum()))], ["word", "c"])

    return run


def _tables(count: np.ndarray, log_base: np.ndarray, ids: np.ndarray, tables: float, discount: float, sample: int) -> np.ndarray:
    return seat(count, (STRENGTH + discount * tables) * np.exp(log_base), discount, ids, 104_729 * sample)


def _word_ids(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw, off = text_bytes(column)
    return raw, off, word_hashes(raw, off[:-1], off[1:])


def _table_sweep(spelling: Spelling, tables: float, discount: float, sample: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells, weights = [np.zeros(0, np.int64)], [np.zeros(0)]
        total = 0.0
        for batch in small_batches(batches, "word", 1 << 20):
            raw, off, ids = _word_ids(batch.column("word"))
            count = batch.column("c").to_numpy(zero_copy_only=False)
            code, cell, heads = spelled(raw, off)
            t = _tables(count, spelling.log_spelled(code, cell, heads), ids, tables, discount, sample)
            cells.append(cell)
            weights.append(np.bincount(code, np.repeat(t, np.diff(off) + 1), len(cell)))
            if len(cells) > 16:
                cells, weights = _merged(cells, weights)
            total += t.sum()
        (cell,), (weight,) = _merged(cells, weights)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(cell, -1)), pa.array(np.append(weight, total))], ["cell", "n"])

    return run


def _merged(cells: list[np.ndarray], weights: list[np.ndarray]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    code, cell = distinct(np.concatenate(cells))
    return [cell], [np.bincount(code, np.concatenate(weights), len(cell))]


def _lexicographer(chain: list[tuple[Spelling, Spelling, float, float, int]], discount: float, n_train: int):
    """chain: for each sample the spelling and tables it was seated by, its own, and its number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "word", 1 << 20):
            raw, off, ids = _word_ids(batch.column("word"))
            count = batch.column("c").to_numpy(zero_copy_only=False)
            p, spelling, last = np.zeros(len(count)), spelled(raw, off), None
            for before, own, t_before, t_own, sample in chain:
                if before is not last:
                    log_own = before.log_spelled(*spelling)
                t = _tables(count, log_own, ids, t_before, discount, sample)
                log_own, last = own.log_spelled(*spelling), own
                p += (np.maximum(count - discount * t, 0) + (STRENGTH + discount * t_own) * np.exp(log_own)) / (STRENGTH + n_train)
            yield pa.RecordBatch.from_arrays([pa.array(ids.view(np.int64)), batch.column("c"), pa.array(np.log10(np.maximum(p / len(chain), 1e-300)))], ["wh", "c", "lp"])

    return run


def lexicon(docs: DataFrame, samples: int = SAMPLES) -> tuple[DataFrame, int, int]:
    """(wh, c, lp) for every word of ``docs`` (text, held), training tokens, training types."""
    vocab = docs.select("text", "held").mapInArrow(_counter(), "word string, c long").groupBy("word").agg(F.sum("c").alias("c"))
    vocab = settle(vocab, "vocabulary")
    stat = vocab.agg(F.sum("c").alias("n"), F.count_if(F.col("c") > 0).alias("v"), F.count_if(F.col("c") == 1).alias("n1"), F.count_if(F.col("c") == 2).alias("n2")).first()
    n, v = stat.n or 0, stat.v or 0
    discount = min(0.95, max(0.05, stat.n1 / max(1, stat.n1 + 2 * stat.n2)))
    spelling, tables, chain = uniform_spelling(), float(v), []
    trained = vocab.where("c > 0")
    for k in range(samples + 1):
        got = trained.mapInArrow(_table_sweep(spelling, tables, discount, k + 1), "cell long, n double").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
        cell, count = got.column("cell").to_numpy(), got.column("n").to_numpy()
        order = np.argsort(cell)
        cell, count = cell[order], count[order]
        seated = float(count[0]) if len(cell) else 0.0
        own = byte_restaurants(cell[1:], count[1:].astype(np.int64), k + 1) if len(cell) > 1 else uniform_spelling()
        if k:  # the first sweep is left out
            chain.append((spelling, own, tables, seated, k + 1))
        spelling, tables = own, seated
    return settle(vocab.mapInArrow(_lexicographer(chain, discount, n), "wh long, c long, lp double"), "lexicon"), n, v


@dataclass
class HotWords:
    """The most frequent words of the lexicon by hash, with their ranks; the first ``dishes`` ranks are dishes."""

    ids: np.ndarray
    count: np.ndarray
    lp: np.ndarray
    rank: np.ndarray
    dishes: int

    def look_up(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each hash is there, and where."""
        at = np.minimum(np.searchsorted(self.ids, h), max(len(self.ids) - 1, 0))
        return (self.ids[at] == h if len(self.ids) else np.zeros(len(h), bool)), at

    def contexts(self, u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of preceding words: where sums over all buckets are kept (-1: in the bucket itself), and the class."""
        known, at = self.look_up(u)
        rank = np.where(known, self.rank[at], self.dishes) if len(self.ids) else np.full(len(u), self.dishes)
        context = np.where(rank < min(OWN, self.dishes), rank, OWN + (u % np.uint64(CLASSES)).astype(np.int64))
        begin = u == BEGIN
        return np.where(begin, len(self.ids), np.where(known, at, -1)), np.where(begin, OWN + CLASSES, context)

    def base(self) -> np.ndarray:
        """The lexicon's probability of every dish, the shared one last."""
        q = np.zeros(self.dishes + 1)
        mine = self.rank < self.dishes
        q[self.rank[mine]] = 10.0 ** self.lp[mine]
        q[-1] = max(1.0 - q.sum(), 1e-12)
        return q / q.sum()


def hot_words(words: DataFrame) -> HotWords:
    top = words.orderBy(F.desc("c"), "wh").limit(HOT_WORDS).toArrow()
    ids, count, lp = top.column("wh").to_numpy().view(np.uint64), top.column("c").to_numpy(), top.column("lp").to_numpy()
    order = np.argsort(ids)
    return HotWords(ids[order], count[order], lp[order], order, min(DISHES, int((count > 0).sum())))


def _tokens(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All tokens (a text's words, then its end) as places among the hashes of different words, their texts,
    the texts' first tokens, and those hashes (the end's is last)."""
    code, words, counts = word_codes(batch.column("text"))
    raw, off = text_bytes(words)
    none = np.zeros(1, np.int64)
    h = np.append(word_hashes(raw, off[:-1], off[1:]), word_hashes(raw[:0], none, none))
    ends, is_word = np.cumsum(counts + 1) - 1, np.ones(len(code) + len(counts), bool)
    is_word[ends] = False
    w = np.full(len(is_word), len(words), np.int32)
    w[is_word] = code
    return w, np.repeat(np.arange(len(counts), dtype=np.int32), counts + 1), ends - counts, h


def _packed(a: np.ndarray) -> bytes:
    """Compressed, all first bytes of the values in front."""
    if not len(a):
        return bytes(8)
    a = np.ascontiguousarray(a).view(np.uint8).reshape(len(a), -1)
    raw = np.empty(a.shape[::-1], np.uint8)
    for k in range(len(raw)):
        raw[k] = a[:, k]
    return raw.size.to_bytes(8, "little") + pa.compress(pa.py_buffer(raw), codec="zstd", asbytes=True)


def _unpacked(b: bytes, kind) -> np.ndarray:
    size, width = int.from_bytes(b[:8], "little"), np.dtype(kind).itemsize
    if not size:
        return np.zeros(0, kind)
    raw = np.frombuffer(pa.decompress(memoryview(b)[8:], decompressed_size=size, codec="zstd"), np.uint8).reshape(width, -1)
    out = np.empty(raw.shape[::-1], np.uint8)
    for k in range(width):
        out[:, k] = raw[k]
    return out.view(kind).ravel()


def _coded(h: np.ndarray, known: np.ndarray, at: np.ndarray, hot: HotWords) -> tuple[np.ndarray, np.ndarray]:
    """Words (with what ``look_up`` found) as their places among the frequent ones, or behind those in a list
    of the others."""
    rare = np.unique(h[~known])
    code = at.astype(np.uint32)
    code[~known] = len(hot.ids) + np.searchsorted(rare, h[~known])
    return code, rare


def _steps_of(code: np.ndarray) -> np.ndarray:
    return np.diff(code, prepend=np.uint32(0))


@dataclass
class Pairs:
    """The different pairs of some texts in the order of their buckets, then of 24 bits of the word before (u)
    and of the word (w), with what ``look_up`` found of them; for each pair its number of texts, and those in a
    row with how often the pair is there."""

    u: np.ndarray
    w: np.ndarray
    u_known: np.ndarray
    w_known: np.ndarray
    u_at: np.ndarray
    w_at: np.ndarray
    bucket: np.ndarray
    n: np.ndarray
    owner: np.ndarray
    times: np.ndarray


def _pairs(batch: pa.RecordBatch, hot: HotWords, buckets: int) -> Pairs:
    """A pair lies with its preceding word; where that one is frequent, with a rare word, or else by both."""
    token, owner, heads, h = _tokens(batch)
    known, at = hot.look_up(h)
    by = np.argsort(np.where(known, at.astype(np.uint64), np.uint64(1 << 23) | (h >> np.uint64(41))), kind="stable")
    rank = np.empty(len(by), np.uint32)
    rank[by] = np.arange(len(by), dtype=np.uint32)
    token, end, wide = rank[token], rank[-1], np.uint64(len(by))
    h, known, at = h[by], known[by], at[by]
    key = np.concatenate([token[:1], token[:-1]]).astype(np.uint64)
    key[heads] = end  # precedes nothing else, and its hash is that of the beginning
    key *= wide
    key += token
    del token
    bits = np.uint64(max(1, batch.num_rows.bit_length()))
    if 2 * len(by).bit_length() + int(bits) <= 64:
        key <<= bits
        key |= owner.view(np.uint32)
        key.sort()
        owner = (key & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int32)
        key >>= bits
    else:
        order = np.argsort(key, kind="stable")
        key, owner = key[order], owner[order]
    other = np.concatenate([[True], key[1:] != key[:-1]])
    entry = other.copy()
    entry[1:] |= owner[1:] != owner[:-1]
    entries = np.flatnonzero(entry)
    times, owner = np.diff(np.append(entries, len(key))).astype(np.uint32), owner[entries]
    first = np.flatnonzero(other[entries])
    before, word = np.divmod(key[entries[first]], wide)
    del key, entry, other
    u, w = h[before], h[word]
    bucket = np.where(known[before] | (before == end), np.where(known[word], pair_hashes(u, w), mixed(w + _ODD)), mixed(u + _ODD)) % np.uint64(buckets)
    order = np.argsort(bucket.astype(np.uint16) if buckets <= 1 << 16 else bucket, kind="stable")
    n = np.diff(np.append(first, len(entries)))[order]
    at_entry = np.repeat(first[order] - (np.cumsum(n) - n), n)
    at_entry += np.arange(len(entries))
    del entries, first
    before, word = before[order], word[order]
    return Pairs(u[order], w[order], known[before], known[word], at[before], at[word], bucket[order].astype(np.int64), n, owner[at_entry], times[at_entry])


def pair_hashes(u: np.ndarray, w: np.ndarray) -> np.ndarray:
    return mixed(mixed(u + _ODD) * _ODD + w)


_BLOCK = "bucket int, base long, u binary, ru binary, w binary, rw binary, n binary, doc binary, times binary, ids binary, flags binary"


def _blocks(hot: HotWords, buckets: int):
    """For each bucket the distinct pairs of some texts, each with its texts (times two, plus one if held out)
    and how often it is there; a chunk's ids go to one bucket."""
    names = [x.split()[0] for x in _BLOCK.split(", ")]
    kinds = [pa.int32(), pa.int64(), *[pa.binary()] * 9]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 8 << 20):
            held = batch.column("held").to_numpy(zero_copy_only=False).astype(bool)
            p = _pairs(batch, hot, buckets)
            doc = p.owner.astype(np.uint32) * np.uint32(2) + held[p.owner]
            times, n, of = p.times, p.n.astype(np.uint32), p.bucket
            first = np.append(0, np.cumsum(p.n))
            base = batch.column("uid")[0].as_py()
            home = int(mixed(np.full(1, base, np.uint64))[0] % np.uint64(buckets))
            rows: list[list] = [[] for _ in names]
            for b in sorted({home, *of[np.flatnonzero(np.diff(of, prepend=-1))].tolist()}):
                lo, hi = np.searchsorted(of, [b, b + 1])
                e0, e1 = first[[lo, hi]]
                ids = flags = None
                if b == home:
                    ids = _packed(batch.column("doc_id").fill_null(0).to_numpy(zero_copy_only=False))
                    flags = _packed((batch.column("doc_id").is_null().to_numpy(zero_copy_only=False) + 2 * held).astype(np.uint8))
                mine = slice(lo, hi)
                uc, ru = _coded(p.u[mine], p.u_known[mine], p.u_at[mine], hot)
                wc, rw = _coded(p.w[mine], p.w_known[mine], p.w_at[mine], hot)
                for column, value in zip(rows, (b, base, *map(_packed, (_steps_of(uc), ru, wc, rw, n[lo:hi], doc[e0:e1], times[e0:e1])), ids, flags)):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(rows, kinds)], names)

    return run


def _rare_words(hot: HotWords, buckets: int):
    """The rarer words of pairs that lie with a preceding word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 8 << 20):
            token, _, heads, h = _tokens(batch)
            known, _ = hot.look_up(h)
            rare = ~known[token]
            rare[1:] &= ~known[token[:-1]]
            rare[heads] = False
            here = np.flatnonzero(rare)
            w, bucket = h[token[here]], mixed(h[token[here - 1]] + _ODD) % np.uint64(buckets)
            _, at = np.unique(mixed(w ^ mixed(bucket + _ODD)), return_index=True)
            yield pa.RecordBatch.from_arrays([pa.array(bucket[at].astype(np.int32)), pa.array(w[at].view(np.int64))], ["bucket", "wh"])

    return run


def _word_blocks(hot: HotWords, buckets: int):
    """Words by bucket (each rare one by its hash, if none is given), as blocks without texts: their hashes,
    counts and log probabilities."""
    names, kinds = [x.split()[0] for x in _BLOCK.split(", ")], [pa.int32(), pa.int64(), *[pa.binary()] * 9]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [batch.column(n).to_numpy(zero_copy_only=False) for n in ("wh", "c", "lp")]
            if "bucket" in batch.schema.names:
                bucket = batch.column("bucket").to_numpy(zero_copy_only=False)
            else:
                h = values[0].view(np.uint64)
                rare = ~hot.look_up(h)[0]
                bucket, values = (mixed(h[rare] + _ODD) % np.uint64(buckets)).astype(np.int32), [v[rare] for v in values]
            order = np.argsort(bucket, kind="stable")
            which, first = np.unique(bucket[order], return_index=True)
            h, c, lp = ([_packed(x) for x in np.split(v[order], first[1:])] if len(which) else [] for v in values)
            none = [None] * len(which)
            columns = [which, none, c, none, lp, h, *[none] * 5]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, kinds)], names)

    return run


_BUCKET = "bucket int, u binary, ru binary, w binary, rw binary, wc binary, wlp binary, c binary, n binary, doc binary, times binary, uids binary, ids_of binary, ids binary, flags binary"
_MODEL = ["u", "ru", "w", "rw", "wc", "wlp", "c"]


def _joined(parts: list[np.ndarray], kind) -> np.ndarray:
    return np.concatenate(parts) if parts else np.zeros(0, kind)


def _hashes(code: np.ndarray, rare: np.ndarray, hot: HotWords) -> np.ndarray:
    return np.concatenate([hot.ids, rare])[code] if len(code) else np.zeros(0, np.uint64)


def _one_list(codes: list[np.ndarray], rares: list[np.ndarray], hot: HotWords) -> tuple[np.ndarray, np.ndarray]:
    """Codes of several blocks as codes of one list of rarer words."""
    frequent, rare = len(hot.ids), np.unique(_joined(rares, np.uint64))
    for code, own in zip(codes, rares):
        mine = code >= frequent
        code[mine] = frequent + np.searchsorted(rare, own)[code[mine] - frequent]
    return _joined(codes, np.uint32), rare


def _order(key: np.ndarray) -> np.ndarray:
    """A stable order of keys; with their places in the low bits, where there is room, sorted at once."""
    bits = np.uint64(max(1, len(key)).bit_length())
    if not len(key) or int(key.max()).bit_length() + int(bits) > 64:
        return np.argsort(key, kind="stable")
    return (np.sort((key << bits) | np.arange(len(key), dtype=np.uint64)) & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)


def _gatherer(hot: HotWords):
    """All blocks of a bucket as one: each pair once, with its training tokens."""

    def run(table: pa.Table) -> pa.Table:
        us, ws, rus, rws, ns, docs, held, times, uids, id_uids, ids, flags, wh, wc, wlp = ([] for _ in range(15))
        texts = 0
        for r in sorted(table.to_pylist(), key=lambda r: (r["base"] is None, r["base"] or 0)):
            if r["base"] is None:
                for out, name, kind in ((wh, "rw", np.uint64), (wc, "u", np.int64), (wlp, "w", np.float64)):
                    out.append(_unpacked(r[name], kind))
                continue
            us.append(np.cumsum(_unpacked(r["u"], np.uint32), dtype=np.uint32))
            ws.append(_unpacked(r["w"], np.uint32).copy())
            rus.append(_unpacked(r["ru"], np.uint64))
            rws.append(_unpacked(r["rw"], np.uint64))
            ns.append(_unpacked(r["n"], np.uint32))
            times.append(_unpacked(r["times"], np.uint32))
            doc = _unpacked(r["doc"], np.uint32)
            held.append((doc & 1).astype(bool))
            doc = (doc >> 1).astype(np.int64)
            here = np.bincount(doc) > 0
            docs.append((texts + np.cumsum(here) - 1)[doc])
            uids.append(np.flatnonzero(here) + r["base"])
            texts += len(uids[-1])
            if r["ids"] is not None:
                ids.append(_unpacked(r["ids"], np.int64))
                flags.append(_unpacked(r["flags"], np.uint8))
                id_uids.append(np.arange(len(ids[-1])) + r["base"])
        (u, ru), (w, rw) = _one_list(us, rus, hot), _one_list(ws, rws, hot)
        n, doc, time = _joined(ns, np.uint32).astype(np.int64), _joined(docs, np.int64), _joined(times, np.uint32)
        width = np.uint64((len(hot.ids) + len(rw)).bit_length())
        key = (u.astype(np.uint64) << width) | w
        order = _order(key)
        key, starts, n = key[order], (np.cumsum(n) - n)[order], n[order]
        at = np.repeat(starts - (np.cumsum(n) - n), n) + np.arange(len(doc))
        doc, time = doc[at], time[at]
        pairs = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        first, key = (np.cumsum(n) - n)[pairs], key[pairs]
        trained = np.where(_joined(held, bool)[at], 0, time).astype(np.int64)
        c = np.add.reduceat(trained, first) if len(first) else np.zeros(0, np.int64)
        n = np.diff(np.append(first, len(doc))).astype(np.uint32)
        uids = _joined(uids, np.int64)
        wh, where = np.unique(_joined(wh, np.uint64), return_index=True)
        at = np.searchsorted(wh, rw)
        if len(rw) and (not len(wh) or (wh[np.minimum(at, len(wh) - 1)] != rw).any()):
            raise RuntimeError("the texts have changed between two readings")
        values = (_steps_of((key >> width).astype(np.uint32)), ru, (key & ((np.uint64(1) << width) - np.uint64(1))).astype(np.uint32), rw, _joined(wc, np.int64)[where][at], _joined(wlp, np.float64)[where][at])
        values += (c, n, doc.astype(np.uint32), time, np.diff(uids, prepend=0), _joined(id_uids, np.int64), _joined(ids, np.int64), _joined(flags, np.uint8))
        names = [x.split()[0] for x in _BUCKET.split(", ")]
        return pa.table([pa.array([table.column("bucket")[0].as_py()], pa.int32()), *(pa.array([_packed(v)], pa.binary()) for v in values)], names=names)

    return run


@dataclass
class Seating:
    """What all buckets need to know: for frequent preceding words their tokens, pairs and tables in all
    buckets (of the first seating, then of each sample), and log10 P(dish | class) (broadcast)."""

    hot: HotWords
    discount: float
    tokens: np.ndarray
    tables: tuple
    chance: object = None

    @property
    def shared(self) -> float:
        return float(np.log10(self.hot.base()[-1]))


class Bucket:
    """The pairs of a bucket: ``of`` counts their preceding words through, ``slot`` is -1 for one that has no
    pairs elsewhere, ``dish`` and ``lp`` are the word's place in the classes and its lexicon probability."""

    def __init__(self, row: dict, hot: HotWords):
        u, w = np.cumsum(_unpacked(row["u"], np.uint32), dtype=np.uint32), _unpacked(row["w"], np.uint32)
        self.c, rw = _unpacked(row["c"], np.int64), _unpacked(row["rw"], np.uint64)
        self.u, self.w = _hashes(u, _unpacked(row["ru"], np.uint64), hot), _hashes(w, rw, hot)
        heads = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]])) if len(u) else np.zeros(0, np.int64)
        self.of, self.width = np.repeat(np.arange(len(heads)), np.diff(np.append(heads, len(u)))), len(heads)
        self.slot, context = hot.contexts(self.u[heads])
        self.context = context[self.of]
        rest = np.full(len(rw), hot.dishes)
        self.dish = np.concatenate([np.minimum(hot.rank, hot.dishes), rest])[w]
        self.lp = np.concatenate([hot.lp, _unpacked(row["wlp"], np.float64)])[w]
        self.words = np.concatenate([hot.count, _unpacked(row["wc"], np.int64)])[w]

    def by_context(self, values: np.ndarray, everywhere: np.ndarray | None) -> np.ndarray:
        """Sums for each pair's preceding word: the bucket's own, or those of all buckets."""
        own = np.bincount(self.of, values, self.width)
        if everywhere is not None:
            own = np.where(self.slot >= 0, everywhere[self.slot], own)
        return own[self.of]

    def parent(self, s: Seating) -> np.ndarray:
        """Each pair's probability by the class of its preceding word."""
        rest = self.dish == s.hot.dishes
        return 10.0 ** (s.chance.value[self.context, self.dish].astype(np.float64) + np.where(rest, self.lp - s.shared, 0.0))

    def seated(self, s: Seating, parent: np.ndarray, before: np.ndarray, salt: int) -> np.ndarray:
        """Tables of each pair, given those that its preceding word had before."""
        tables = np.minimum(self.c, 1).astype(np.float64)
        live = np.flatnonzero(self.c > 1)
        tables[live] = seat(self.c[live], (STRENGTH + s.discount * before[live]) * parent[live], s.discount, pair_hashes(self.u[live], self.w[live]), salt)
        return tables

    def first_tables(self, s: Seating) -> np.ndarray:
        """The first seating: a table for each pair before, the lexicon as the parent."""
        pairs = self.by_context(np.minimum(self.c, 1), s.tables[0])
        return self.seated(s, 10.0**self.lp, pairs, 17)

    def samples(self, s: Seating, samples: int) -> tuple[np.ndarray, list[np.ndarray]]:
        parent, before = self.parent(s), self.by_context(self.first_tables(s), s.tables[1])
        return parent, [self.seated(s, parent, before, 19 + k) for k in range(samples)]


_CHUNK = 4096  # slots in a row of sums


def _sums(hot: HotWords, of_bucket, cells: bool):
    """Sums over the buckets of one task: key < _CONTEXTS: a class's dishes; then slots in chunks; -1: pairs
    of one and of two tokens. ``of_bucket`` gives the values of pairs: the first is counted in classes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wide, slots, few = hot.dishes + 1, None, np.zeros(2, np.int64)
        grid = np.zeros(_CONTEXTS * wide if cells else 0, np.int64)
        for batch in batches:
            for k in range(batch.num_rows):
                b = Bucket({n: batch.column(n)[k].as_py() for n in _MODEL}, hot)
                values = of_bucket(b)
                if slots is None:
                    slots = np.zeros((len(hot.ids) + 1, len(values)), np.int64)
                for j, v in enumerate(values):
                    own = np.bincount(b.of, v, b.width).astype(np.int64)
                    np.add.at(slots[:, j], b.slot[b.slot >= 0], own[b.slot >= 0])
                if cells:
                    cell, back = np.unique(b.context * wide + b.dish, return_inverse=True)
                    grid[cell] += np.bincount(back, values[0], len(cell)).astype(np.int64)
                few += (b.c == 1).sum(), (b.c == 2).sum()
        if slots is None:
            return
        out = [(k, grid[k * wide : k * wide + wide]) for k in range(_CONTEXTS if cells else 0)]
        out += [(_CONTEXTS + k // _CHUNK, slots[k : k + _CHUNK].ravel()) for k in range(0, len(slots), _CHUNK)]
        for key, v in [*out, (-1, few)]:
            yield pa.RecordBatch.from_arrays([pa.array([key], pa.int32()), pa.array([_packed(v)], pa.binary())], ["key", "v"])

    return run


def _added(table: pa.Table) -> pa.Table:
    total = 0
    for v in table.column("v").to_pylist():
        total = total + _unpacked(v, np.int64)
    return pa.table([table.column("key").slice(0, 1), pa.array([_packed(total)], pa.binary())], names=["key", "v"])


def _dish_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for key, v in zip(batch.column("key").to_pylist(), batch.column("v").to_pylist()):
            v = _unpacked(v, np.int64)
            w = np.flatnonzero(v)
            if len(w):
                yield pa.RecordBatch.from_arrays([pa.array([key], pa.int32()), pa.array([w.astype(np.int32)]), pa.array([v[w]])], ["context", "w", "c"])


def summed(state: DataFrame, hot: HotWords, of_bucket, width: int, cells: bool) -> tuple[DataFrame | None, np.ndarray, np.ndarray]:
    """Classes with their customers (context, w, c), sums by slot, and the numbers of pairs of one and two tokens."""
    got = state.select(*_MODEL).mapInArrow(_sums(hot, of_bucket, cells), "key int, v binary")
    got = settle(got.groupBy("key").applyInArrow(_added, "key int, v binary"), "sums")
    slots, few = np.zeros((len(hot.ids) + 1, width), np.int64), np.zeros(2, np.int64)
    for r in got.where(f"key < 0 or key >= {_CONTEXTS}").collect():
        v = _unpacked(r.v, np.int64)
        if r.key < 0:
            few = v
        else:
            slots[(r.key - _CONTEXTS) * _CHUNK :][:_CHUNK] = v.reshape(-1, width)
    return got.where(f"key >= 0 and key < {_CONTEXTS}").mapInArrow(_dish_lists, "context int, w array<int>, c array<long>") if cells else None, slots, few


def pair_buckets(src: DataFrame, words: DataFrame, hot: HotWords, n: int) -> DataFrame:
    """One row for each bucket of pairs, of about ``BUCKET_TOKENS`` tokens."""
    buckets = 4 + n // BUCKET_TOKENS
    marked = src.select(F.monotonically_increasing_id().alias("uid"), "doc_id", "held", "text")
    rare = src.select("text").mapInArrow(_rare_words(hot, buckets), "bucket int, wh long").join(words, "wh").select("bucket", "wh", "c", "lp")
    lexical = [df.mapInArrow(_word_blocks(hot, buckets), _BLOCK) for df in (words.select("wh", "c", "lp"), rare)]
    every = marked.mapInArrow(_blocks(hot, buckets), _BLOCK).unionByName(lexical[0]).unionByName(lexical[1])
    return settle(every.groupBy("bucket").applyInArrow(_gatherer(hot), _BUCKET), "pairs")


_RANGE = 12  # bits of the numbers of the texts that are summed together
_PART = "range long, uid binary, n binary, known binary, base binary, lp binary, ids binary, flags binary"


def _text_sums(table: pa.Table) -> pa.Table:
    """One row for each text of a range."""
    parts, ids = [r for r in table.to_pylist() if r["ids"] is None], [r for r in table.to_pylist() if r["ids"] is not None]
    uid = _joined([_unpacked(r["uid"], np.int64) for r in ids], np.int64)
    order = np.argsort(uid)
    uid, doc_id, flags = uid[order], _joined([_unpacked(r["ids"], np.int64) for r in ids], np.int64)[order], _joined([_unpacked(r["flags"], np.uint8) for r in ids], np.uint8)[order]
    sums = np.zeros((4, len(uid)))
    for r in parts:
        at = np.searchsorted(uid, _unpacked(r["uid"], np.int64))
        for total, name in zip(sums, ("n", "known", "base", "lp")):
            total[at] += _unpacked(r[name], np.float64)
    n, known = (np.round(x).astype(np.int64) for x in sums[:2])
    return pa.table([pa.array(doc_id, mask=(flags & 1).astype(bool)), pa.array((flags & 2) > 0), pa.array(n), pa.array(known), pa.array(sums[2]), pa.array(sums[3])], names=["doc_id", "held", "n_tokens", "n_known", "base_score", "score"])


def _scorer(s: Seating, samples: int, n_train: int, n_types: int):
    """What each bucket's pairs add to the sums of their texts, by ranges of texts; a text's id is with one of them."""
    names = [x.split()[0] for x in _PART.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                b = Bucket(row, s.hot)
                parent, tables = b.samples(s, samples)
                total, p = STRENGTH + b.by_context(b.c, s.tokens), np.zeros(len(b.c))
                for k, t in enumerate(tables):
                    p += b.c - s.discount * t + (STRENGTH + s.discount * b.by_context(t, s.tables[2 + k])) * parent
                lp = np.log10(np.maximum(p / samples / total, 1e-300))
                base = np.log10((b.words + 0.1) / (n_train + 0.1 * (n_types + 1)))
                uids, doc, times = np.cumsum(_unpacked(row["uids"], np.int64)), _unpacked(row["doc"], np.uint32), _unpacked(row["times"], np.uint32).astype(np.float64)
                pair = np.repeat(np.arange(len(lp)), _unpacked(row["n"], np.uint32))
                sums = [np.bincount(doc, times * v[pair], len(uids)) for v in (np.ones(len(lp)), b.words > 0, base, lp)]
                yield by_range(uids, sums, [])
                yield by_range(_unpacked(row["ids_of"], np.int64), [], [_unpacked(row["ids"], np.int64), _unpacked(row["flags"], np.uint8)])

    def by_range(uids: np.ndarray, sums: list[np.ndarray], ids: list[np.ndarray]) -> pa.RecordBatch:
        which, first = np.unique(uids >> _RANGE, return_index=True)
        cut = lambda v: pa.array([_packed(x) for x in np.split(v, first[1:])] if len(which) else [], pa.binary())
        none = pa.nulls(len(which), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(which), cut(uids), *(map(cut, sums) if sums else [none] * 4), *(map(cut, ids) if ids else [none] * 2)], names)

    return run


def rate(n1: float, n2: float) -> float:
    """A discount from the numbers of dishes with one and with two customers."""
    return float(min(0.95, max(0.05, n1 / max(1.0, n1 + 2 * n2))))


@dataclass
class Root:
    """The root restaurant: customers are the contexts' tables."""

    base: np.ndarray
    customers: np.ndarray
    tables: np.ndarray
    discount: float

    def chance(self, less: np.ndarray | None = None, at: np.ndarray | None = None) -> np.ndarray:
        """Probability of every dish, or of the dishes ``at`` with ``less`` of their customers gone."""
        k, s, q = (self.customers, self.tables, self.base) if at is None else (self.customers[at] - less, self.tables[at], self.base[at])
        gone = 0 if at is None else less
        s = np.minimum(s, np.maximum(k, 0))
        return (np.maximum(k - self.discount * s, 0) + (STRENGTH + self.discount * self.tables.sum()) * q) / (STRENGTH + self.customers.sum() - gone)

    def reseated(self, customers: np.ndarray, salt: int) -> Root:
        d = rate((customers == 1).sum(), (customers == 2).sum())
        open_ = STRENGTH + d * np.minimum(self.tables, customers).sum()
        tables = seat(customers.astype(np.int64), open_ * self.base, d, np.arange(len(customers), dtype=np.uint64), salt)
        return Root(self.base, customers, np.minimum(tables, customers), d)


_STATE = "context int, w array<int>, c array<long>, t array<long>, p array<float>, back array<double>"


def _context_sweep(root: Root, discount: float, add: bool, salt: int | None):
    """Add the predictive probabilities of the present seating, what the dishes have of their own (p) and the
    weight of the parent by sample (back), then seat all customers again."""

    def lists(values: list[np.ndarray], kind) -> pa.ListArray:
        cuts = np.cumsum([0, *map(len, values)]).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(cuts), pa.array(np.concatenate(values), kind))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent = root.chance()
        for batch in batches:
            for k in range(batch.num_rows):
                context = batch.column("context")[k].as_py()
                w, c, t, p, back = (batch.column(n)[k].values.to_numpy(zero_copy_only=False) for n in ("w", "c", "t", "p", "back"))
                if add:
                    p = (c - discount * t) / (STRENGTH + c.sum()) + (p if len(p) else 0)
                    back = np.append(back, (STRENGTH + discount * t.sum()) / (STRENGTH + c.sum()))
                if salt is not None:
                    pull = (STRENGTH + discount * t.sum()) * root.chance(t, w)
                    t = seat(c, pull, discount, (context * len(parent) + w).astype(np.uint64), salt).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([context], pa.int32()), lists([w], pa.int32()), lists([c], pa.int64()), lists([t], pa.int64()), lists([np.asarray(p, np.float32)], pa.float32()), lists([back], pa.float64())], ["context", "w", "c", "t", "p", "back"])

    return run


def _table_counter(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(width)
        for batch in batches:
            for w, t in zip(batch.column("w"), batch.column("t")):
                total[w.values.to_numpy()] += t.values.to_numpy()
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["t"])

    return run


def context_model(table: DataFrame, base: np.ndarray, samples: int = SAMPLES, burn_in: int = BURN_IN) -> np.ndarray:
    """log10 P(dish | context), averaged over the samples."""
    width = len(base)
    state = table.select("context", "w", "c", F.transform("c", lambda x: F.lit(1).cast("long")).alias("t"), F.array().cast("array<float>").alias("p"), F.array().cast("array<double>").alias("back"))
    state = settle(state.repartition(16, "context"), "contexts")
    few = state.agg(F.sum(F.size(F.filter("c", lambda x: x == 1))).alias("a"), F.sum(F.size(F.filter("c", lambda x: x == 2))).alias("b")).first()
    discount = rate(few.a or 0, few.b or 0)

    def tables_of(now: DataFrame) -> np.ndarray:
        return sum((np.frombuffer(r.t) for r in now.select("w", "t").mapInArrow(_table_counter(width), "t binary").collect()), np.zeros(width))

    customers = tables_of(state)
    root = Root(base, customers, np.minimum(customers, 1), 0.5).reseated(customers, 1)
    roots = []
    for k in range(burn_in + samples + 1):
        add, last = k > burn_in, k == burn_in + samples
        roots += [root.chance()] if add else []
        state = settle(state.mapInArrow(_context_sweep(root, discount, add, None if last else 31 * k + 7), _STATE), "contexts")
        if not last:
            root = root.reseated(tables_of(state), 31 * k + 8)
    out = np.empty((_CONTEXTS, width), np.float32)
    out[:] = sum(roots)
    for part in range(8):  # an eighth at a time: neither side holds two copies of it all
        got = state.where(F.col("context") % 8 == part).select("context", "w", "p", "back").toArrow()
        for context, w, p, back in zip(got.column("context").to_pylist(), got.column("w"), got.column("p"), got.column("back")):
            row = sum(b * r for b, r in zip(back.as_py(), roots))
            row[w.values.to_numpy()] += p.values.to_numpy()
            out[context] = row
    out /= np.float32(samples)
    np.maximum(out, np.float32(1e-37), out=out)
    return np.log10(out, out=out)


def scored(docs: DataFrame, parts: int = 10, samples: int = SAMPLES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, token counts, base and model scores of every row, and
    the perplexity by token."""
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), (split_of(F.col(id_col), parts) == 0).alias("held"), F.col(text_col).cast("string").alias("text"))
    words, n, v = lexicon(src, samples)
    hot = hot_words(words)
    state = pair_buckets(src, words, hot, n)
    _, slots, few = summed(state, hot, lambda b: [np.minimum(b.c, 1), b.c], 2, False)
    first = Seating(hot, rate(*few), slots[:, 1], (slots[:, 0],))
    classes, slots, _ = summed(state, hot, lambda b: [b.first_tables(first)], 1, True)
    final = replace(first, tables=(*first.tables, slots[:, 0]), chance=docs.sparkSession.sparkContext.broadcast(context_model(classes, hot.base(), samples)))
    _, slots, _ = summed(state, hot, lambda b: b.samples(final, samples)[1], samples, False)
    final = replace(final, tables=(*final.tables, *slots.T))
    parts = state.mapInArrow(_scorer(final, samples, n, v), _PART)
    sums = parts.groupBy("range").applyInArrow(_text_sums, "doc_id long, held boolean, n_tokens long, n_known long, base_score double, score double")
    return sums.select("doc_id", F.col("held").alias("held_out"), "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity"))


def op7_query(spark, sf_dir: str) -> DataFrame:
    got = scored(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return got.select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score")
