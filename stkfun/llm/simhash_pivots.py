"""SimHash near-duplicates by pivot distance tables.

Fingerprints: 64 majority bits over the XXH64 (seed 42) of word shingles.
Links: fingerprints at ``max_bits`` or fewer differing bits. With ``blocks``
bit blocks, two linked fingerprints agree on at least ``blocks - max_bits`` of
them, so equality on every choice of that many blocks brings each link together
at least once. Inside such a bucket a table of Hamming distances to reference
fingerprints discards pairs whose largest coordinate difference exceeds
``max_bits`` (the triangle inequality makes that safe); survivors are verified
bit by bit. A large bucket is cut by further agreeing blocks of its free bits
and returns a spanning forest, never all its pairs.

Near copies at a shingle similarity of 0.8 differ in up to a quarter of the bits,
too many for blocks. ``similar_links`` brings them together by equal bands of
smallest shingle hashes instead and confirms pairs by their shingles inside the
bucket; what leaves a bucket is a forest of confirmed pairs.

Defined cases: null and wordless texts have fingerprint 0 and link like any
other; rows are kept one to one, repeated rows and null ids included; a
component of null ids alone has a null component_id; an empty table gives an
empty result; only the id and text columns are read, others may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.functions.shared import settle, settle_counted
from stkfun.llm.batches import gram_hashes, lowered, mixed, small_batches, text_bytes, word_hashes, word_spans

PIVOTS = 24
_ROW = ["doc_id", "row_key", "row_key2"]
_DENSE = 2048
_NEAR_ROWS = 12


def fingerprint_one(words: bytes, starts: list[int], ends: list[int], shingle: int) -> int:
    """Majority bits over the shingles of one text of single-spaced words."""
    n = len(starts)
    if not n:
        return 0
    view, digest = memoryview(words), xxhash.xxh64_intdigest
    if n < shingle:
        hashes = [digest(view[starts[0] : ends[-1]], 42)]
    else:
        hashes = [digest(view[a:b], 42) for a, b in zip(starts, ends[shingle - 1 :])]
    bits = np.unpackbits(np.array(hashes, np.uint64).view(np.uint8), bitorder="little").reshape(-1, 64)
    ones = np.add.reduce(bits, axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def _fingerprinter(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            raw, off = text_bytes(batch.column("text"))
            raw = lowered(raw)
            out = np.zeros(batch.num_rows, np.uint64)
            for i in range(batch.num_rows):
                words = b" ".join(raw[off[i] : off[i + 1]].tobytes().split())
                at = np.frombuffer(words, np.uint8)
                s, e, _ = word_spans(at, np.array([0, len(at)]))
                out[i] = fingerprint_one(words, s.tolist(), e.tolist(), shingle)
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in _ROW), pa.array(out.view(np.int64))], [*_ROW, "fp"])

    return run


#: At a similarity of 0.8 a pair without a common band is expected 3 times in a million.
BANDS, BAND_ROWS = 24, 4


def shingle_hashes(raw: np.ndarray, off: np.ndarray, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """The shingle hashes of all texts back to back, and where each text's begin; a shorter text is one shingle."""
    starts, ends, first = word_spans(raw, off)
    words, counts = word_hashes(raw, starts, ends), np.diff(first)
    owner = np.repeat(np.arange(len(counts)), counts)
    grams = gram_hashes(words, shingle)
    inside = owner[: len(grams)] == owner[shingle - 1 :] if len(grams) else np.zeros(0, bool)
    grams, owner = grams[inside], owner[: len(grams)][inside]
    whole = np.array([xxhash.xxh64_intdigest(words[a:b].tobytes()) for a, b in zip(first, first[1:]) if b - a < shingle], np.uint64)
    short = np.flatnonzero(counts < shingle)
    order = np.argsort(np.concatenate([owner, short]), kind="stable")
    hashes = mixed(np.concatenate([grams, whole])[order])
    return hashes, np.searchsorted(np.concatenate([owner, short])[order], np.arange(len(counts)))


def smallest_hashes(hashes: np.ndarray, heads: np.ndarray, n: int = BANDS * BAND_ROWS) -> np.ndarray:
    """For each text the least value of ``n`` hash functions over its shingles (32 bits each)."""
    out = np.empty((len(heads), n), np.uint32)
    for k, factor in enumerate(pivot_values(n) | np.uint64(1)):
        out[:, k] = np.minimum.reduceat((hashes * factor) >> np.uint64(32), heads)
    return out


def _profiler(shingle: int):
    mark = _fingerprinter(shingle)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            raw, off = text_bytes(batch.column("text"))
            hashes, heads = shingle_hashes(lowered(raw), off, shingle)
            least = smallest_hashes(hashes, heads)
            keys = np.stack([gram_hashes_of_rows(least[:, k * BAND_ROWS : (k + 1) * BAND_ROWS], k) for k in range(BANDS)], 1)
            sig = np.add.reduceat(mixed(hashes + np.uint64(1)), heads)
            base = pa.Table.from_batches(mark([batch])).combine_chunks()
            cuts = pa.array(np.arange(0, len(least) * BANDS + 1, BANDS, dtype=np.int32))
            extra = [pa.array(sig.view(np.int64)), pa.ListArray.from_arrays(cuts, pa.array(keys.ravel().view(np.int64)))]
            yield pa.RecordBatch.from_arrays([*(base.column(n).combine_chunks() for n in (*_ROW, "fp")), *extra], [*_ROW, "fp", "sig", "keys"])

    return run


def _shingler(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            raw, off = text_bytes(batch.column("text"))
            hashes, heads = shingle_hashes(lowered(raw), off, shingle)
            sets = [np.unique(h) for h in np.split(hashes, heads[1:])]
            cuts = pa.array(np.cumsum([0, *map(len, sets)]).astype(np.int32))
            yield pa.RecordBatch.from_arrays([batch.column("node"), batch.column("fp"), pa.ListArray.from_arrays(cuts, pa.array(np.concatenate(sets).view(np.int64)))], ["node", "fp", "grams"])

    return run


def gram_hashes_of_rows(rows: np.ndarray, seed: int) -> np.ndarray:
    """One 64-bit hash of each row."""
    out = np.full(len(rows), seed + 1, np.uint64)
    for column in rows.T:
        out = mixed(out * np.uint64(0x9E3779B97F4A7C15) + column)
    return out


def confirmed(values: np.ndarray, off: np.ndarray, similarity: float) -> np.ndarray:
    """Index pairs of sets at the similarity that span every component of such pairs.

    Sets are ``values[off[i]:off[i + 1]]``, each without repeats. A reached set is
    held against those not reached yet, so a group costs few comparisons and no
    pair is concluded from others."""
    sizes = np.diff(off)
    ids = np.unique(values, return_inverse=True)[1]
    member = np.zeros(int(ids.max(initial=-1)) + 1, bool)
    rest, found = np.arange(len(sizes)), []
    while len(rest):
        queue, rest = [rest[0]], rest[1:]
        while queue and len(rest):
            s = queue.pop()
            able = np.minimum(sizes[rest], sizes[s]) >= similarity * np.maximum(sizes[rest], sizes[s]) - 1e-9
            near = rest[able]
            if not len(near):
                continue
            own = ids[off[s] : off[s + 1]]
            member[own] = True
            heads = np.cumsum(sizes[near]) - sizes[near]
            at = np.arange(sizes[near].sum()) + np.repeat(off[near] - heads, sizes[near])
            both = np.add.reduceat(member[ids[at]].astype(np.int64), heads)
            member[own] = False
            hit = both >= similarity * (sizes[s] + sizes[near] - both) - 1e-9
            if hit.any():
                found.append(np.stack([np.full(hit.sum(), s), near[hit]], 1))
                queue += near[hit].tolist()
                able[able] = hit
                rest = rest[~able]
    return np.concatenate(found) if found else np.zeros((0, 2), np.int64)


def _confirmer(similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def edges(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
            whole = pa.Table.from_batches(parts).combine_chunks()
            fps, grams = whole.column("fp").to_numpy(), whole.column("grams").combine_chunks()
            off = np.concatenate([[0], np.cumsum(grams.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
            pairs = confirmed(grams.flatten().to_numpy(zero_copy_only=False), off, similarity)
            return pa.RecordBatch.from_arrays([pa.array(fps[pairs[:, 0]]), pa.array(fps[pairs[:, 1]])], ["u", "v"])

        held, last = [], None
        for batch in batches:
            key = batch.column("key").to_numpy(zero_copy_only=False)
            if not len(key):
                continue
            cuts = [0, *(np.flatnonzero(np.diff(key)) + 1).tolist(), len(key)]
            for a, b in zip(cuts, cuts[1:]):
                if held and key[a] != last:
                    yield edges(held)
                    held = []
                held.append(batch.slice(a, b - a))
                last = key[a]
        if held:
            yield edges(held)

    return run


def similar_links(src: DataFrame, profiles: DataFrame, similarity: float, shingle: int) -> DataFrame:
    """u, v: edges between fingerprints of texts at the shingle similarity.

    ``src``: row_key, text; ``profiles``: fp, row_key, sig, keys. Every different text
    is searched by its bands; buckets of the same members are looked at once; a
    bucket's pairs are confirmed by their shingles before any is left out."""
    # Equal sig: equal shingles, so equal keys.
    nodes = profiles.groupBy("fp", "sig").agg(F.min("row_key").alias("row_key"), F.any_value("keys").alias("keys"))
    nodes = settle(nodes.select(F.xxhash64("fp", "sig").alias("node"), "fp", "row_key", "keys"), "profiles")
    spread = nodes.select("node", F.explode("keys").alias("key"))
    shared = spread.groupBy("key").agg(F.count("*").alias("n"), F.bit_xor("node").alias("a"), F.bit_xor(F.xxhash64("node")).alias("b")).where("n > 1")
    members = settle(spread.join(shared.groupBy("n", "a", "b").agg(F.min("key").alias("key")).select("key"), "key"), "members")
    wanted = nodes.join(members.select("node").distinct(), "node").select("node", "fp", "row_key")
    texts = src.join(wanted, "row_key").groupBy("node", "fp").agg(F.any_value("text").alias("text"))
    sets = settle(texts.mapInArrow(_shingler(shingle), "node long, fp long, grams array<long>"), "shingles")
    dealt = members.join(sets, "node").select("key", "fp", "grams").repartition("key").sortWithinPartitions("key")
    return dealt.mapInArrow(_confirmer(similarity), "u long, v long").where("u <> v").distinct()


def text_marks(text: Column) -> list[Column]:
    """Two independent hashes that stand for a whole text, as row_key and row_key2."""
    text = text.cast("string")
    return [F.xxhash64(text).alias("row_key"), F.xxhash64(F.lit("second"), text).alias("row_key2")]


def texts_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), *text_marks(F.col(text_col)), F.col(text_col).cast("string").alias("text"))


def fingerprints(docs: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, row_key and row_key2 (of the text), fp (as a signed long) for every row."""
    return texts_of(docs, id_col, text_col).mapInArrow(_fingerprinter(shingle), "doc_id long, row_key long, row_key2 long, fp long")


def block_masks(blocks: int, keep: int) -> list[int]:
    """For every choice of ``keep`` blocks, the mask of their bits."""
    edges = [round(i * 64 / blocks) for i in range(blocks + 1)]
    masks = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(edges, edges[1:])]
    return [sum(c) for c in combinations(masks, keep)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def pivot_values(n: int = PIVOTS) -> np.ndarray:
    """Reference fingerprints, fixed by their index."""
    return np.array([xxhash.xxh64_intdigest(f"pivot {i}".encode(), 42) for i in range(n)], np.uint64)


def distance_table(fps: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    """Hamming distances, one row for each pivot."""
    return np.bitwise_count(pivots[:, None] ^ fps[None, :]).astype(np.int8)


def close_pairs(fps: np.ndarray, table: np.ndarray, i: np.ndarray, j: np.ndarray, max_bits: int) -> np.ndarray:
    """Which index pairs link: pivots discard, bits verify."""
    for row in table:
        stay = np.abs(row[i] - row[j]) <= max_bits
        i, j = i[stay], j[stay]
        if not len(i):
            return np.zeros((0, 2), np.int64)
    ok = np.bitwise_count(fps[i] ^ fps[j]) <= max_bits
    return np.stack([i[ok], j[ok]], 1)


def _merge(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    while len(i):
        a, b = label[i], label[j]
        apart = a != b
        if not apart.any():
            break
        i, j, a, b = i[apart], j[apart], a[apart], b[apart]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    return label


def forest(fps: np.ndarray, pivots: np.ndarray, max_bits: int) -> np.ndarray:
    """For distinct fingerprints, the smallest index of each one's component."""
    label = np.arange(len(fps))

    def link(idx: np.ndarray, bits: list[int]) -> None:
        nonlocal label
        if len(idx) <= _DENSE or len(bits) <= 12:
            part = fps[idx]
            table = distance_table(part, pivots)
            for a in range(0, len(idx), 128):
                b = min(a + 128, len(idx))
                alive = np.abs(table[0][a:b, None] - table[0][None, :]) <= max_bits
                for row in table[1:4]:
                    alive &= np.abs(row[a:b, None] - row[None, :]) <= max_bits
                i, j = np.nonzero(np.triu(alive, a + 1))
                pairs = close_pairs(part, table[4:], i + a, j, max_bits)
                label = _merge(label, idx[pairs[:, 0]], idx[pairs[:, 1]])
            return
        for part in np.array_split(np.array(bits), max_bits + 1):
            mask = np.uint64(sum(1 << int(b) for b in part))
            key = fps[idx] & mask
            order = np.argsort(key, kind="stable")
            cuts = np.flatnonzero(np.diff(key[order])) + 1
            rest = [b for b in bits if b not in set(part.tolist())]
            for group in np.split(order, cuts):
                if len(group) > 1:
                    link(idx[group], rest)

    agree = np.bitwise_and.reduce(~(fps ^ fps[0]))
    link(np.arange(len(fps)), [b for b in range(64) if not (int(agree) >> b) & 1])
    return label


def _linker(max_bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pivots = pivot_values()
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def edges(key: np.ndarray, fps: np.ndarray) -> pa.RecordBatch:
            found = []
            starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
            sizes = np.diff(np.append(starts, len(key)))
            table = None
            small = np.repeat(sizes <= _NEAR_ROWS, sizes)
            for d in range(1, min(_NEAR_ROWS, int(sizes.max(initial=1)))):
                i = np.flatnonzero((key[:-d] == key[d:]) & small[:-d])
                if not len(i):
                    break
                if table is None:
                    table = distance_table(fps, pivots)
                pairs = close_pairs(fps, table, i, i + d, max_bits)
                found.append(np.stack([fps[pairs[:, 0]], fps[pairs[:, 1]]], 1))
            for a, n in zip(starts[sizes > _NEAR_ROWS], sizes[sizes > _NEAR_ROWS]):
                group = np.unique(fps[a : a + n])
                root = forest(group, pivots, max_bits)
                child = np.flatnonzero(root != np.arange(len(group)))
                found.append(np.stack([group[child], group[root[child]]], 1))
            out = np.concatenate(found) if found else np.zeros((0, 2), np.uint64)
            out = np.unique(out[out[:, 0] != out[:, 1]], axis=0) if len(out) else out
            return pa.RecordBatch.from_arrays([pa.array(out[:, 0].copy().view(np.int64)), pa.array(out[:, 1].copy().view(np.int64))], ["u", "v"])

        for batch in batches:
            key = batch.column("key").to_numpy(zero_copy_only=False)
            fps = batch.column("fp").to_numpy(zero_copy_only=False).view(np.uint64)
            if not len(key):
                continue
            # All but the last bucket, which may go on, is whole; parts of it are only gathered.
            cut = int(np.flatnonzero(key != key[-1])[-1]) + 1 if (key != key[-1]).any() else 0
            if cut or held and held[-1][0][-1] != key[0]:
                held.append((key[:cut], fps[:cut]))
                yield edges(*(np.concatenate(v) for v in zip(*held)))
                held = []
            held.append((key[cut:], fps[cut:]))
        if held:
            yield edges(*(np.concatenate(v) for v in zip(*held)))

    return run


def links(fps: DataFrame, max_bits: int = 3, blocks: int = 6) -> DataFrame:
    """u, v: edges between distinct fingerprints that connect every linked pair.

    ``fps`` has distinct values in ``fp``."""
    masks = [signed(m) for m in block_masks(blocks, blocks - max_bits)]
    keys = F.array(*[F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(m))) for i, m in enumerate(masks)])
    spread = fps.select("fp", F.explode(keys).alias("key")).repartition("key").sortWithinPartitions("key")
    return spread.select("key", "fp").mapInArrow(_linker(max_bits), "u long, v long").distinct()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """node, root: each linked node and the smallest node that it reaches.

    Alternating star contraction: neighbours above a node hang from its smallest
    neighbour, then those below do; each round is one written table."""
    now = settle(edges.select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).where("a <> b").distinct(), "edges")
    mark = None
    for _ in range(max_rounds):
        both = now.union(now.select(F.col("b"), F.col("a"))).toDF("x", "y")
        low = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
        large = both.join(low, "x").where("y > x").select(F.col("y").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
        now, seen = settle_counted(small.distinct(), "edges", n=F.count("*"), total=F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")))
        if seen == mark:
            break
        mark = seen
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))


def near_duplicates(docs: DataFrame, shingle: int = 3, max_bits: int = 3, blocks: int = 6, similarity: float | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, row_key, row_key2, fp, root (smallest fingerprint of the component), component_id.

    ``similarity`` also links texts whose shingles are as similar, at any distance."""
    if similarity is None:
        marked = settle(fingerprints(docs, shingle, id_col, text_col), "fingerprints")
    else:
        src = texts_of(docs, id_col, text_col)
        marked = settle(src.mapInArrow(_profiler(shingle), "doc_id long, row_key long, row_key2 long, fp long, sig long, keys array<long>"), "fingerprints")
    distinct = marked.groupBy("fp").agg(F.min("doc_id").alias("low"))
    edges = links(distinct.select("fp"), max_bits, blocks)
    if similarity is not None:
        edges = edges.union(similar_links(src.select("row_key", "text"), marked, similarity, shingle))
    comp = components(edges)
    rooted = distinct.join(comp, distinct.fp == comp.node, "left").select("fp", "low", F.coalesce("root", "fp").alias("root"))
    rooted = settle(rooted, "rooted")
    whole = rooted.groupBy("root").agg(F.min("low").alias("component_id"))
    named = rooted.join(whole, "root").select("fp", "root", "component_id")
    return marked.select(*_ROW, "fp").join(named, "fp").select(*_ROW, "fp", "root", "component_id")


def keep_one(docs: DataFrame, shingle: int = 5, max_bits: int = 3, similarity: float | None = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` without near-duplicates: of each component the row with
    the smallest id stays (null ids last), of several the one with the smallest
    text hash; rows of the same id and text count as one row."""
    found = near_duplicates(docs, shingle, max_bits, similarity=similarity, id_col=id_col, text_col=text_col)
    keepers = found.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.coalesce("doc_id", F.lit(0)).alias("id"), "row_key", "row_key2")).alias("k"))
    key = ["none", "id", "row_key", "row_key2"]
    rows = docs.select(F.struct(*docs.columns).alias("doc"), F.col(id_col).isNull().alias("none"), F.coalesce(F.col(id_col).cast("long"), F.lit(0)).alias("id"), *text_marks(F.col(text_col)))
    kept = rows.join(keepers.select("k.*"), key, "left_semi")
    return kept.dropDuplicates(key).select("doc.*")


def op1_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
