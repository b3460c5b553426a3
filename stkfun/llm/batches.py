"""Vectorised word handling over Arrow batches of whole texts.

Words are maximal runs of bytes other than space and 09-0D, the same as
``[^\\x20\\x09-\\x0D]+`` over code points, since UTF-8 never uses those bytes
inside a longer character.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

_MIX1 = np.uint64(0xFF51AFD7ED558CCD)
_MIX2 = np.uint64(0xC4CEB9FE1A85EC53)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_LONG_WORD = 256


def small_batches(batches: Iterator[pa.RecordBatch], column: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cut batches so that each holds about ``limit`` bytes of ``column`` (one row at least)."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        ends = np.cumsum(lengths(batch.column(column)))
        at = 0
        while at < n:
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + limit, "right")))
            yield batch.slice(at, to - at)
            at = to


def lengths(column: pa.Array) -> np.ndarray:
    """Bytes of each text, nulls as 0."""
    return np.diff(_offsets(column))


def _offsets(column: pa.Array) -> np.ndarray:
    wide = (pa.types.is_large_string, pa.types.is_large_binary, pa.types.is_large_list)
    width = np.int64 if any(f(column.type) for f in wide) else np.int32
    return np.frombuffer(column.buffers()[1], width)[column.offset : column.offset + len(column) + 1].astype(np.int64)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The texts' bytes back to back and the n+1 offsets; null is empty."""
    if column.null_count:
        column = column.fill_null("")
    off = _offsets(column)
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def lowered(raw: np.ndarray) -> np.ndarray:
    """A-Z to a-z."""
    return _LOWER[raw]


def word_spans(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and the index of each document's first word (n+1 entries)."""
    if not len(raw):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    inside = ~_SPACE[raw]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    edge = off[(off > 0) & (off < len(raw))]
    first[edge] = inside[edge]
    last[edge - 1] = inside[edge - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, off)


def word_codes(column: pa.Array) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """All words, A-Z lowered, as places in an array of different words (which may hold an
    empty one that no place names); that array; each text's number of words."""
    if column.null_count:
        column = column.fill_null("")
    lists = pc.ascii_split_whitespace(pc.ascii_lower(column))
    words = lists.flatten().dictionary_encode()
    code, first = words.indices.to_numpy(), _offsets(lists)
    first, counts = first - first[0], np.diff(first)
    void = np.flatnonzero((lengths(words.dictionary) == 0)[code])
    if len(void):
        code = np.delete(code, void)
        counts -= np.bincount(np.searchsorted(first, void, "right") - 1, minlength=len(counts))
    words = words.dictionary
    del lists
    pa.default_memory_pool().release_unused()  # workers stay, and keep what they once had
    return code, words, counts


def distinct(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each value's place among the different values, and those as they first come."""
    found = pa.array(values).dictionary_encode()
    return found.indices.to_numpy(), found.dictionary.to_numpy()


def mixed(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    h = h ^ (h >> np.uint64(33))
    h = h * _MIX1
    h = h ^ (h >> np.uint64(29))
    h = h * _MIX2
    return h ^ (h >> np.uint64(32))


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit hash of each word's bytes, the same in every process."""
    size = ends - starts
    h = (size.astype(np.uint64) + np.uint64(seed)) * _ODD
    if not len(size):
        return h
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    eight = np.lib.stride_tricks.sliding_window_view(padded, 8)
    pick = slice(None)
    at, left, part = starts, np.minimum(size, _LONG_WORD), h
    k = 0
    while True:
        value = eight[at].view(np.uint64).ravel()
        short = left < 8
        if short.any():
            keep = (np.uint64(1) << (np.minimum(left, 7).astype(np.uint64) * np.uint64(8))) - np.uint64(1)
            value = np.where(short, value & keep, value)
        part = mixed(part ^ value)
        h[pick] = part
        k += 8
        more = np.flatnonzero(np.minimum(size, _LONG_WORD) > k)
        if not len(more):
            break
        pick, at, left, part = more, starts[more] + k, np.minimum(size[more], _LONG_WORD) - k, h[more]
    for i in np.flatnonzero(size > _LONG_WORD):
        h[i] = xxhash.xxh64_intdigest(raw[starts[i] : ends[i]].tobytes(), seed)
    return h


def gram_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of ``n`` consecutive words; runs may cross documents, callers cut them."""
    if len(h) < n:
        return np.zeros(0, np.uint64)
    out = h[: len(h) - n + 1].copy()
    for j in range(1, n):
        out = mixed(out * _ODD + h[j : len(h) - n + 1 + j])
    return out


_ODD_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def span_hashes(h: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Hash of any runs of words: differences of prefix sums, shifted to one place."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    n = len(h)
    powers = np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(n - 1, _ODD, np.uint64)]))
    back = np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(n - 1, _ODD_INVERSE, np.uint64)]))
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * powers, dtype=np.uint64)])
    return mixed((sums[starts + sizes] - sums[starts]) * back[starts] + np.asarray(sizes, np.uint64))


def sliding(values: np.ndarray, width: int, best=np.minimum) -> np.ndarray:
    """Minimum (or maximum) of each window of ``width`` values, by doubling."""
    span, out = 1, values
    while span * 2 <= width:
        out = best(out[: len(out) - span], out[span:])
        span *= 2
    rest = width - span
    return best(out[: len(out) - rest], out[rest:]) if rest else out
