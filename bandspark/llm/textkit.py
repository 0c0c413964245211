"""Vectorised kernels over the raw UTF-8 bytes of Arrow string columns.

A *word* is a maximal run of bytes outside ``\\x20 \\x09-\\x0D``; as every byte of a multi-byte
character lies outside that set, this equals ``[^\\x20\\x09-\\x0D]+`` over code points.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bytes handled by one kernel call; whole documents, so a longer document makes a longer call.
BLOCK_BYTES = 1 << 20
#: Bytes that are hashed at once (a longer word is one piece): tables of powers of that length stay in a worker.
HASH_BYTES = 1 << 17

WHITE = np.zeros(256, bool)
WHITE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_U = np.uint64
_MIX1, _MIX2 = _U(0xBF58476D1CE4E5B9), _U(0x94D049BB133111EB)
_BASE = 0x9E3779B97F4A7C15 | 1
_TABLE = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64)
_TABLE_LOWER = _TABLE[LOWER]
_power = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


#: Bits of a filter of keys: 8 MB whatever the number of keys.
FILTER_BITS = 1 << 26


def key_filter(keys: DataFrame, key: Column) -> DataFrame:
    """(_k, _bits): a bitmap over hashed keys, at most FILTER_BITS / 32768 rows of 4 KB. It says yes to all of the keys, and to few others."""
    spot = F.pmod(key, F.lit(FILTER_BITS))
    return keys.groupBy(F.bitmap_bucket_number(spot).alias("_k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(spot)).alias("_bits"))


def with_maybe(rows: DataFrame, key: Column, bits: DataFrame) -> DataFrame:
    """Adds ``_maybe``: whether the filter says yes. Rows it denies need no join, so their texts need not be dealt out."""
    spot = F.pmod(key, F.lit(FILTER_BITS))
    at = F.bitmap_bit_position(spot)
    byte = F.conv(F.hex(F.substring("_bits", F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    yes = F.floor(byte / F.pow(F.lit(2), at % 8)).cast("int") % 2 == 1
    met = rows.withColumn("_k", F.bitmap_bucket_number(spot)).join(F.broadcast(bits), "_k", "left")  # bounded as said
    return met.withColumn("_maybe", F.coalesce(yes, F.lit(False))).drop("_k", "_bits")


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads 64-bit values."""
    h = h ^ (h >> _U(30))
    h = h * _MIX1
    h ^= h >> _U(27)
    h *= _MIX2
    h ^= h >> _U(31)
    return h


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_power["up"]) < n:
        size = 1 << int(n - 1).bit_length()
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            p, step = np.ones(1, np.uint64), base
            while len(p) < size:
                p = np.concatenate([p, p * _U(step)])
                step = step * step % (1 << 64)
            _power[name] = p
    return _power["up"], _power["down"]


def string_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (n + 1) of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    if not wide and not pa.types.is_string(column.type):
        column = column.cast(pa.string())
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1] if offsets is not None and len(column) else np.zeros(1, np.int32)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    lo, hi = int(offsets[0]), int(offsets[-1])
    return data[lo:hi], offsets.astype(np.int64) - lo


def blocks(offsets: np.ndarray, size: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``size`` bytes each, whole rows, at least one row."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + size, side="right")) - 1
        to = min(n, max(to, at + 1))
        yield at, to
        at = to


def small_batches(batches: Iterator[pa.RecordBatch], column: str | int = "text", size: int = 4 * BLOCK_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``size`` bytes of text, so that what is made of one batch stays small; unused memory goes back in between."""
    for batch in batches:
        _, offsets = string_buffer(batch.columns[column] if isinstance(column, int) else batch.column(column))
        for a, b in blocks(offsets, size):
            yield batch.slice(a, b - a)
        pa.default_memory_pool().release_unused()
    give_back()


def give_back() -> None:
    """Freed memory goes back to the system: a worker that waits for its next task would keep it."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim:
        trim(0)


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of all words, and the word offsets of each row (n + 1)."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    solid = ~WHITE[data]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    last = solid.copy()
    last[:-1] &= ~solid[1:]
    cut = offsets[1:-1]
    cut = cut[(cut > 0) & (cut < n)]
    first[cut] = solid[cut]
    last[cut - 1] = solid[cut - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = True) -> np.ndarray:
    """64-bit polynomial hash of every word (A-Z lowered if asked), by differences of prefix sums."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    out = np.empty(len(starts), np.uint64)
    table = _TABLE_LOWER if lower else _TABLE
    at = 0
    while at < len(starts):  # pieces end between words, so memory stays bounded in a long document
        to = max(at + 1, int(np.searchsorted(ends, starts[at] + HASH_BYTES, side="right")))
        lo, hi = int(starts[at]), int(ends[to - 1])
        up, down = _powers(hi - lo)
        sums = np.zeros(hi - lo + 1, np.uint64)
        np.cumsum(table[data[lo:hi]] * up[: hi - lo], out=sums[1:])
        s, e = starts[at:to] - lo, ends[at:to] - lo
        out[at:to] = mix((sums[e] - sums[s]) * down[s] + (e - s).astype(np.uint64))
        at = to
    return out


def shingle_hashes(words: np.ndarray, row_offsets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word windows of each row, in text order, and their row offsets.

    A row with 1 to k - 1 words has its whole sequence as its one shingle, a row without words none."""
    counts = np.diff(row_offsets)
    made = np.where(counts >= k, counts - k + 1, (counts > 0).astype(counts.dtype))
    offsets = np.zeros(len(counts) + 1, np.int64)
    np.cumsum(made, out=offsets[1:])
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64), offsets
    windows = max(0, n - k + 1)
    h = np.full(windows, _U(0x2545F4914F6CDD1D))
    for j in range(k):
        h = mix(h * _U(0xD6E8FEB86659FD93) + words[j : j + windows])
    ok = np.ones(windows, bool)
    edge = row_offsets[1:-1]
    for j in range(1, k):
        at = edge - j
        ok[at[(at >= 0) & (at < windows)]] = False
    out = np.empty(offsets[-1], np.uint64)
    long_rows = counts >= k
    into = np.repeat(long_rows, made)
    # windows of rows with k words or more, in order
    starts = row_offsets[:-1][long_rows]
    if len(starts):
        sizes = made[long_rows]
        index = np.repeat(starts - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
        out[into] = h[index]
    for r in np.flatnonzero((counts > 0) & (counts < k)):
        v = np.array([0xA0761D6478BD642F + int(counts[r])], np.uint64)
        for i in range(row_offsets[r], row_offsets[r + 1]):
            v = mix(v * _U(0xE7037ED1A0B428DB) + words[i : i + 1])
        out[offsets[r]] = v[0]
    return out, offsets
