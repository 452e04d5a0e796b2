"""What the operators share: reading documents, Arrow slices, hashing of words and shingles in numpy.

Words are maximal runs of bytes other than space and 0x09-0x0D. All byte positions refer to UTF-8.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from neardup.session import ship_package

#: Texts are worked on in slices of this size: their arrays fit a core's cache, and workers stay small.
SLICE_BYTES = 1 << 19


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id and text of the whole documents table."""
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/documents.parquet").select("doc_id", "text")


def texts_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; null counts as empty."""
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    n, at = len(column), column.offset
    _, offsets, data = column.buffers()
    if n == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    offs = np.frombuffer(offsets, np.int64 if wide else np.int32)[at : at + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    raw = raw[offs[0] : offs[-1]]
    return raw, offs - offs[0]


def slices(offs: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about limit bytes each; a longer row is a range of its own."""
    n, i = len(offs) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + limit, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def tidy(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches; after each one memory that isn't needed any more goes back to the system."""
    for b in batches:
        yield b
        pa.default_memory_pool().release_unused()
        _trim()


def _trim() -> None:
    import ctypes

    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def _mix_scalar(x: int) -> int:
    x = (x ^ (x >> 30)) * 0xBF58476D1CE4E5B9 & 0xFFFFFFFFFFFFFFFF
    x = (x ^ (x >> 27)) * 0x94D049BB133111EB & 0xFFFFFFFFFFFFFFFF
    return x ^ (x >> 31)


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every bit over 64 bits."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


BASE = 0x9E3779B97F4A7C15
BASE_INV = pow(BASE, -1, 1 << 64)
GOLDEN = np.uint64(0xD6E8FEB86659FD93)
BYTE_CODE = np.array([_mix_scalar(0x51ED27 + 977 * i) for i in range(256)], np.uint64)
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class _Powers:
    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE ** i and BASE ** -i modulo 2 ** 64 for i below n; at most a million of them stay in memory."""
    if len(_Powers.up) >= n:
        return _Powers.up, _Powers.down
    pair = []
    for b in (BASE, BASE_INV):
        steps = np.full(n, np.uint64(b))
        steps[0] = 1
        pair.append(np.multiply.accumulate(steps))
    if n <= 1 << 20:
        _Powers.up, _Powers.down = pair
    return pair[0], pair[1]


def prefix_hash(buf: np.ndarray) -> np.ndarray:
    """Running sums from which the hash of any byte range follows."""
    up, _ = powers(len(buf) + 1)
    out = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum(BYTE_CODE[buf] * up[: len(buf)], out=out[1:])
    return out


def range_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte ranges, by content and length alone."""
    _, down = powers(len(sums))
    return mix((sums[end] - sums[start]) * down[start] + (end - start).astype(np.uint64) * GOLDEN)


def word_bounds(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of each word; words end where a row ends."""
    n = len(buf)
    if n == 0:
        none = np.zeros(0, np.int64)
        return none, none, none
    inside = ~IS_SPACE[buf]
    full = offs[:-1] < offs[1:]
    first, last = offs[:-1][full], offs[1:][full] - 1
    before = np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    before[first] = False
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, inside[1:]
    after[last] = False
    starts = np.flatnonzero(inside & ~before)
    ends = np.flatnonzero(inside & ~after) + 1
    rows = np.searchsorted(offs, starts, side="right") - 1
    return starts, ends, rows


_STEP = [np.uint64(_mix_scalar(0xABCDEF + i) | 1) for i in range(64)]


def gram_hash(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k consecutive words, from the hashes of words."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.full(n, np.uint64(_mix_scalar(k)))
    for j in range(k):
        total += words[j : j + n] * _STEP[j % 64]
    return mix(total)


def shingle_rows(buf: np.ndarray, offs: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all word shingles in order, and for each row where its own begin and end.

    A row of 1 to k - 1 words has one shingle, its whole sequence; a row without words has none.
    """
    starts, ends, rows = word_bounds(buf, offs)
    n_rows = len(offs) - 1
    words = range_hash(prefix_hash(buf), starts, ends)
    count = np.bincount(rows, minlength=n_rows)
    grams = gram_hash(words, k)
    whole = rows[: len(grams)] == rows[k - 1 :] if len(grams) else np.zeros(0, bool)
    hashes, owner = grams[whole], rows[: len(grams)][whole]
    few = np.flatnonzero((count > 0) & (count < k))
    if len(few):
        begin = np.concatenate(([0], np.cumsum(count)))
        short = np.array([gram_hash(words[begin[r] : begin[r] + count[r]], int(count[r]))[0] for r in few], np.uint64)
        hashes, owner = np.concatenate((hashes, short)), np.concatenate((owner, few))
        order = np.argsort(owner, kind="stable")
        hashes, owner = hashes[order], owner[order]
    return hashes, np.searchsorted(owner, np.arange(n_rows + 1))
