"""Array kernels over the flat byte buffer of an Arrow string column.

A batch of texts is handled as one byte array with offsets: words, their 64-bit hashes and
shingles of words come from whole-array operations, with no Python call for each word.
Memory is bounded by working through a batch in chunks of whole documents (``chunks``); one
document larger than a chunk is a chunk of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
CHUNK_BYTES = 512 << 10
_BLOCK = 128 << 10
_BASE = 0x9E3779B97F4A7C15 | 1
_powers: list[np.ndarray] = []

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Bytes of words that only white space (space, tab, LF, VT, FF, CR) ends.
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[32, 9, 10, 11, 12, 13]] = False
#: ASCII digits, lower-case ASCII letters and all bytes of non-ASCII characters.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[97:123] = ALNUM[128:] = True


def flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, dtype=kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)), at


def chunks(offsets: np.ndarray, most: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Runs [i, j) of rows with at most ``most`` bytes, or one row that has more."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1
        j = min(n, max(i + 1, j))
        yield i, j
        i = j


def mix64(h: np.ndarray) -> np.ndarray:
    """A bijection on 64-bit values, in place."""
    h ^= h >> U64(33)
    h *= U64(0xFF51AFD7ED558CCD)
    h ^= h >> U64(33)
    h *= U64(0xC4CEB9FE1A85EC53)
    h ^= h >> U64(33)
    return h


def _power_tables(n: int) -> list[np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        size = max(n, _BLOCK) + 1
        _powers[:] = []
        for base in (_BASE, pow(_BASE, -1, 1 << 64)):
            steps = np.full(size, base, U64)
            steps[0] = 1
            _powers.append(np.cumprod(steps, dtype=U64))
    return _powers


def spans_hash(b: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of b[start:end], for ascending spans that don't overlap."""
    out = np.empty(len(starts), U64)
    i = 0
    while i < len(starts):
        base = starts[i]
        j = max(i + 1, int(np.searchsorted(ends, base + _BLOCK, side="right")))
        part = b[base : ends[j - 1]]
        up, down = _power_tables(len(part))
        sums = np.zeros(len(part) + 1, U64)
        np.cumsum((part.astype(U64) + U64(1)) * up[: len(part)], out=sums[1:])
        s, e = starts[i:j] - base, ends[i:j] - base
        out[i:j] = (sums[e] - sums[s]) * down[s] + (e - s).astype(U64) * U64(0xD6E8FEB86659FD93)
        i = j
    return mix64(out)


def words(b: np.ndarray, rows: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words in ``b``, and for each row the index of its first word.

    ``rows`` are row offsets into ``b`` (one more than rows); ``table`` tells which bytes are
    part of words. No word crosses the end of a row.
    """
    if not len(b):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(rows), np.int64)
    inside = table[b]
    before = np.empty_like(inside)
    before[0] = False
    before[1:] = inside[:-1]
    first = rows[:-1]
    before[first[first < len(b)]] = False
    after = np.empty_like(inside)
    after[-1] = False
    after[:-1] = inside[1:]
    last = rows[1:] - 1
    after[last[last >= 0]] = False
    starts = np.flatnonzero(inside & ~before)
    return starts, np.flatnonzero(inside & ~after) + 1, np.searchsorted(starts, rows)


def shingles(h: np.ndarray, rows: np.ndarray, k: int, whole: bool) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of k words in each row and the row offsets into them.

    With ``whole``, a row of fewer words, but not none, gives its whole sequence as one.
    """
    n = np.diff(rows)
    count = np.maximum(n - k + 1, 0)
    short = (n > 0) & (n < k)
    if whole:
        count[short] = 1
    at = np.zeros(len(rows), np.int64)
    np.cumsum(count, out=at[1:])
    first = np.repeat(rows[:-1] - at[:-1], count) + np.arange(at[-1])
    size = np.repeat(np.minimum(n, k), count)
    acc = np.full(at[-1], 0x51ED270B9D3D9E31, U64)
    for j in range(k):
        part = h[np.minimum(first + j, max(len(h) - 1, 0))]
        step = acc * U64(0x9FB21C651E98DF25) + part
        acc = step if not (whole and short.any()) else np.where(j < size, step, acc)
    acc += size.astype(U64)
    return mix64(acc), at


def distinct(h: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each row, and the row offsets into them."""
    parts = [np.unique(h[s:e]) for s, e in zip(rows[:-1], rows[1:], strict=True)]
    at = np.zeros(len(rows), np.int64)
    np.cumsum([len(p) for p in parts], out=at[1:])
    return (np.concatenate(parts) if parts else np.zeros(0, U64)), at


def ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices start, start+1, ... of each span, one span after the other."""
    at = np.cumsum(sizes) - sizes
    return np.repeat(starts - at, sizes) + np.arange(int(sizes.sum()))


def lists(values: np.ndarray, offsets: np.ndarray, kind: pa.DataType) -> pa.Array:
    """An Arrow list column."""
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(values, kind))


def row_sums(values: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Sum of each row's values; 0 for rows that have none."""
    sums = np.zeros(len(values) + 1, dtype=np.int64 if values.dtype.kind in "bi" else values.dtype)
    np.cumsum(values, out=sums[1:])
    return sums[rows[1:]] - sums[rows[:-1]]
