"""Polynomial hashes over the bytes of many texts at once, and their words.

All texts of an Arrow batch lie in one byte buffer; everything here works on that buffer with NumPy,
so there is no Python step per text, word or byte.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
_ODD = U(0x9E3779B97F4A7C15)
_INVERSE = U(pow(int(_ODD), -1, 1 << 64))
_POW = np.ones(1, U)
_INV = np.ones(1, U)
#: White space of the contracts: space and the bytes 9 to 13.
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def release() -> None:
    """Gives memory that is no longer used back to the system, where its allocator can."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """`run`, whose worker doesn't keep the memory of one task until it gets another: an executor may hold several that wait."""

    def tidied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release()

    return tidied


def byte_values(seed: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(1, 1 << 63, 256, dtype=U) * U(2) + U(1)


VALUES = byte_values(11)
VALUES_2 = byte_values(12)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the base and of its inverse, modulo 2**64."""
    global _POW, _INV
    if len(_POW) < n:
        size = max(n + n // 4, 1 << 18)
        for base, put in ((_ODD, "_POW"), (_INVERSE, "_INV")):
            p = np.full(size, base, U)
            p[0] = 1
            globals()[put] = np.multiply.accumulate(p)
    return _POW[:n], _INV[:n]


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def prefix(data: np.ndarray, values: np.ndarray = VALUES) -> np.ndarray:
    """Hashes of all prefixes; any substring's hash follows from two of them."""
    out = np.zeros(len(data) + 1, U)
    np.cumsum(values[data] * powers(len(data))[1], out=out[1:])
    return out


def raw(p: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Hashes of data[lo:hi], the same wherever the substring stands."""
    return (p[hi] - p[lo]) * powers(len(p))[0][lo]


def span(p: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    return mix(raw(p, lo, hi) + (hi - lo).astype(U))


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and the bounds of its rows; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, bounds, data = column.buffers()
    if bounds is None or len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    bounds = np.frombuffer(bounds, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[bounds[0] : bounds[-1]], bounds - bounds[0]


def pieces(bounds: np.ndarray, most: int = 1 << 19) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about `most` bytes together; a longer row is a range of its own."""
    i, n = 0, len(bounds) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(bounds, bounds[i] + most, "right")) - 1)
        yield i, j
        i = j


def words(data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of each word, and the row it belongs to; words don't cross rows."""
    solid = ~SPACE[data]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    cut = bounds[:-1][bounds[:-1] < bounds[1:]]
    first[cut] = solid[cut]
    last = np.zeros(len(data) + 1, bool)
    last[1:] = solid
    last[1:-1] &= ~solid[1:]
    last[cut[cut > 0]] |= solid[cut[cut > 0] - 1]
    lo, hi = np.flatnonzero(first), np.flatnonzero(last)
    row = np.searchsorted(bounds, lo, "right") - 1
    return lo, hi, row


def shingles(data: np.ndarray, bounds: np.ndarray, k: int, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every run of k words, in order; a row of fewer words has one run of all of them."""
    if lower:
        data = LOWER[data]
    lo, hi, row = words(data, bounds)
    if not len(lo):
        return np.zeros(0, np.int64), np.zeros(0, U)
    word = span(prefix(data), lo, hi)
    n = len(word)
    if n >= k:
        run = word[: n - k + 1].copy()
        for i in range(1, k):
            run = mix(run * U(0x100000001B3) + word[i : n - k + 1 + i])
        whole = row[: n - k + 1] == row[k - 1 :]
        rows, out = row[: n - k + 1][whole], run[whole]
    else:
        rows, out = np.zeros(0, np.int64), np.zeros(0, U)
    count = np.bincount(row, minlength=len(bounds) - 1)
    few = np.flatnonzero((count > 0) & (count < k))
    if len(few):
        begin = np.searchsorted(row, few)
        short = np.empty(len(few), U)
        for size in np.unique(count[few]):
            at = count[few] == size
            run = word[begin[at]].copy()
            for i in range(1, size):
                run = mix(run * U(0x100000001B3) + word[begin[at] + i])
            short[at] = mix(run + U(size))
        rows, out = np.concatenate([rows, few]), np.concatenate([out, short])
        order = np.argsort(rows, kind="stable")
        rows, out = rows[order], out[order]
    return rows, out


def distinct(rows: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct (row, value) pairs."""
    order = np.lexsort((values, rows))
    rows, values = rows[order], values[order]
    if not len(rows):
        return rows, values
    new = np.r_[True, (rows[1:] != rows[:-1]) | (values[1:] != values[:-1])]
    return rows[new], values[new]


def binary(data: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """A binary column of data[bounds[i]:bounds[i + 1]]."""
    return pa.Array.from_buffers(pa.binary(), len(bounds) - 1, [None, pa.py_buffer(np.ascontiguousarray(bounds, np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def longs(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64), pa.int64())
