"""Vectorised word scanning over the UTF-8 buffers of Arrow string columns.

Every operator here reads texts as Arrow batches.  The functions below work on slices of a batch (whole
documents, about ``SLICE`` bytes of text together), so that the memory of a task depends on the slice and on its
longest document only.  Words are maximal runs of bytes outside ``\\x20\\x09-\\x0D``; A-Z may be lower-cased.
A word is identified by a 64-bit polynomial hash over a random byte table; two different words of a corpus share
one with a chance of about (number of words)^2 / 2^65.
"""

from __future__ import annotations

import ctypes
import functools
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

SLICE = 1 << 20
U = np.uint64

SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_TABLE = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
_TABLE_LOWER = _TABLE[LOWER]
_BASE = U(0x9E3779B97F4A7C15)
_BASE_INVERSE = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_powers = np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)


def tidy(run: Callable) -> Callable:
    """Wraps a function of Arrow batches: at its end freed memory goes back to the system, since Python workers outlive their tasks."""

    @functools.wraps(run)
    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (OSError, AttributeError):
                pass  # another C library

    return wrapped


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash: every input bit reaches every output bit."""
    x = x ^ (x >> U(33))
    x = x * U(0xFF51AFD7ED558CCD)
    x = x ^ (x >> U(33))
    x = x * U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(33))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        size = max(n, SLICE + 1)
        up = np.full(size, _BASE, dtype=np.uint64)
        down = np.full(size, _BASE_INVERSE, dtype=np.uint64)
        up[0] = down[0] = 1
        _powers = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _powers


def fold_latin(data: np.ndarray) -> np.ndarray:
    """The bytes with the two-byte capitals U+00C0 to U+00DE (but the multiplication sign) in lower case."""
    lead = np.flatnonzero(data[:-1] == 0xC3) + 1
    lead = lead[(data[lead] >= 0x80) & (data[lead] <= 0x9E) & (data[lead] != 0x97)]
    if not len(lead):
        return data
    data = data.copy()
    data[lead] += 0x20
    return data


def as_string(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    return column.cast(pa.large_string())


def slices(column: pa.Array, limit: int = SLICE) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets): offsets has one entry more than rows; null texts have no bytes."""
    column = as_string(column)
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    if not n:
        return
    _, where, data = column.buffers()
    offsets = np.frombuffer(where, dtype=np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, dtype=np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, side="right")) - 1)
        hi = min(hi, n)
        yield lo, hi, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi


class Words:
    """Words of one slice: byte spans, and for each document the number of its first word."""

    __slots__ = ("data", "end", "first", "offsets", "start")

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        n = len(data)
        inside = ~SPACE[data]
        edge = np.zeros(n + 1, dtype=bool)
        edge[offsets] = True
        begins, ends = inside.copy(), inside.copy()
        if n:
            begins[1:] &= ~inside[:-1] | edge[1:n]
            ends[:-1] &= ~inside[1:] | edge[1:n]
        self.data, self.offsets = data, offsets
        self.start, self.end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
        self.first = np.searchsorted(self.start, offsets)

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def documents(self) -> np.ndarray:
        """The document of each word."""
        return np.repeat(np.arange(len(self.offsets) - 1), self.counts())

    def hashes(self, lower: bool = True) -> np.ndarray:
        return span_hashes(self.data, self.start, self.end, lower)


def span_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, lower: bool) -> np.ndarray:
    """64-bit hash of each byte span; equal bytes give equal hashes wherever they stand."""
    if not len(start):
        return np.zeros(0, dtype=np.uint64)
    up, down = _power_tables(len(data) + 1)
    sums = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum((_TABLE_LOWER if lower else _TABLE)[data] * up[: len(data)], out=sums[1:])
    return mix((sums[end] - sums[start]) * down[start] + (end - start).astype(np.uint64))


def windows(hashes: np.ndarray, first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of each run of ``width`` words inside a document."""
    n = len(hashes)
    if n < width:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    total = np.zeros(n - width + 1, dtype=np.uint64)
    for k in range(width):
        total = total * U(0xD6E8FEB86659FD93) + hashes[k : n - width + 1 + k]
    fits = np.ones(n - width + 1, dtype=bool)
    for back in range(1, width):
        cut = first[1:] - back
        fits[cut[(cut >= 0) & (cut <= n - width) & (cut >= first[:-1])]] = False
    # a document shorter than the window leaves starts before its first word to its neighbour
    starts = np.flatnonzero(fits)
    return mix(total[starts]), starts


def per_document(flags: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sum of ``flags`` (by word or by byte) within each document."""
    sums = np.zeros(len(flags) + 1, dtype=np.int64)
    np.cumsum(flags, out=sums[1:])
    return sums[first[1:]] - sums[first[:-1]]


def crc_of_id(ids: np.ndarray) -> np.ndarray:
    """crc32 of the decimal text of each id, as Spark's crc32(cast(id as string))."""
    import zlib

    return np.array([zlib.crc32(str(x).encode()) for x in ids.tolist()], dtype=np.int64)
