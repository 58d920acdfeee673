"""Vectorised reading of text columns: words, their hashes and shingles, without a Python loop over words."""

from __future__ import annotations

import ctypes
import sys
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once; one document may be longer and is then handled alone.
SLICE_BYTES = 1 << 20
#: Most rows handled at once.
SLICE_ROWS = 4096

_P = np.uint64(0x9E3779B97F4A7C15)  # odd, so it has an inverse modulo 2**64
_P_INV = np.uint64(pow(int(_P), -1, 1 << 64))
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_GRAM = np.array([0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3], dtype=np.uint64)


#: How to drop what operators keep in a worker from one of their tasks to the next.
HELD: list[Callable[[], None]] = []


def drop_held() -> None:
    for drop in HELD:
        drop()


def released(run: Callable, keep: bool = False) -> Callable:
    """A mapInArrow function that hands memory it no longer needs back to the system when its partition ends.

    Workers live on between tasks, and executors are charged for what an idle one holds. Unless keep is set, what other
    operators have left in the worker goes first.
    """

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not keep:
            drop_held()
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


def give_back() -> None:
    """Return freed memory to the system, where the allocators can."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    """Spread 64-bit values evenly (the finaliser of a common 64-bit generator)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class _Powers:
    """Powers of the hash base and of its inverse, grown on demand."""

    up = np.ones(1, dtype=np.uint64)
    down = np.ones(1, dtype=np.uint64)

    @classmethod
    def to(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            keep = n <= SLICE_BYTES * 4
            size = max(n, SLICE_BYTES // 2 + 1024)
            up, down = np.full(size, _P), np.full(size, _P_INV)
            up[0] = down[0] = 1
            np.multiply.accumulate(up, out=up)
            np.multiply.accumulate(down, out=down)
            if not keep:  # a single huge document: don't hold its tables for ever
                return up[:n], down[:n]
            cls.up, cls.down = up, down
        return cls.up[:n], cls.down[:n]


def prefix_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """h and inverse powers such that (h[e] - h[s]) * inv[s] hashes data[s:e] wherever it stands."""
    up, down = _Powers.to(len(data) + 1)
    h = np.empty(len(data) + 1, dtype=np.uint64)
    h[0] = 0
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=h[1:])
    return h, down


def slices(column: pa.Array, limit: int = 0) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, bytes, offsets) of runs of rows that together have about limit bytes; null: empty."""
    limit = limit or SLICE_BYTES
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column, "").cast(pa.large_string())
    n = len(column)
    if not n:
        return
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + n + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None and raw.size else np.zeros(0, dtype=np.uint8)
    i = 0
    while i < n:
        j = min(n, i + SLICE_ROWS, max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1))
        yield i, j, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words (runs of bytes that aren't ASCII white space) and how many each row has."""
    n = len(data)
    if not n:
        none = np.zeros(0, dtype=np.int64)
        return none, none, np.zeros(len(offsets) - 1, dtype=np.int64)
    word = ~_SPACE[data]
    first = np.empty(n, dtype=bool)
    first[0] = True
    np.logical_not(word[:-1], out=first[1:])
    edges = offsets[:-1]
    first[edges[edges < n]] = True
    last = np.empty(n, dtype=bool)
    last[-1] = True
    np.logical_not(word[1:], out=last[:-1])
    last[edges[(edges > 0) & (edges <= n)] - 1] = True
    starts = np.flatnonzero(word & first)
    ends = np.flatnonzero(word & last) + 1
    return starts, ends, np.diff(np.searchsorted(starts, offsets))


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the words with A-Z lower-cased, words per row, starts and ends."""
    starts, ends, per_row = word_bounds(data, offsets)
    h, inv = prefix_hashes(_LOWER[data])
    return mix((h[ends] - h[starts]) * inv[starts] + (ends - starts).astype(np.uint64)), per_row, starts, ends


def shingles(hashes: np.ndarray, per_row: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k-word shingles and how many each row has; a row with fewer words, but some, gives its whole sequence."""
    first = np.concatenate([[0], np.cumsum(per_row)])
    count = np.where(per_row >= k, per_row - k + 1, np.minimum(per_row, 1))
    n = len(hashes)
    if not n:
        return np.zeros(0, dtype=np.uint64), count
    total = np.zeros(n, dtype=np.uint64)
    for j in range(min(k, n)):
        weight = _GRAM[j % len(_GRAM)] + np.uint64(2 * (j // len(_GRAM)))
        total[: n - j] += hashes[j:] * weight
    at = np.repeat(first[:-1] - np.concatenate([[0], np.cumsum(count)])[:-1], count) + np.arange(count.sum())
    out = mix(total[at])
    short = np.flatnonzero((per_row > 0) & (per_row < k))
    if len(short):
        place = np.concatenate([[0], np.cumsum(count)])[:-1][short]
        for row, to in zip(short.tolist(), place.tolist(), strict=True):
            own = hashes[first[row] : first[row + 1]]
            weights = np.array([int(_GRAM[j % len(_GRAM)]) + 2 * (j // len(_GRAM)) for j in range(len(own))], dtype=np.uint64)
            out[to] = mix((own * weights).sum(dtype=np.uint64, keepdims=True) + np.uint64(len(own)))[0]
    return out, count


def distinct(values: np.ndarray, per_row: np.ndarray, rank: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of each row, by rank (0 to 15) and then by value, and how many."""
    n = len(per_row)
    row = np.repeat(np.arange(n), per_row)
    if n <= SLICE_ROWS:  # one sort of packed keys; values whose upper 48 bits are equal stay in any order
        packed = (row.astype(np.uint64) << np.uint64(52)) | (values >> np.uint64(16))
        if rank is not None:
            packed |= rank.astype(np.uint64) << np.uint64(48)
        order = np.argsort(packed)
    else:
        order = np.lexsort((values, row) if rank is None else (values, rank, row))
    v, r = values[order], row[order]
    keep = np.ones(len(v), dtype=bool)
    keep[1:] = (v[1:] != v[:-1]) | (r[1:] != r[:-1])
    return v[keep], np.bincount(r[keep], minlength=n)


def binary(values: np.ndarray, per_row: np.ndarray) -> pa.Array:
    """Cut values by row into a binary column of their raw bytes."""
    ends = np.concatenate([[0], np.cumsum(per_row)]) * values.itemsize
    return pa.Array.from_buffers(pa.binary(), len(per_row), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(values))])
