"""Vectorised byte-level text primitives for Arrow batches.

Everything works on slices of about ``SLICE_BYTES`` of UTF-8, so that the
temporary arrays stay in cache and memory does not depend on the batch size.
A null text counts as empty.  One longer document is a slice of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20

#: Words are separated by space and the ASCII controls 9 to 13.
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
#: Only A to Z are lower-cased.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_STEP = np.uint64(0x9E3779B97F4A7C15)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_BASE = 0x5851F42D4C957F2D
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser that is one to one."""
    h = (h ^ (h >> np.uint64(30))) * _M1
    h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


with np.errstate(over="ignore"):
    _BYTE_CODES = mix(np.arange(1, 257, dtype=np.uint64) * _STEP)
    _LOWER_CODES = _BYTE_CODES[LOWER]

_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = max(SLICE_BYTES * 2, 1 << max(0, n - 1).bit_length())
    if size not in _powers:
        up, down = np.full(size, _BASE, np.uint64), np.full(size, _BASE_INVERSE, np.uint64)
        up[0] = down[0] = 1
        with np.errstate(over="ignore"):
            tables = (np.cumprod(up), np.cumprod(down))
        if size > SLICE_BYTES * 2:
            return tables
        _powers[size] = tables
    return _powers[size]


def string_buffers(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column and its offsets; nulls have length zero."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    n = len(column)
    if n == 0 or data is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    return np.frombuffer(data, np.uint8)[off[0] : off[-1]], off - off[0]


def slices(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yield (first row, end row, bytes, offsets) of consecutive rows."""
    data, off = string_buffers(column)
    n, first = len(off) - 1, 0
    while first < n:
        end = int(np.searchsorted(off, off[first] + limit, "right")) - 1
        end = min(n, max(end, first + 1))
        yield first, end, data[off[first] : off[end]], off[first : end + 1] - off[first]
        first = end


def word_spans(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of every word; a row's end also ends a word."""
    n = len(data)
    if n == 0:
        empty = np.zeros(0, np.int64)
        return empty, empty, empty
    inside = ~IS_SPACE[data]
    edge = np.zeros(n + 1, bool)
    edge[off] = True
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = inside[:-1]
    starts = np.flatnonzero(inside & (~before | edge[:n]))
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = inside[1:]
    ends = np.flatnonzero(inside & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(off, starts, "right") - 1


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = True) -> np.ndarray:
    """A 64-bit hash of each word's bytes, after lower-casing A to Z."""
    up, down = _power_tables(len(data) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((_LOWER_CODES if lower else _BYTE_CODES)[data] * up[: len(data)], out=sums[1:])
        h = (sums[ends] - sums[starts]) * down[starts]
        return mix(h + (ends - starts).astype(np.uint64) * _STEP)


def combine(parts: list[np.ndarray]) -> np.ndarray:
    """An order-dependent hash of several hashes."""
    with np.errstate(over="ignore"):
        h = np.full(len(parts[0]), len(parts), np.uint64) * _STEP
        for p in parts:
            h = mix(h * np.uint64(_BASE) + p)
        return h


def shingle_sets(column: pa.Array, width: int = 5) -> Iterator[np.ndarray]:
    """For each row its sorted distinct word shingles as 64-bit hashes.

    With fewer words than ``width`` the whole sequence is one shingle; without
    words the set is empty.
    """
    for first, end, data, off in slices(column):
        starts, ends, row = word_spans(data, off)
        hashes = word_hashes(data, starts, ends)
        bounds = np.searchsorted(row, np.arange(end - first + 1))
        full = np.zeros(0, np.uint64)
        if len(hashes) >= width:
            full = combine([hashes[i : len(hashes) - width + 1 + i] for i in range(width)])
        for k in range(end - first):
            a, b = int(bounds[k]), int(bounds[k + 1])
            if b - a >= width:
                s = np.sort(full[a : b - width + 1])
                yield s[np.concatenate(([True], s[1:] != s[:-1]))]
            elif b > a:
                yield combine([hashes[i : i + 1] for i in range(a, b)])
            else:
                yield full[:0]
