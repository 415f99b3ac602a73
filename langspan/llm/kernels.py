"""NumPy kernels over Arrow text columns: words, hashes and word shingles without a Python object per word.

A text column arrives as one byte buffer with row offsets. The kernels work on slices of about ``SLICE_BYTES``,
so a worker's memory follows the slice (or the longest single text), not the Arrow batch. Word = maximal run of
bytes other than space and tab..carriage return; A-Z count as a-z. A word's hash is a polynomial over random byte
codes modulo 2**64, finalised by an avalanche step; equal words have equal hashes in every row and process.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20
U = np.uint64
_BASE = 0x9E3779B97F4A7C15  # odd, so that it has an inverse modulo 2**64
_INVERSE = pow(_BASE, -1, 1 << 64)
_MIX1, _MIX2, _STEP = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB), U(0xD6E8FEB86659FD93)

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True


#: The wider set of separators: all ASCII but letters and digits.
NOT_LETTER = np.ones(256, bool)
for _first, _end in ((48, 58), (65, 91), (97, 123), (128, 256)):
    NOT_LETTER[_first:_end] = False


def lowered(data: np.ndarray) -> np.ndarray:
    """Bytes with the capitals of Latin-1's letters lowered too (A-Z are dealt with by ``word_hashes``)."""
    if len(data) < 2:
        return data
    capital = (data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97)
    if not capital.any():
        return data
    data = data.copy()
    data[1:][capital] += 32
    return data


def mix(h: np.ndarray) -> np.ndarray:
    """Avalanche of 64-bit integers (a bijection)."""
    h = h ^ (h >> U(30))
    h *= _MIX1
    h ^= h >> U(27)
    h *= _MIX2
    h ^= h >> U(31)
    return h


_CODES = mix(np.arange(1, 257, dtype=U) * U(_BASE))
LOWER_CODES = _CODES.copy()
LOWER_CODES[65:91] = _CODES[97:123]
_powers: list[np.ndarray] = [np.ones(1, U), np.ones(1, U)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, SLICE_BYTES + 1)
        for k, base in enumerate((_BASE, _INVERSE)):
            table = np.full(size, U(base))
            table[0] = U(1)
            _powers[k] = np.multiply.accumulate(table)
    return _powers[0], _powers[1]


def slices(column: pa.Array, most: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, row offsets into them); nulls are empty texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    if not n:
        return
    wide = pa.types.is_large_string(column.type)
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(0, np.uint8)
    first = 0
    while first < n:
        end = max(first + 1, int(np.searchsorted(offsets, offsets[first] + most, "right")) - 1)
        yield first, end, data[offsets[first] : offsets[end]], offsets[first : end + 1] - offsets[first]
        first = end


def words(data: np.ndarray, offsets: np.ndarray, separators: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of every word, and how many words each row has (as offsets into the words)."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = ~separators[data]
    begin, last = inside.copy(), inside.copy()
    begin[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    edge = offsets[:-1][offsets[:-1] < offsets[1:]]
    begin[edge] = inside[edge]
    edge = offsets[1:][offsets[:-1] < offsets[1:]] - 1
    last[edge] = inside[edge]
    starts, ends = np.flatnonzero(begin), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each lower-cased (A-Z) word."""
    if not len(starts):
        return np.zeros(0, U)
    powers, inverses = _power_tables(len(data) + 1)
    sums = np.zeros(len(data) + 1, U)
    np.cumsum(LOWER_CODES[data] * powers[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * inverses[starts] + (ends - starts).astype(U))


def shingles(hashes: np.ndarray, size: int) -> np.ndarray:
    """Hash of every run of ``size`` words, one for each start (rows are not told apart: see ``row_shingles``)."""
    n = len(hashes) - size + 1
    if n <= 0:
        return np.zeros(0, U)
    total = hashes[:n].copy()
    for k in range(1, size):
        total *= _STEP
        total += hashes[k : k + n]
    return mix(total + U(size))


def row_shingles(hashes: np.ndarray, bounds: np.ndarray, size: int) -> Iterator[np.ndarray]:
    """For each row its sorted distinct shingles; fewer words than ``size`` make one shingle, none make an empty set."""
    every = shingles(hashes, size)
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a >= size:
            row = np.sort(every[a : b - size + 1])
            keep = np.empty(len(row), bool)
            keep[0] = True
            np.not_equal(row[1:], row[:-1], out=keep[1:])
            yield row[keep]
        else:
            yield shingles(hashes[a:b], b - a) if b > a else np.zeros(0, U)
