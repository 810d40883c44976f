"""64-bit word hashes of whole Arrow string columns, vectorised over the UTF-8 bytes.

A word's hash is a polynomial over random byte values; prefix sums give it for all words of a
column at once, with no Python object per word. Shingle hashes combine word hashes in order.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_RANDOM = np.random.default_rng(20240229)
_BYTE = _RANDOM.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = 0x9E3779B97F4A7C15 | 1
_UNBASE = pow(_BASE, -1, 1 << 64)
_PLACE = _RANDOM.integers(1, 1 << 63, 64, dtype=np.uint64) | np.uint64(1)
_SEGMENT = 1 << 15  # its arrays stay in a cache
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}

#: ASCII white space ends a word, all else belongs to it.
SPACE_ENDS = np.ones(256, bool)
SPACE_ENDS[[0x20, *range(0x09, 0x0E)]] = False
#: ASCII letters and digits and all bytes of other scripts make a word; ASCII punctuation ends it.
ALNUM_WORDS = np.zeros(256, bool)
ALNUM_WORDS[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 32
_CODE = _BYTE[_LOWER]


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse; lengths beyond a segment (one giant word) are not kept."""
    size = _SEGMENT + 1 if n <= _SEGMENT + 1 else n
    if size not in _POWERS:
        both = []
        for base in (_BASE, _UNBASE):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            both.append(np.cumprod(p, dtype=np.uint64))
        if size > _SEGMENT + 1:
            return both[0], both[1]
        _POWERS[size] = (both[0], both[1])
    return _POWERS[size]


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all rows one after another, and rows + 1 offsets; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64, len(column) + 1, column.offset * 8) if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def words(raw: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first byte and end byte of each word (ASCII letters lower-cased), and rows + 1 offsets into the words."""
    n = len(raw)
    if n == 0:
        none = np.zeros(0, np.int64)
        return np.zeros(0, np.uint64), none, none, np.zeros(len(offsets), np.int64)
    own = inside[raw]
    begin = own.copy()
    begin[1:] &= ~own[:-1]
    cuts = offsets[(offsets > 0) & (offsets < n)]
    begin[cuts] = own[cuts]
    end = own.copy()
    end[:-1] &= ~own[1:]
    end[cuts - 1] = own[cuts - 1]
    starts, ends = np.flatnonzero(begin), np.flatnonzero(end) + 1
    hashes = np.empty(len(starts), np.uint64)
    first = 0
    while first < len(starts):
        low = starts[first]
        last = max(int(np.searchsorted(ends, low + _SEGMENT, "right")), first + 1)
        high = ends[last - 1]
        power, unpower = _powers(int(high - low) + 1)
        sums = np.zeros(int(high - low) + 1, np.uint64)
        codes = _CODE[raw[low:high]]
        codes *= power[: high - low]
        np.cumsum(codes, out=sums[1:])
        s, e = starts[first:last] - low, ends[first:last] - low
        hashes[first:last] = mix((sums[e] - sums[s]) * unpower[s] + (e - s).astype(np.uint64))
        first = last
    return hashes, starts, ends, np.searchsorted(starts, offsets)


def shingles(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all runs of so many words; fewer words: of the whole sequence as one; no word: none."""
    n = len(hashes)
    if n == 0:
        return hashes
    size = min(width, n)
    total = np.full(n - size + 1, size, np.uint64)
    for k in range(size):
        total += hashes[k : n - size + 1 + k] * _PLACE[k]
    return mix(total)


def _first(values: np.ndarray) -> np.ndarray:
    """Whether each of sorted values is the first of its kind."""
    new = np.ones(len(values), bool)
    np.not_equal(values[1:], values[:-1], out=new[1:])
    return new


def unique(values: np.ndarray) -> np.ndarray:
    """Sorted distinct values; faster than numpy's own for arrays of a text's size."""
    values = np.sort(values)
    return values[_first(values)]


def counted(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values and how often each occurs."""
    values = np.sort(values)
    at = np.flatnonzero(_first(values))
    return values[at], np.diff(at, append=len(values))


def row_shingles(hashes: np.ndarray, at: np.ndarray, width: int) -> Iterator[np.ndarray]:
    """``shingles`` of each row, given all word hashes and rows + 1 offsets; the runs of all rows are made at once."""
    runs = shingles(hashes, width) if len(hashes) >= width else hashes[:0]
    for first, end in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        yield runs[first : end - width + 1] if end - first >= width else shingles(hashes[first:end], width)
