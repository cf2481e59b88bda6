"""Words of Arrow strings as numpy arrays of 64-bit hashes, without a Python object for each word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15)
_STEP = np.array([0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB], _U)
_powers = np.ones(1, _U)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    h = h ^ (h >> _U(30))
    h = h * _U(0xBF58476D1CE4E5B9)
    h ^= h >> _U(27)
    h *= _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


def powers(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        size = 1 << max(6, (n - 1).bit_length())
        p = np.full(size, _BASE)
        p[0] = 1
        _powers = np.multiply.accumulate(p)
    return _powers


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and n + 1 offsets; a null is an empty string."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    o = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64) if n else np.zeros(1, np.int64)
    b = np.frombuffer(data, np.uint8)[o[0] : o[-1]] if data is not None and data.size else np.zeros(0, np.uint8)
    return b, o - o[0]


def slices(offsets: np.ndarray, most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Runs of texts of about ``most`` bytes together (a longer text stands alone)."""
    n, i = len(offsets) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def segment_hashes(data: np.ndarray, inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of inside bytes within each text: start, end, hash, and where each text's runs begin (n + 1)."""
    n = len(data)
    if not n or not inside.any():
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, _U), np.zeros(len(offsets), np.int64)
    before, after = np.ones(n, bool), np.ones(n, bool)
    before[1:], after[:-1] = ~inside[:-1], ~inside[1:]
    edge = offsets[:-1]
    before[edge[edge < n]] = True
    edge = offsets[1:] - 1
    after[edge[edge >= 0]] = True
    starts, ends = np.flatnonzero(inside & before), np.flatnonzero(inside & after) + 1
    size = ends - starts
    first = np.cumsum(size) - size
    place = np.arange(int(size.sum())) - np.repeat(first, size)
    value = (data[inside].astype(_U) + _U(1)) * powers(int(size.max()))[place]
    h = mix(np.add.reduceat(value, first) + size.astype(_U) * _STEP[1])
    return starts, ends, h, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words (A-Z lowered, split at ASCII white space), and where each text's words begin (n + 1)."""
    low = _LOWER[data]
    _, _, h, at = segment_hashes(low, ~_SPACE[low], offsets)
    return h, at


def shingle_hashes(words: np.ndarray, at: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word shingles (a text of fewer words is one shingle), and where each text's shingles begin."""
    n = np.diff(at)
    count = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    begin = np.concatenate([[0], np.cumsum(count)])
    first = np.repeat(at[:-1] - begin[:-1], count) + np.arange(begin[-1])
    short = np.repeat(n < k, count)
    size = np.repeat(np.minimum(n, k), count)
    h = size.astype(_U) * _U(0x2545F4914F6CDD1D)
    last = max(len(words) - 1, 0)
    for j in range(k):
        part = words[np.minimum(first + j, last)] * _STEP[j % 5] if len(words) else h
        h = h + (np.where(size > j, part, _U(0)) if short.any() else part)
        h = mix(h) if j == k - 1 or j % 5 == 4 else h
    return h, begin
