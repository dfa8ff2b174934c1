"""Texts of an Arrow batch as arrays of symbols, and hashes of their runs.

A symbol is a byte or a word. The hash of a run is a polynomial over the
symbols' random 64-bit values, modulo 2**64, taken from prefix sums: any run
costs two look-ups, and equal runs have equal hashes wherever they stand.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
SPACES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
#: Symbols in one block of vector work.
BLOCK = 1 << 19

_BASE = 0x9E3779B97F4A7C15
_rng = np.random.default_rng(20240229)
BYTE_VALUE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
IS_SPACE = np.zeros(256, bool)
IS_SPACE[list(SPACES)] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


@lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    inverse = pow(_BASE, -1, 2**64)
    return np.cumprod(np.full(n, U(_BASE))), np.cumprod(np.full(n, U(inverse)))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(20, int(n - 1).bit_length())
    return _powers(size)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    h = h ^ (h >> U(30))
    h = h * U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h *= U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


class Runs:
    """Hashes of runs [s, e) of one symbol array."""

    def __init__(self, values: np.ndarray):
        self.n = len(values)
        up, self._down = powers(self.n + 1)
        self._sums = np.zeros(self.n + 1, np.uint64)
        np.cumsum(values * up[: self.n], out=self._sums[1:])

    def of(self, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        return (self._sums[e] - self._sums[s]) * self._down[s]

    def grams(self, k: int) -> np.ndarray:
        if self.n < k:
            return np.zeros(0, np.uint64)
        return (self._sums[k:] - self._sums[:-k]) * self._down[: self.n - k + 1]


def raw_texts(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts in a row, and the n + 1 borders; null is empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if col.null_count:
        col = pc.fill_null(col, "")
    if not len(col):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, offsets, data = col.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def blocks(borders: np.ndarray, most: int = BLOCK) -> Iterator[tuple[int, int]]:
    """Ranges of neighbouring texts of up to ``most`` symbols in all; a longer text stands alone."""
    i, n = 0, len(borders) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(borders, borders[i] + most, "right")) - 1)
        yield i, j
        i = j


def slices(batch: pa.RecordBatch, column: int = 1, most: int = 6 << 20) -> Iterator[pa.RecordBatch]:
    """A batch in pieces of up to ``most`` bytes of text, so that vector work on it needs little memory; a longer text stands alone."""
    col = batch.column(column)
    if not len(col):
        return
    at = np.r_[0, np.cumsum(pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64))]
    for i, j in blocks(at, most):
        yield batch.slice(i, j - i)


def word_spans(raw: np.ndarray, borders: np.ndarray, is_gap: np.ndarray = IS_SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First byte and end of every word, and the n + 1 borders of the texts counted in words."""
    if not len(raw):
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(borders), np.int64)
    word = ~is_gap[raw]
    first = word.copy()
    first[1:] &= ~word[:-1]
    cuts = borders[1:-1][borders[1:-1] < len(raw)]
    first[cuts] = word[cuts]
    last = word.copy()
    last[:-1] &= ~word[1:]
    before = cuts[cuts > 0] - 1
    last[before] = word[before]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return start, end, np.searchsorted(start, borders)


def word_values(raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit value for each word, from its bytes and its length."""
    if not len(start):
        return np.zeros(0, np.uint64)
    out = np.empty(len(start), np.uint64)
    i = 0
    while i < len(start):  # a piece of bytes at a time, whole words only
        j = max(i + 1, int(np.searchsorted(end, start[i] + 2 * BLOCK, "right")))
        lo = start[i]
        runs = Runs(BYTE_VALUE[raw[lo : end[j - 1]]])
        s, e = start[i:j] - lo, end[i:j] - lo
        out[i:j] = mix(runs.of(s, e) + (e - s).astype(np.uint64) * U(0xD6E8FEB86659FD93)) | U(1)
        i = j
    return out


def windows_min(key: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every w neighbours, in log2(w) passes."""
    size = 1
    while size * 2 <= w:
        key = np.minimum(key[:-size], key[size:])
        size *= 2
    rest = w - size
    return np.minimum(key[: len(key) - rest], key[rest:]) if rest else key
