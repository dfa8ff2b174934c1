"""Lossless delta codec over the integer view of floating-point values.

Bits of neighbouring values are subtracted (modulo 2**64), zigzag-mapped and packed in
one width for a page; codes that don't fit, or that equal the marker (all ones), are
escaped with the whole value. The width is the one of least size by an exact model
(``cost``). The ``split`` stream holds all codes, then all escaped values, so that
decoding is array work; ``interleaved`` has each value behind its marker.
"""

from __future__ import annotations

from bisect import bisect_left
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from . import cost

RAW, DELTA, CONSTANT, RUNS = 0, 1, 2, 3
_BLOCK = 8192


def to_bits(v: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(v).view(np.uint64 if v.dtype.itemsize == 8 else np.uint32)


def zigzag(d: np.ndarray) -> np.ndarray:
    """Unsigned code of a wrapped difference (as unsigned): small magnitudes get small codes."""
    top = d.dtype.type(d.dtype.itemsize * 8 - 1)
    return (d << d.dtype.type(1)) ^ (np.zeros(1, d.dtype) - (d >> top))


def unzigzag(z: np.ndarray) -> np.ndarray:
    one = z.dtype.type(1)
    return (z >> one) ^ (np.zeros(1, z.dtype) - (z & one))


def codes(bits: np.ndarray) -> np.ndarray:
    return zigzag(bits[1:] - bits[:-1])


def _pack(values: np.ndarray, n: int) -> np.ndarray:
    """Bits of ``values``, n each, high first, as an array of 0 and 1."""
    size = values.dtype.itemsize
    wide = np.ascontiguousarray(values, values.dtype.newbyteorder(">")).view(np.uint8).reshape(-1, size)
    out = [np.unpackbits(wide[i : i + _BLOCK], axis=1)[:, 8 * size - n :].ravel() for i in range(0, len(values), _BLOCK)]
    return np.concatenate(out) if out else np.zeros(0, np.uint8)


class _Bits:
    """Numbers of up to 64 bits, high bit first, at any bit of a byte string: each is cut out of the eight bytes (and one more) that hold it."""

    def __init__(self, data: bytes | pa.Buffer):
        own = np.frombuffer(data, np.uint8)
        self.size = 8 * len(own)
        self._bytes = np.r_[own, np.zeros(9, np.uint8)]
        self._words = np.ndarray(len(own) + 1, ">u8", self._bytes, 0, (1,))

    def at(self, places: np.ndarray, n: int, dtype) -> np.ndarray:
        out = np.empty(len(places), np.uint64)
        for i in range(0, len(places), 8 * _BLOCK):
            p = places[i : i + 8 * _BLOCK]
            byte, shift = p >> 3, (p & 7).astype(np.uint64)
            v = (self._words[byte].astype(np.uint64) << shift) >> np.uint64(64 - n)
            if n > 57:  # the last bits of some stand in a ninth byte
                over = np.uint64(n) + shift
                rest = np.where(over > 64, over - np.minimum(over, np.uint64(64)), np.uint64(0))
                v |= self._bytes[byte + 8].astype(np.uint64) >> (np.uint64(8) - rest)
            out[i : i + 8 * _BLOCK] = v
        return out.astype(dtype)

    def run(self, start: int, count: int, n: int, dtype) -> np.ndarray:
        """``count`` numbers of ``n`` bits from bit ``start``."""
        if start + count * n > self.size:
            raise ValueError("page too short")
        return self.at(start + n * np.arange(count, dtype=np.int64), n, dtype)


def _interleaved_places(data: bytes | pa.Buffer, start: int, count: int, n: int, full: int) -> np.ndarray:
    """Bit at which each code begins where a whole value follows each marker.

    Codes between two markers are ``n`` bits apart, so their places agree modulo ``n``, and
    the next marker is the next run of ``n`` ones at a place of the same remainder.
    """
    bits = np.unpackbits(np.frombuffer(data, np.uint8))[start:]
    sums = np.zeros(len(bits) + 1, np.int32)
    np.cumsum(bits, out=sums[1:])
    marks = np.flatnonzero(sums[n:] - sums[: len(sums) - n] == n)
    rest = marks % n
    order = np.argsort(rest, kind="stable")
    cuts = np.searchsorted(rest[order], np.arange(n + 1))
    marks = marks[order]
    by_rest: dict[int, list[int]] = {}
    at, left, first, size = 0, count, [], []
    while left:
        r = at % n
        own = by_rest.get(r)
        if own is None:
            own = by_rest[r] = marks[cuts[r] : cuts[r + 1]].tolist()
        k = bisect_left(own, at)
        m = min(left, (own[k] - at) // n + 1 if k < len(own) else left)
        first.append(at)
        size.append(m)
        left -= m
        at += m * n + full
    size = np.array(size, np.int64)
    steps = np.arange(count, dtype=np.int64) - np.repeat(np.cumsum(size) - size, size)
    return start + np.repeat(np.array(first, np.int64), size) + n * steps


@dataclass(frozen=True)
class Page:
    tag: int
    n_bits: int
    data: bytes
    #: Size by the model, header included; the data is at most 7 bits longer.
    predicted_bits: int


def encode_page(v: np.ndarray, policy: str = "exact", fixed_bits: int | None = None, min_saving: float = 0.0, stream: str = "split", rle: bool = False) -> Page:
    bits = to_bits(v)
    full = bits.dtype.itemsize * 8
    raw = Page(RAW, full, bits.tobytes(), full * len(v))
    if len(v) < 2:
        return raw
    z = codes(bits)
    if policy == "fixed":
        if fixed_bits is None or not 1 <= fixed_bits <= full:
            raise ValueError(f"fixed_bits must be 1 to {full}")
        n = fixed_bits
    else:
        n = cost.best_bits(cost.histogram(z), cost.marker_histogram(z), policy, full)[0]
    head = np.unpackbits(np.array([n], np.uint8)), _pack(bits[:1], full)
    if not z.any():
        return Page(CONSTANT, 0, np.packbits(np.concatenate([np.zeros(8, np.uint8), head[1]])).tobytes(), 8 + full)
    n = max(n, 1)
    head = np.unpackbits(np.array([n], np.uint8)), head[1]
    marker = z.dtype.type((1 << n) - 1)
    escaped = (z >= marker) if n < full else (z == marker)
    code = np.where(escaped, marker, z)
    size = 8 + full + n * len(z) + full * int(escaped.sum())
    if rle:
        at = np.flatnonzero(np.r_[True, (code[1:] != code[:-1]) | escaped[1:] | escaped[:-1]])
        run = np.diff(np.r_[at, len(code)]).astype(np.uint32)
        runs = 8 + full + 32 + (n + 32) * len(at) + full * int(escaped.sum())
        if runs < min(size, (1 - min_saving) * full * len(v)):
            body = [*head, _pack(np.array([len(at)], np.uint32), 32), _pack(run, 32), _pack(code[at], n), _pack(bits[1:][escaped], full)]
            return Page(RUNS, n, np.packbits(np.concatenate(body)).tobytes(), runs)
    if policy != "fixed" and size > (1 - min_saving) * full * len(v):
        return raw
    if stream == "split":
        body = [_pack(code, n), _pack(bits[1:][escaped], full)]
    else:
        at = np.arange(len(z)) * n + full * np.r_[0, np.cumsum(escaped)[:-1]]
        flat = np.zeros(n * len(z) + full * int(escaped.sum()), np.uint8)
        flat[(at[:, None] + np.arange(n)).ravel()] = _pack(code, n)
        flat[(at[escaped][:, None] + n + np.arange(full)).ravel()] = _pack(bits[1:][escaped], full)
        body = [flat]
    return Page(DELTA, n, np.packbits(np.concatenate([*head, *body])).tobytes(), size)


def decode_page(tag: int, data: bytes | pa.Buffer, count: int, dtype=np.float64, stream: str = "split") -> np.ndarray:
    """``count`` values; anything that doesn't add up raises ValueError."""
    dtype = np.dtype(dtype)
    word = np.dtype(np.uint64 if dtype.itemsize == 8 else np.uint32)
    full = word.itemsize * 8
    if tag == RAW:
        if len(data) != count * word.itemsize:
            raise ValueError("raw page of a wrong length")
        return np.frombuffer(data, dtype).copy()
    bits = _Bits(data)
    if bits.size < 8 + full or count < 1:
        raise ValueError("page too short")
    n = int(bits.run(0, 1, 8, np.int64)[0])
    first = bits.run(8, 1, full, word)
    at = 8 + full
    if tag == CONSTANT:
        return np.repeat(first, count).view(dtype)
    if tag not in (DELTA, RUNS) or not 1 <= n <= full:
        raise ValueError("unknown page")
    marker = word.type((1 << n) - 1)
    if tag == DELTA and stream == "interleaved":
        places = _interleaved_places(data, at, count - 1, n, full)
        if len(places) and places[-1] + n > bits.size:
            raise ValueError("page too short")
        z = bits.at(places, n, word)
        escaped = np.flatnonzero(z == marker)
        if len(escaped) and places[escaped[-1]] + n + full > bits.size:
            raise ValueError("page too short")
        values = bits.at(places[escaped] + n, full, word)
    else:
        if tag == RUNS:
            m = int(bits.run(at, 1, 32, np.int64)[0])
            run = bits.run(at + 32, m, 32, np.int64)
            if run.sum() != count - 1:
                raise ValueError("runs of a wrong length")
            z = np.repeat(bits.run(at + 32 + 32 * m, m, n, word), run)
            at += 32 + (32 + n) * m
        else:
            z = bits.run(at, count - 1, n, word)
            at += (count - 1) * n
        escaped = np.flatnonzero(z == marker)
        values = bits.run(at, len(escaped), full, word)
    step = unzigzag(z)
    step[escaped] = 0
    sums = np.cumsum(np.r_[first, step], dtype=word)
    # behind an escape the sums go on from its value
    shift = np.zeros(count, word)
    shift[escaped + 1] = values - sums[escaped + 1] - np.r_[np.zeros(1, word), (values - sums[escaped + 1])[:-1]] if len(escaped) else 0
    return (sums + np.cumsum(shift, dtype=word)).view(dtype)
