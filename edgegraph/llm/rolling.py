"""Hashes of all windows of a text chunk at once, from prefix sums (numpy, modulo a prime).

A sequence v_0, v_1, ... has the prefix sums H[i] = sum(v_k * B**k for k < i), so the items s..e-1
hash to (H[e] - H[s]) * B**-s, whatever stands before them. This is done modulo 2**31 - 1 for two
bases with an item table of its own each, so no sequences collide by their form alone; a finaliser
spreads both results over 64 bits. Such hashes find candidates. Where a decision rests on equality,
digest() of the bytes themselves tells sequences apart.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa

_U = np.uint64
_PRIME = (1 << 31) - 1
_BASES = (1_209_471_823, 1_873_504_217)
_M, _S = _U(_PRIME), _U(31)
_STEP = 1 << 15


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> _U(30))
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


_RANDOM = mix(np.arange(1, 257, dtype=np.uint64) * _U(0x9E3779B97F4A7C15))
_BYTES = (_RANDOM >> _U(33), mix(_RANDOM) >> _U(33))
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def _fold(x: np.ndarray) -> np.ndarray:
    """x modulo the prime, up to a few units above it; x is overwritten."""
    for _ in range(2):
        high = x >> _S
        x &= _M
        x += high
    return x


class _Powers:
    """Powers of both bases and of their inverses, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = [np.ones(1, dtype=np.uint64)] * 2

    def upto(self, n: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
        if len(self.up[0]) < n:
            n = max(n, 1 << 16)
            self.up = [self._row(b, n) for b in _BASES]
            self.down = [self._row(pow(b, -1, _PRIME), n) for b in _BASES]
        return self.up, self.down

    @staticmethod
    def _row(base: int, n: int) -> np.ndarray:
        out = np.ones(n, dtype=np.uint64)
        k = 1
        while k < n:
            out[k : 2 * k] = out[: min(k, n - k)] * _U(pow(base, k, _PRIME)) % _M
            k *= 2
        return out


_POWERS = _Powers()


class Prefix:
    """Prefix sums of a sequence of 64-bit items; at() hashes the items lo..hi-1 for arrays lo, hi."""

    def __init__(self, items: np.ndarray) -> None:
        self._sum(len(items), ((items & _U(0x7FFFFFFF), None), (items >> _U(33), None)))

    @classmethod
    def of_bytes(cls, data: np.ndarray) -> Prefix:
        out = cls.__new__(cls)
        out._sum(len(data), ((data, table) for table in _BYTES))
        return out

    def _sum(self, n: int, rows) -> None:
        up, self._down = _POWERS.upto(n + 1)
        self._sums = []
        for (row, table), power in zip(rows, up, strict=True):
            sums = np.zeros(n + 1, dtype=np.uint64)
            for at in range(0, n, _STEP):  # in pieces that stay in the processor's cache
                x = row[at : at + _STEP] if table is None else table[row[at : at + _STEP]]
                x = x * power[at : at + len(x)]
                x = (x & _M) + (x >> _S)
                x[0] += sums[at]
                np.cumsum(x, out=x)
                sums[at + 1 : at + 1 + len(x)] = _fold(x)
            self._sums.append(sums)

    def _key(self, far, near, shift) -> np.ndarray:
        out = None
        for sums, down in zip(self._sums, self._down, strict=True):
            x = sums[far] + _U(2 * _PRIME)
            x -= sums[near]
            x *= down[shift]
            x = _fold(x)
            np.subtract(x, _M, out=x, where=x >= _M)
            out = x if out is None else (out << _S) | x
        return mix(out)

    def at(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        out = np.empty(len(lo), dtype=np.uint64)
        for i in range(0, len(lo), _STEP):
            part = lo[i : i + _STEP]
            out[i : i + _STEP] = self._key(hi[i : i + _STEP], part, part)
        return out

    def every(self, width: int) -> np.ndarray:
        """Hashes of all windows of the width, by their start."""
        n = max(0, len(self._sums[0]) - width)
        out = np.empty(n, dtype=np.uint64)
        for i in range(0, n, _STEP):
            to = min(n, i + _STEP)
            out[i:to] = self._key(slice(i + width, to + width), slice(i, to), slice(i, to))
        return out


def digest(data: bytes | memoryview, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The first 128 bits of the SHA-256 of data[lo:hi] for arrays lo, hi: rows of two 64-bit halves."""
    sha = hashlib.sha256
    flat = b"".join([sha(data[a:b]).digest()[:16] for a, b in zip(lo.tolist(), hi.tolist(), strict=True)])
    return np.frombuffer(flat, dtype=np.uint64).reshape(-1, 2)


def joined(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words data[starts:ends] one after the other with a space after each, and where each begins
    (one more entry at the end)."""
    size = ends - starts + 1
    into = np.concatenate(([0], np.cumsum(size)))
    out = np.full(into[-1], 0x20, dtype=np.uint8)
    # each byte of a word moves by the same distance as its word
    flag = np.zeros(len(data) + 1, dtype=np.int8)
    flag[starts] += 1
    flag[ends] -= 1
    source = np.flatnonzero(np.cumsum(flag[:-1], dtype=np.int8))
    out[source + np.repeat(into[:-1] - starts, size - 1)] = data[source]
    return out, into


def text_bytes(column: pa.ChunkedArray | pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column laid end to end, and the offsets of its rows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    n = len(column)
    if not n:
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    if data is None or off[-1] == off[0]:
        return np.zeros(0, dtype=np.uint8), off - off[0]
    return np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]], off - off[0]


def words(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words (runs without white space of six ASCII kinds), and for each
    row the index of its first word (one more entry at the end)."""
    n = len(data)
    inside = ~_SPACE[data]
    edge = np.zeros(n + 1, dtype=bool)
    edge[off] = True
    before, after = np.zeros(n, dtype=bool), np.zeros(n, dtype=bool)
    before[1:] = inside[:-1]
    after[:-1] = inside[1:]
    starts = np.flatnonzero(inside & (edge[:n] | ~before))
    ends = np.flatnonzero(inside & (edge[1:] | ~after)) + 1
    return starts, ends, np.searchsorted(starts, off)


def spread(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """All integers of the ranges lo..hi-1, one range after the other."""
    size = hi - lo
    total = int(size.sum())
    if not total:
        return np.zeros(0, dtype=np.int64)
    return np.repeat(lo - np.concatenate(([0], np.cumsum(size)[:-1])), size) + np.arange(total)


def covered(starts: np.ndarray, width: int, n: int) -> np.ndarray:
    """Which of n places lie in a window of the width that begins at one of the starts."""
    step = np.bincount(starts, minlength=n + 1)[: n + 1].astype(np.int32)
    step[width:] -= np.bincount(starts, minlength=n + 1)[: n + 1 - width].astype(np.int32) if n + 1 > width else 0
    return np.cumsum(step)[:n] > 0
