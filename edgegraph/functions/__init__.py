"""Column functions shared by all operators."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Kinds of vertices; a vertex id is key * 16 + kind, so keys of different tables never meet.
KINDS = {name: i for i, name in enumerate("region nation customer supplier part order event document page url turn cell vector".split())}


def vid(key: Column, kind: str) -> Column:
    return key.cast("long") * 16 + KINDS[kind]


def portable_hash(seed: int, *keys: Column) -> Column:
    """The first 15 hex digits of md5("seed|key|key...") as a long: the same in any SQL engine with md5."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), *(k.cast("string") for k in keys))), 1, 15), 16, 10).cast("long")


def portable_hash_sql(seed: int, *keys: str) -> str:
    """The same as a DuckDB expression."""
    return f"('0x' || substr(md5(concat_ws('|', '{seed}', {', '.join(f'({k})::varchar' for k in keys)})), 1, 15))::bigint"


def portable_hash_py(seed: int, *keys: int) -> int:
    """The same in Python."""
    import hashlib

    return int(hashlib.md5("|".join(map(str, (seed, *keys))).encode()).hexdigest()[:15], 16)


def distinct(values: np.ndarray) -> np.ndarray:
    """The values in order, each once, by a sort: np.unique's hash table is slower on large arrays."""
    values = np.sort(values)
    return values[np.append(True, values[1:] != values[:-1])[: len(values)]]


def spans(start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The positions start, start + 1, .. of each span, one span after the other, and the number of its span for each."""
    of = np.repeat(np.arange(len(size)), size)
    before = np.cumsum(size) - size
    return np.arange(len(of)) + (start - before)[of], of


class Hashes:
    """portable_hash_py of many keys, for one seed after the other: MD5 on arrays, one block for each hash.
    keys: arrays of whole numbers, or single numbers. What the keys put into a block is kept. Keys below 0, or
    too long for one block, are hashed one by one."""

    ROWS = 16384  # that are hashed together: their words stay in the cache

    def __init__(self, *keys) -> None:
        keys = [np.asarray(x, dtype=np.int64) for x in keys]
        self.n = 0 if any(x.size == 0 for x in keys) else max(x.size for x in keys)
        self.keys, self.blocks = [x if x.ndim else np.full(self.n, x) for x in keys], {}
        self.single = any((x < 0).any() for x in keys)
        if self.single:
            return
        digits = [np.searchsorted(_TENS, x, "right").astype(np.int64) for x in self.keys]  # less one
        form = digits[0]
        for d in digits[1:]:
            form = form * 20 + d
        self.groups = [(np.flatnonzero(form == f), f) for f in np.unique(form)]
        if len(self.groups) == 1:
            self.groups = [(slice(None), self.groups[0][1])]

    def _words(self, length: int) -> list:
        """For each group of keys of equal lengths: its rows, the words of their blocks after a seed of that length, and the bytes of all."""
        if length not in self.blocks:
            found = []
            for rows, form in self.groups:
                parts = [x[rows] for x in self.keys]
                sizes = [int(form) // 20 ** (len(parts) - 1 - j) % 20 + 1 for j in range(len(parts))]
                words, at = [0] * 14, length
                if length + sum(sizes) + len(sizes) > 55:
                    found.append((rows, None, 0))
                    continue

                def put(byte, at, words=words):
                    words[at // 4] = words[at // 4] + byte * (1 << 8 * (at % 4))

                for x, size in zip(parts, sizes, strict=True):
                    put(ord("|"), at)
                    for j in range(size, 0, -1):
                        rest = x // 10
                        put((x - rest * 10 + ord("0")).astype(np.uint32), at + j)
                        x = rest
                    at += 1 + size
                put(0x80, at)
                found.append((rows, words, at))
            self.blocks = {length: found}
        return self.blocks[length]

    def __call__(self, seed: int) -> np.ndarray:
        if not self.n:
            return np.empty(0, np.int64)
        text = str(seed).encode()
        one_by_one = lambda rows: [portable_hash_py(seed, *x) for x in zip(*(k[rows].tolist() for k in self.keys), strict=True)]
        if self.single:
            return np.array(one_by_one(slice(None)), np.int64)
        out = np.empty(self.n, np.int64)
        for rows, words, size in self._words(len(text)):
            if words is None:
                out[rows] = one_by_one(rows)
                continue
            words = [*words, 8 * size]
            for j, c in enumerate(text):
                words[j // 4] = words[j // 4] + c * (1 << 8 * (j % 4))
            n = next((len(w) for w in words if not isinstance(w, int)))
            found = np.empty(n, np.int64)
            for x in range(0, n, self.ROWS):
                found[x : x + self.ROWS] = _md5([w if isinstance(w, int) else w[x : x + self.ROWS] for w in words], min(self.ROWS, n - x))
            out[rows] = found
        return out


_TENS = np.array([10**i for i in range(1, 19)], dtype=np.int64)
_SINE = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_TURN = [7, 12, 17, 22, 5, 9, 14, 20, 4, 11, 16, 23, 6, 10, 15, 21]


def _md5(words: list, n: int) -> np.ndarray:
    """The first 60 bits of the MD5 of one block each; words: the first 15 of it, numbers or arrays."""
    start = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
    a, b, c, d = (np.full(n, x, np.uint32) for x in start)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    words = [*words, 0]
    for i in range(64):
        kind = i // 16
        if kind == 0:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            g = i
        elif kind == 1:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            g = (5 * i + 1) % 16
        elif kind == 2:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            g = (3 * i + 5) % 16
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
            g = 7 * i % 16
        f += a
        if isinstance(words[g], int):
            f += np.uint32((_SINE[i] + words[g]) % (1 << 32))
        else:
            f += words[g]
            f += np.uint32(_SINE[i])
        turn = _TURN[4 * kind + i % 4]
        np.left_shift(f, np.uint32(turn), out=t)
        f >>= np.uint32(32 - turn)
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    a += np.uint32(start[0])
    b += np.uint32(start[1])
    return ((a.byteswap().astype(np.uint64) << np.uint64(28)) | (b.byteswap().astype(np.uint64) >> np.uint64(4))).astype(np.int64)
