"""Questions and answers between tasks over packed arrays.

A chunk of documents asks one question for each distinct 64-bit key it holds. Its keys travel as
one binary value for each range of the key space (a *board*), so a key costs its bare bytes and not
a row. The owner of a board reads what all chunks ask, and answers each chunk with packed bits in
the order of its keys. A chunk finds its answers again by sorting its own keys anew, so a lost task
can be run again anywhere. A key costs one entry a chunk at most, however often it occurs there.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ASKED = "board int, chunk int, kind int, n int, body binary"
ANSWERED = "chunk int, board int, kind int, bits binary"
_ASKED = pa.schema([("board", pa.int32()), ("chunk", pa.int32()), ("kind", pa.int32()), ("n", pa.int32()), ("body", pa.binary())])
_ANSWERED = pa.schema([("chunk", pa.int32()), ("board", pa.int32()), ("kind", pa.int32()), ("bits", pa.binary())])


def deal(docs: DataFrame, chunk_bytes: int, carry: tuple[str, ...] = ()) -> tuple[DataFrame, int]:
    """(doc_id, text, chunk), and columns to carry as __name: the rows dealt into chunks of about
    chunk_bytes; and all texts' bytes."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), *(F.col(c).alias(f"__{c}") for c in carry))
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    chunks = max(1, math.ceil(size / chunk_bytes))
    return docs.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(chunks)).cast("int")), size


def board_of(keys: np.ndarray, boards: int) -> np.ndarray:
    """The board of each key: monotone in the key, even for well mixed keys."""
    return ((keys >> np.uint64(32)) * np.uint64(boards)) >> np.uint64(32)


def cuts(keys: np.ndarray, boards: int) -> np.ndarray:
    """Where each board's part begins in sorted keys (boards + 1 entries)."""
    return np.searchsorted(board_of(keys, boards), np.arange(boards + 1, dtype=np.uint64))


def ask(chunk: int, kind: int, keys: np.ndarray, columns: list[np.ndarray], flags: list[np.ndarray], boards: int) -> Iterator[tuple]:
    """Rows of ASKED for sorted keys; columns ride along item by item, flags as packed bits."""
    at = cuts(keys, boards)
    for b in np.flatnonzero(np.diff(at)):
        lo, hi = at[b], at[b + 1]
        yield int(b), chunk, kind, int(hi - lo), b"".join([*(c[lo:hi].tobytes() for c in columns), *(np.packbits(f[lo:hi]).tobytes() for f in flags)])


def asked_table(rows: Iterable[tuple]) -> pa.Table:
    return pa.Table.from_arrays([pa.array(x, t) for x, t in zip([*zip(*rows)] or [()] * 5, _ASKED.types, strict=True)], schema=_ASKED)


def unpack(n: int, body: bytes, kinds: list, flags: int) -> list[np.ndarray]:
    """The columns (of the dtypes kinds) and flags of one body."""
    out, at = [], 0
    for kind in kinds:
        out.append(np.frombuffer(body, dtype=kind, count=n, offset=at))
        at += n * np.dtype(kind).itemsize
    step = (n + 7) // 8
    for _ in range(flags):
        out.append(np.unpackbits(np.frombuffer(body, dtype=np.uint8, count=step, offset=at), count=n).astype(bool))
        at += step
    return out


def owner(answer: Callable[[int, list[tuple[int, int, bytes]]], list[list[np.ndarray]]]) -> Callable[[pa.Table], pa.Table]:
    """A group function over one board: answer gets, for each kind of question, (chunk, n, body) in
    the order of chunks and gives a list of bit arrays for each of them."""

    def run(table: pa.Table) -> pa.Table:
        board = table["board"][0].as_py()
        asked: dict[int, list[tuple[int, int, bytes]]] = {}
        for c, k, n, body in zip(*(table[x].to_pylist() for x in ("chunk", "kind", "n", "body")), strict=True):
            asked.setdefault(k, []).append((c, n, body))
        rows = []
        for kind, parts in sorted(asked.items()):
            parts.sort(key=lambda x: x[0])
            rows += [(c, board, kind, b"".join(np.packbits(b).tobytes() for b in bits)) for (c, _, _), bits in zip(parts, answer(kind, parts), strict=True)]
        return pa.Table.from_arrays([pa.array(x, t) for x, t in zip([*zip(*rows)] or [()] * 4, _ANSWERED.types, strict=True)], schema=_ANSWERED)

    return run


def answers(table: pa.Table, kind: int, keys: np.ndarray, boards: int, flags: int) -> list[np.ndarray]:
    """The bits of a chunk's answers, in the order of its sorted keys."""
    at = cuts(keys, boards)
    out = [np.zeros(len(keys), dtype=bool) for _ in range(flags)]
    for b, k, bits in zip(*(table[x].to_pylist() for x in ("board", "kind", "bits")), strict=True):
        if k == kind:
            lo, hi = int(at[b]), int(at[b + 1])
            step = (hi - lo + 7) // 8
            for i in range(flags):
                out[i][lo:hi] = np.unpackbits(np.frombuffer(bits, dtype=np.uint8, count=step, offset=i * step), count=hi - lo).astype(bool)
    return out


def repeats(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct keys, each item's place among them, and how often each occurs."""
    uniq, inverse, count = np.unique(keys, return_inverse=True, return_counts=True)
    return uniq, inverse.reshape(-1), count


def repeats_wide(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """repeats() for 128-bit keys: rows of two halves, sorted by the first and then by the second."""
    order = np.argsort(keys[:, 0], kind="stable")
    first = keys[order, 0]
    same = first[1:] == first[:-1]
    if (same & (keys[order[1:], 1] != keys[order[:-1], 1])).any():
        order = np.lexsort((keys[:, 1], keys[:, 0]))
    ranked = keys[order]
    new = np.ones(len(keys), dtype=bool)
    new[1:] = (ranked[1:] != ranked[:-1]).any(axis=1)
    place = np.empty(len(keys), dtype=np.int64)
    place[order] = np.cumsum(new) - 1
    at = np.flatnonzero(new)
    return ranked[at], place, np.diff(np.append(at, len(keys)))
