"""Cost-balanced packing of token documents into sequences.

The cost of a piece of n tokens is ``linear * n + quadratic * n**2`` (attention stays inside a piece).
Each task packs what it reads, a bounded number of tokens at a time: documents in descending order of
cost go to the sequence of the lowest cost so far that still has room for them. Where none has, the
piece is cut to fill the cheapest one with room, and the rest waits for its turn. Documents longer than
a sequence first give whole sequences. No rows are exchanged.

The sequences of one round hold exactly its tokens: as many full ones as fit, and the remainder in
sequences whose lengths are powers of two, which need no padding.
"""

from __future__ import annotations

import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import library_encoder, texts_of

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, cost double"


def assign(lengths: list[int], size: int, linear: float, quadratic: float) -> list[tuple[int, int, int, int, int]]:
    """(document, start, length, sequence, offset) of all pieces, for documents given by their lengths."""
    total = sum(lengths)
    room = [size] * (total // size)
    room += [1 << b for b in range(size.bit_length() - 1, -1, -1) if (total % size) >> b & 1]
    room_a, cost, filled = np.array(room, dtype=np.int64), np.zeros(len(room)), np.zeros(len(room), dtype=np.int64)
    price = lambda n: linear * n + quadratic * n * n
    out, waiting, full = [], [], 0

    def put(doc: int, start: int, n: int, s: int) -> None:
        out.append((doc, start, n, s, int(filled[s])))
        filled[s] += n
        room_a[s] -= n
        cost[s] = cost[s] + price(n) if room_a[s] else np.inf

    for doc, n in enumerate(lengths):
        start = 0
        while n - start >= size:
            put(doc, start, size, full)
            full, start = full + 1, start + size
        if n > start:
            heapq.heappush(waiting, (-(n - start), doc, start))
    cost[room_a == 0] = np.inf
    while waiting:
        n, doc, start = heapq.heappop(waiting)
        n = -n
        fits = np.where(room_a >= n, cost, np.inf)
        s = int(fits.argmin())
        if fits[s] == np.inf:
            s = int(np.where(room_a > 0, cost, np.inf).argmin())
            part = int(room_a[s])
            heapq.heappush(waiting, (-(n - part), doc, start + part))
            n = part
        put(doc, start, n, s)
    return out


def pack(docs: DataFrame, path: str, size: int = 2048, end_id: int = 1, linear: float = 1.0, quadratic: float = 1 / 1024, round_tokens: int = 4_000_000, with_ids: bool = False) -> DataFrame:
    """Pieces of all documents: each id of each text, and end_id after it, lies in exactly one.

    docs: doc_id, text (other columns are ignored). One or more rows per input row: where the piece
    begins in its document, its length, the CRC-32 of its ids as little-endian unsigned 32-bit integers,
    the document's tokens, its sequence and its place there (gapless from 0), and its estimated cost;
    with_ids adds the ids. A null text is empty and gives its end_id alone; rows of the same doc_id are
    packed as documents of their own. size is a power of two.
    """

    def run(batches):
        encode = library_encoder(path)
        base, done = TaskContext.get().partitionId() << 36, 0
        end = np.array([end_id], dtype="<u4").tobytes()

        def flush(ids: list, texts: list[bytes]):
            nonlocal done
            pieces = assign([len(x) // 4 for x in texts], size, linear, quadratic)
            doc, start, n, seq, at = np.array(pieces, dtype=np.int64).reshape(-1, 5).T
            cut = [texts[d][4 * s : 4 * (s + k)] for d, s, k in zip(doc, start, n, strict=True)]
            own = np.array([len(x) // 4 for x in texts], dtype=np.int64)
            cols = [pa.array([ids[d] for d in doc], pa.int64()), start, n, [zlib.crc32(x) for x in cut], own[doc], base + done + seq, at, linear * n + quadratic * n.astype(float) ** 2]
            if with_ids:
                cols.append(pa.array([np.frombuffer(x, dtype="<u4").astype(np.int32) for x in cut], pa.list_(pa.int32())))
            done += int(seq.max()) + 1
            names = [x.split()[0] for x in PIECES.split(", ")] + ["ids"] * with_ids
            yield pa.RecordBatch.from_arrays([pa.array(c) if not isinstance(c, pa.Array) else c for c in cols], names)

        ids, held, tokens = [], [], 0
        for batch in batches:
            for part, texts in texts_of(batch):
                for d, t in zip(part["doc_id"].to_pylist(), texts, strict=True):
                    held.append(encode(t).astype("<u4").tobytes() + end)
                    ids.append(d)
                    tokens += len(held[-1]) // 4
                    if tokens >= round_tokens:
                        yield from flush(ids, held)
                        ids, held, tokens = [], [], 0
        if held:
            yield from flush(ids, held)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, PIECES + ", ids array<int>" * with_ids)
