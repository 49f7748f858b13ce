"""Triangles and degrees of every vertex without a row for each wedge.

Vertices have one of r colours by hash, and an edge lies in the block of its two colours. A task gets the
blocks of three colours, so a triangle is found where its colours are, once; an edge is sent to r tasks.
Blocks travel as packed arrays of sorted differences, a few bytes an edge. A task points its edges to the
end of higher degree and looks up the wedges in pieces, which bounds its memory; wedges never leave it.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import EdgeGraph

#: edges of a task with three colours
TASK_EDGES = 3_000_000
#: edges that a task of the first stage packs at once, and wedges looked up at once
PACK_EDGES, WEDGES = 1_000_000, 1_000_000


def pack(*columns: np.ndarray) -> bytes:
    """Columns of longs, byte by byte of equal weight, compressed."""
    raw = np.stack([np.asarray(c, dtype="<i8") for c in columns]).view(np.uint8).reshape(-1, 8).T
    return len(columns[0]).to_bytes(8, "little") + pa.compress(np.ascontiguousarray(raw).tobytes(), codec="zstd", asbytes=True)


def unpack(data: bytes, n_columns: int) -> np.ndarray:
    n = int.from_bytes(data[:8], "little")
    raw = np.frombuffer(pa.decompress(data[8:], decompressed_size=n * n_columns * 8, codec="zstd", asbytes=True), dtype=np.uint8)
    return np.ascontiguousarray(raw.reshape(8, -1).T).view("<i8").reshape(n_columns, n)


def pack_pairs(x: np.ndarray, y: np.ndarray) -> bytes:
    """Pairs in order: differences of x, and of y inside an x."""
    order = np.lexsort((y, x))
    x, y = x[order], y[order]
    dx = np.diff(x, prepend=0)
    dy = np.diff(y, prepend=0)
    return pack(dx, np.where(dx != 0, y, dy))


def unpack_pairs(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    dx, dy = unpack(data, 2)
    if not len(dx):
        return dx, dy
    first = dx != 0
    first[0] = True
    run = np.cumsum(dy)
    start = np.flatnonzero(first)
    before = np.repeat(run[start] - dy[start], np.diff(start, append=len(dx)))
    return np.cumsum(dx), run - before


def local_triangles(x: np.ndarray, y: np.ndarray, cx: np.ndarray, cy: np.ndarray, colours: tuple[int, int, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The vertices of some edges, their colours, and for each the triangles whose corners have just these three colours."""
    vid, first, at = np.unique(np.concatenate((x, y)), return_index=True, return_inverse=True)
    colour = np.concatenate((cx, cy))[first]
    n, m = len(vid), len(x)
    rank = np.empty(n, dtype=np.int64)
    by_rank = np.lexsort((np.arange(n), np.bincount(at, minlength=n)))
    rank[by_rank] = np.arange(n)
    hue = colour[by_rank]
    a, b = np.minimum(rank[at[:m]], rank[at[m:]]), np.maximum(rank[at[:m]], rank[at[m:]])
    keys = np.sort(a * n + b)
    bits = max(10, min(25, (16 * m).bit_length()))
    seen = np.zeros(1 << bits, dtype=bool)  # tells most wedges that are open from the others
    cell = lambda u, v: (u * 2654435761 + v) & ((1 << bits) - 1)
    seen[cell(keys // n, keys % n)] = True
    apart = len(set(colours)) == 3
    # with three colours, the ends of a wedge differ in theirs: the lower meets all of the upper
    upper = hue[b] == np.where(hue[a] == colours[2], colours[1], colours[2]) if apart else np.zeros(m, dtype=bool)
    order = np.lexsort((b, upper, a))
    a, b, upper = a[order], b[order], upper[order]
    end = np.searchsorted(a, np.arange(n), side="right")[a]
    low = end - np.bincount(a[upper], minlength=n)[a] if apart else np.arange(m) + 1
    size = np.where(upper, 0, end - low)
    total, t, i = np.cumsum(size), np.zeros(n, dtype=np.int64), 0
    while i < m:
        done = total[i - 1] if i else 0
        j = max(i + 1, int(np.searchsorted(total, done + WEDGES, side="right")))
        s = size[i:j]
        one = np.repeat(np.arange(i, j), s)
        two = np.arange(len(one)) - np.repeat(total[i:j] - s - done, s) + low[one]
        u, v = b[one], b[two]
        if apart:
            u, v = np.minimum(u, v), np.maximum(u, v)
        near = np.flatnonzero(seen[cell(u, v)])
        key = u[near] * n + v[near]
        place = np.minimum(np.searchsorted(keys, key), m - 1)
        near = near[keys[place] == key]
        corners = np.stack((a[one[near]], u[near], v[near]))
        if not apart:
            corners = corners[:, (np.sort(hue[corners], axis=0) == np.array(colours)[:, None]).all(axis=0)]
        t += np.bincount(corners.ravel(), minlength=n)
        i = j
    return vid, colour, t[rank]


def triangle_stats(g: EdgeGraph, task_edges: int | None = None) -> DataFrame:
    """(vid, degree, triangles) of every vertex."""
    m = g.edges.count()
    r = max(1, math.ceil(math.sqrt(6 * m / (task_edges or TASK_EDGES))), 3 if m > 50_000 else 1)
    triples = list(itertools.combinations_with_replacement(range(r), 3))
    number = {t: i for i, t in enumerate(triples)}
    of_pair = {p * r + q: [number[tuple(sorted((p, q, c)))] for c in range(r)] for p in range(r) for q in range(p, r)}
    colour = lambda c: F.pmod(F.xxhash64(c), F.lit(r)).cast("int")

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in itertools.chain(batches, [None]):
            if batch is not None:
                held.append(batch)
                n += batch.num_rows
            if n and (batch is None or n >= PACK_EDGES):
                table = pa.Table.from_batches(held)
                pair, x, y = (table[c].to_numpy() for c in ("pair", "x", "y"))
                order = np.argsort(pair, kind="stable")
                keys, start = np.unique(pair[order], return_index=True)
                blocks = [pack_pairs(x[some], y[some]) for some in np.split(order, start[1:])]
                yield pa.record_batch({"pair": pa.array(keys, pa.int32()), "data": pa.array(blocks, pa.binary())})
                held, n = [], 0

    def block(table: pa.Table) -> pa.Table:
        pair = table["pair"][0].as_py()
        x, y = (np.concatenate(c) for c in zip(*map(unpack_pairs, table["data"].to_pylist()), strict=True))
        return pa.table({"pair": pa.array([pair], pa.int32()), "data": pa.array([pack_pairs(x, y)], pa.binary()), "triples": pa.array([of_pair[pair]], pa.list_(pa.int32()))})

    def count(table: pa.Table) -> pa.Table:
        colours = triples[table["triple"][0].as_py()]
        blocks = [(p, *unpack_pairs(d)) for p, d in zip(table["pair"].to_pylist(), table["data"].to_pylist(), strict=True)]
        x, y = (np.concatenate([b[i] for b in blocks]) for i in (1, 2))
        cx, cy = (np.concatenate([np.full(len(b[1]), f(b[0])) for b in blocks]) for f in (lambda p: p // r, lambda p: p % r))
        vid, hue, t = local_triangles(x, y, cx, cy, colours)
        # the edges of two colours p <= q count for the degrees where the colours are p, p, q
        own = (cx == colours[0]) & (cy == colours[2]) if colours[0] == colours[1] else np.zeros(len(x), dtype=bool)
        degree = np.bincount(np.searchsorted(vid, np.concatenate((x[own], y[own]))), minlength=len(vid))
        part = hue * r + vid // 16 % r
        kept = np.flatnonzero((t > 0) | (degree > 0))
        kept = kept[np.argsort(part[kept], kind="stable")]
        keys, start = np.unique(part[kept], return_index=True)
        some = [k for k in np.split(kept, start[1:]) if len(k)]
        return pa.table({"part": pa.array(keys, pa.int32()), "data": pa.array([pack(np.diff(vid[k], prepend=0), degree[k], t[k]) for k in some], pa.binary())})

    def summed(table: pa.Table) -> pa.Table:
        columns = [unpack(d, 3) for d in table["data"].to_pylist()]
        vid, at = np.unique(np.concatenate([np.cumsum(c[0]) for c in columns]), return_inverse=True)
        total = [np.zeros(len(vid), dtype=np.int64) for _ in range(2)]
        for i in (1, 2):
            np.add.at(total[i - 1], at, np.concatenate([c[i] for c in columns]))
        return pa.table({"vid": vid, "degree": total[0], "triangles": total[1]})

    e = g.edges.select("src", "dst", colour("src").alias("p"), colour("dst").alias("q"))
    swap = F.col("p") > F.col("q")
    e = e.select((F.least("p", "q") * r + F.greatest("p", "q")).alias("pair"), F.when(swap, F.col("dst")).otherwise(F.col("src")).alias("x"), F.when(swap, F.col("src")).otherwise(F.col("dst")).alias("y"))
    blocks = e.mapInArrow(packed, "pair int, data binary").groupBy("pair").applyInArrow(block, "pair int, data binary, triples array<int>")
    sent = blocks.select("pair", "data", F.explode("triples").alias("triple"))
    return sent.groupBy("triple").applyInArrow(count, "part int, data binary").groupBy("part").applyInArrow(summed, "vid long, degree long, triangles long")
