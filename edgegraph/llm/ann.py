"""Approximate nearest neighbours by collision counting over sorted projections.

Vectors are dealt into blocks of bounded size. A block keeps one sorted array for each of ``projections``
random lines. A query looks into the ``used`` lines on which its own projection is farthest from zero, where
near vectors stand apart from the rest most, through windows centred at that projection; virtual rehashing
widens the windows step by step, and only what a step adds is counted. A vector that collides on
``threshold`` of these lines is verified by its exact inner product. The search of a block ends when a
vector as near as the k-th best one found would have reached the threshold with probability ``sure``, or
when the windows hold the whole block.

Inner products become distances by one more coordinate, sqrt(M**2 - |x|**2) with M the largest norm, and
queries scaled to norm M. On a line where the query stands at c, a vector of cosine s to it then stands at
s * c plus a normal error of variance (1 - s**2) * M**2, whichever lines the query chose, so the chance of a
collision is known for each line. Queries meet all blocks, in blocks of their own; each such pair of blocks
returns the k best at most, and the best of all are ranked.
"""

from __future__ import annotations

import math
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

_FOUND = "query_id long, vec_id array<long>, score array<double>"


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, v array<double>): vectors that are not null or zero and hold finite components only.
    Of rows that share a vec_id the smallest vector counts; rows without vec_id take no part."""
    v = F.col("embedding").cast("array<double>")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("v", lambda x: x != 0)
    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & fine).groupBy("vec_id").agg(F.min("v").alias("v"))


def _matrix(table: pa.Table, dim: int) -> tuple[np.ndarray, np.ndarray]:
    ids = table["vec_id"].to_numpy()
    flat = pa.concat_arrays([c.flatten() for c in table["v"].chunks]).to_numpy() if table.num_rows else np.zeros(0)
    return ids, np.ascontiguousarray(flat.reshape(-1, dim))


def _below(z: np.ndarray) -> np.ndarray:
    """The chance that a standard normal variable is below z."""
    return 0.5 + 0.5 * np.array([math.erf(x) for x in z / math.sqrt(2)])


class Block:
    """Sorted projections of one block of vectors."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, largest: float, lines: np.ndarray, used: int, threshold: float, sure: float) -> None:
        order = np.argsort(ids)
        self.ids, self.x, self.largest, self.lines = ids[order], vectors[order], largest, lines
        extra = np.sqrt(np.maximum(largest**2 - (self.x**2).sum(axis=1), 0.0))
        self.sorted = np.empty((lines.shape[1], len(ids)), dtype=np.float32)
        self.order = np.empty(self.sorted.shape, dtype=np.int32)
        for i, line in enumerate(np.ascontiguousarray(lines.T)):
            at = (self.x @ line[:-1] + extra * line[-1]).astype(np.float32)
            self.order[i] = np.argsort(at)
            self.sorted[i] = at[self.order[i]]
        self.used = min(used, lines.shape[1])
        self.need = math.ceil(threshold * self.used)
        self.z = NormalDist().inv_cdf(sure)
        self.start = 0.05 * largest
        self.verified = self.searched = 0

    def reached(self, centre: np.ndarray, half: float, cosine: float) -> bool:
        """Whether a vector of this cosine to the query has collided often enough, as surely as asked for."""
        cosine = min(cosine, 1.0 - 1e-12)
        error = math.sqrt(1.0 - cosine**2) * self.largest
        away = centre * (1.0 - cosine)
        p = _below((away + half) / error) - _below((away - half) / error)
        return p.sum() - self.need + 0.5 >= self.z * math.sqrt((p * (1.0 - p)).sum())

    def search(self, query_id: int, query: np.ndarray, k: int, growth: float) -> tuple[np.ndarray, np.ndarray]:
        norm = math.sqrt(query @ query)
        centre = (query * (self.largest / norm)) @ self.lines[:-1]
        chosen = np.argsort(-np.abs(centre), kind="stable")[: self.used]
        centre = centre[chosen]
        lines = [(self.sorted[i], self.order[i], c) for i, c in zip(chosen, centre, strict=True)]
        n = len(self.ids)
        count = np.zeros(n, dtype=np.int64)
        verified = np.zeros(n, dtype=bool)
        own = np.searchsorted(self.ids, query_id)
        verified[own : own + 1] = self.ids[own : own + 1] == query_id  # never a candidate
        take, score = np.zeros(0, dtype=np.int64), np.zeros(0)
        windows = None
        half = self.start
        while True:
            wider = [(int(at.searchsorted(np.float32(c - half))), int(at.searchsorted(np.float32(c + half), side="right"))) for at, _, c in lines]
            if windows is None:
                added = [o[a:b] for (_, o, _), (a, b) in zip(lines, wider, strict=True)]
            else:
                added = [part for (_, o, _), (a, b), (c, d) in zip(lines, wider, windows, strict=True) for part in (o[a:c], o[d:b])]
            windows = wider
            count += np.bincount(np.concatenate(added), minlength=n)
            fresh = np.flatnonzero((count >= self.need) & ~verified)
            verified[fresh] = True
            take, score = np.concatenate([take, fresh]), np.concatenate([score, self.x[fresh] @ query])
            if all(a == 0 and b == n for a, b in windows):
                break
            if len(take) >= k and self.reached(centre, half, np.partition(score, len(take) - k)[len(take) - k] / (norm * self.largest)):
                break
            half *= growth
        self.start = half / growth**2  # queries of one block need windows alike
        self.verified, self.searched = self.verified + len(take), self.searched + n
        if len(take) > k:
            kth = np.partition(score, len(take) - k)[len(take) - k]
            take = take[score >= kth - 1e-9 * (abs(kth) + 1)]
        exact = (self.x[take] * query).sum(axis=1)  # the same sum for equal vectors, wherever they stand
        best = np.lexsort((self.ids[take], -exact))[:k]
        return self.ids[take][best], exact[best]


def _meet(vectors: DataFrame, is_query: Column, k: int, block_rows: int, query_rows: int, prepare) -> DataFrame:
    """The best k of what all pairs of a block of vectors and a block of queries give.

    prepare(ids, vectors, largest norm) readies a block and returns a function of a query's id and vector
    that gives the vec_ids and scores of k candidates at most.
    """
    v = usable(vectors)
    norm = F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)
    found = v.groupBy(F.size("v").alias("dim")).agg(F.count(F.lit(1)).alias("n"), F.max(norm).alias("most"), F.sum(is_query.cast("long")).alias("queries")).orderBy(F.desc("n"), "dim").first()
    dim, n, largest, queries = (found["dim"], found["n"], math.sqrt(found["most"]), found["queries"] or 0) if found else (1, 0, 1.0, 0)
    v = v.where(F.size("v") == dim)
    blocks, parts = max(1, math.ceil(n / block_rows)), max(1, math.ceil(queries / query_rows))

    def deal(rows: DataFrame, own: str, count: int, other: str, others: int) -> DataFrame:
        rows = rows.withColumn(own, F.pmod(F.xxhash64("vec_id", F.lit(own)), F.lit(count)).cast("int"))
        return rows.withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(others - 1))))

    def search(_, stored: pa.Table, asked: pa.Table) -> pa.Table:
        out = []
        if stored.num_rows and asked.num_rows:
            block = prepare(*_matrix(stored, dim), largest)
            ids, queries = _matrix(asked, dim)
            for i in np.argsort(ids):
                out.append((int(ids[i]), *block(int(ids[i]), queries[i])))
        cols = [*zip(*out)] or [()] * 3
        return pa.Table.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.list_(pa.int64())), pa.array(cols[2], pa.list_(pa.float64()))], ["query_id", "vec_id", "score"])

    stored = deal(v, "block", blocks, "part", parts).select("block", "part", "vec_id", "v")
    asked = deal(v.where(is_query), "part", parts, "block", blocks).select("block", "part", "vec_id", "v")
    pairs = stored.groupBy("block", "part").cogroup(asked.groupBy("block", "part")).applyInArrow(search, _FOUND)
    each = pairs.select("query_id", F.explode(F.arrays_zip("vec_id", "score")).alias("x")).select("query_id", "x.vec_id", "x.score")
    place = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return each.withColumn("rank", F.row_number().over(place)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def nearest(vectors: DataFrame, is_query: Column, k: int = 20, projections: int = 512, used: int = 48, threshold: float = 0.3, sure: float = 0.95, growth: float = 1.1, block_rows: int = 32_768, query_rows: int = 8_192, seed: int = 7) -> DataFrame:
    """The k vectors of the largest inner product for each query, among all rows but the query's own.

    vectors: vec_id, embedding (array of numbers); is_query: a condition on vec_id. Returns query_id, rank
    (from 1, ties to the smaller vec_id), vec_id, score (in double precision, on the vectors given). See
    usable() for the rows that take part; of these, only those of the commonest length (the shorter one if
    two are as common). Where fewer than k candidates exist, all are returned. The answer is approximate:
    each vector among the k nearest is found with a probability of about ``sure`` at least. An empty table
    gives no rows. A task holds one block: 8 bytes for each of its rows and projections, and its vectors.
    """

    def prepare(ids: np.ndarray, x: np.ndarray, largest: float):
        lines = np.random.default_rng(seed).standard_normal((x.shape[1] + 1, projections))
        block = Block(ids, x, largest, lines, used, threshold, sure)
        return lambda query_id, query: block.search(query_id, query, k, growth)

    return _meet(vectors, is_query, k, block_rows, query_rows, prepare)


def brute_force(vectors: DataFrame, is_query: Column, k: int = 20, block_rows: int = 32_768, query_rows: int = 8_192) -> DataFrame:
    """The exact answer to nearest(), from all inner products: the baseline for its recall."""

    def prepare(ids: np.ndarray, x: np.ndarray, largest: float):
        def search(query_id: int, query: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            others = ids != query_id
            score = (x[others] * query).sum(axis=1)
            best = np.lexsort((ids[others], -score))[:k]
            return ids[others][best], score[best]

        return search

    return _meet(vectors, is_query, k, block_rows, query_rows, prepare)
