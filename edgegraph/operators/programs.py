"""Programs of the replica engine: distances, components, independent sets, betweenness."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import portable_hash
from ..model import EdgePartitioning
from ..plans import Scratch
from .engine import Local, Outcome, Program, run_program


def _neighbours(a: np.ndarray, b: np.ndarray, w: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Both directions of all edges in order of their first end: offsets, other ends, weights."""
    ends, others, weight = np.concatenate((a, b)), np.concatenate((b, a)), np.concatenate((w, w))
    order = np.argsort(ends, kind="stable")
    return np.searchsorted(ends[order], np.arange(n + 1)), others[order], weight[order]


def _nearest(part: Local):
    """Distances inside one part, from the vertices whose distance is new."""
    at, others, weight = _neighbours(part.a, part.b, part.weight, len(part.value))
    best = part.value.astype(np.float64)
    front = part.dirty[best[part.dirty] < np.inf]
    while len(front):
        size = at[front + 1] - at[front]
        edge = np.repeat(at[front] - (np.cumsum(size) - size), size) + np.arange(size.sum())
        to, far = others[edge], np.repeat(best[front], size) + weight[edge]
        nearer = far < best[to]
        to = to[nearer]
        np.minimum.at(best, to, far[nearer])
        front = np.unique(to)
    return best


def distances(p: EdgePartitioning, sources: int | list[int], weight: str | None = None, **options) -> Outcome:
    """(vid, value): the distance from the nearest source, null where none is reached. Unit steps, or a
    column of non-negative weights of the assigned edges."""
    some = [sources] if isinstance(sources, int) else list(sources)

    def setup(copies: DataFrame) -> DataFrame:
        start = F.col("vid").isin(some)
        return copies.select("part", "vid", "n_copies", F.when(start, F.lit(0.0)).alias("value"), start.alias("dirty"))

    return run_program(p, Program("distance", "double", setup, _nearest, lambda v, w: v + w), weight=weight, **options)


def _smallest(part: Local):
    """The smallest label of each local component to all of its members."""
    a, b, value = part.a, part.b, part.value
    root = np.arange(len(value))
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        while not (new[new] == new).all():
            new = new[new]
        if (new == root).all():
            break
        root = new
    least = value.copy()
    np.minimum.at(least, root, value)
    return least[root]


def components(p: EdgePartitioning, **options) -> Outcome:
    """(vid, value): the smallest vertex of each component. Vertex ids serve as labels, which are unique,
    and the smallest one needs no draw."""

    def setup(copies: DataFrame) -> DataFrame:
        return copies.select("part", "vid", "n_copies", F.col("vid").alias("value"), F.lit(True).alias("dirty"))

    return run_program(p, Program("components", "long", setup, _smallest, lambda v, w: v), **options)


_WAITS, _READY, _IN, _OUT = range(4)


def _decide(part: Local):
    """Settles what a part can tell: out beside a member; ready where all neighbours of lower rank are out,
    which makes a vertex of one part a member at once."""
    status, low = part.value, np.lexsort((part.vid, part.extra["rank"]))
    place = np.empty(len(low), dtype=np.int64)
    place[low] = np.arange(len(low))
    ends, others = np.concatenate((part.a, part.b)), np.concatenate((part.b, part.a))
    lower = place[others] < place[ends]
    while True:
        before = status.copy()
        beside = np.zeros(len(status), dtype=bool)
        beside[ends[status[others] == _IN]] = True
        status[beside & (status < _IN)] = _OUT
        blocked = np.zeros(len(status), dtype=bool)
        blocked[ends[lower & (status[others] != _OUT)]] = True
        status[~blocked & (status == _WAITS)] = _READY
        status[(status == _READY) & (part.copies == 1)] = _IN
        if (status == before).all():
            return status


def maximal_independent_set(p: EdgePartitioning, seed: int = 0, **options) -> tuple[DataFrame, int]:
    """(vid, in_set) and the supersteps taken: the set that takes vertices by a fixed random rank, each
    unless a neighbour is in. Ranks are spread to the parts by the setup; a shared vertex joins when all
    of its replicas are ready, and leaves when one sees a member beside it, which the reconcile decides.
    """

    def setup(copies: DataFrame) -> DataFrame:
        return copies.select("part", "vid", "n_copies", portable_hash(seed, F.col("vid")).alias("rank"), F.lit(_WAITS).alias("value"), F.lit(True).alias("dirty"))

    def agree(c: str) -> Column:
        return F.when(F.max(c) == _OUT, _OUT).when(F.min(c) >= _READY, _IN).otherwise(_WAITS)

    program = Program("independent-set", "int", setup, _decide, reconcile=agree, whole=True, adopt=lambda own, told: np.where(told >= _IN, told, own), extra="rank long")
    out = run_program(p, program, **options)
    return out.states.select("vid", (F.col("value") == _IN).alias("in_set")), out.supersteps


def betweenness(p: EdgePartitioning, sources: list[int]) -> DataFrame:
    """(vid, score): the sum over sources of the share of shortest paths that pass through a vertex (ends
    not counted). Path counts must go level by level and be summed over replicas, so this program gains
    nothing from solving parts as a whole; distances come from the engine."""
    scratch = Scratch(p.spark, "betweenness")
    total = None
    for s in sources:
        dist = scratch.store(distances(p, s).states.where("value is not null").select("vid", F.col("value").cast("int").alias("d")))
        side = lambda v, d: dist.select(F.col("vid").alias(v), F.col("d").alias(d))
        down = p.assigned.join(side("src", "ds"), "src").join(side("dst", "dd"), "dst").where("abs(ds - dd) = 1")
        near = F.col("ds") < F.col("dd")
        down = scratch.store(down.select("part", F.when(near, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(near, F.col("dst")).otherwise(F.col("src")).alias("v"), F.greatest("ds", "dd").alias("level")))
        deepest = dist.agg(F.max("d")).first()[0] or 0
        paths = scratch.store(dist.where("d = 0").select("vid", F.lit(1.0).alias("paths")))
        for level in range(1, deepest + 1):  # partial counts by part, then the sum over replicas
            local = down.where(F.col("level") == level).join(paths.withColumnRenamed("vid", "u"), "u").groupBy("part", "v").agg(F.sum("paths").alias("n"))
            paths = scratch.store(paths.union(local.groupBy(F.col("v").alias("vid")).agg(F.sum("n").alias("paths"))))
        owed = scratch.store(dist.select("vid", F.lit(0.0).alias("dep")).where("false"))
        for level in range(deepest, 0, -1):
            below = down.where(F.col("level") == level).join(paths.select(F.col("vid").alias("v"), F.col("paths").alias("pv")), "v").join(paths.select(F.col("vid").alias("u"), F.col("paths").alias("pu")), "u")
            below = below.join(owed.select(F.col("vid").alias("v"), "dep"), "v", "left")
            local = below.groupBy("part", "u").agg(F.sum(F.col("pu") / F.col("pv") * (1 + F.coalesce("dep", F.lit(0.0)))).alias("n"))
            owed = scratch.store(owed.union(local.groupBy(F.col("u").alias("vid")).agg(F.sum("n").alias("dep"))))
        own = owed.where(F.col("vid") != s)
        total = own if total is None else total.union(own)
    score = p.replicas().select("vid").distinct().join(total.groupBy("vid").agg(F.sum("dep").alias("score")), "vid", "left")
    return score.select("vid", F.coalesce("score", F.lit(0.0)).alias("score"))
