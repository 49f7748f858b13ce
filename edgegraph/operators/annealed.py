"""Annealed swap: a vertex partitioner that swaps the parts of vertices, the baseline of the comparison.

Parts start with as many vertices each. In a round every vertex proposes to swap parts with a neighbour and
with a random vertex, by hash, where that brings both more neighbours of their own part; random partners
are the vertices of a hash cell, and cells grow in number with the graph, so each vertex has one;
proposals that are best for both sides are carried out together, so swaps never meet and the sizes of
parts stay exactly as they were. The temperature first accepts swaps that bring less, and falls to 1. From
then on a swap must lower the number of cut edges, and of swaps whose ends are linked only the best one is
carried out, so that number falls by each of them and every run ends.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import Hashes, distinct, portable_hash, spans
from ..model import EdgeGraph, EdgePartitioning
from ..plans import Scratch
from .baselines import edges_from_vertices


def start_parts(g: EdgeGraph, k: int, seed: int = 0) -> DataFrame:
    """(vid, part): about as many vertices in each part, dealt by hash. Ranks come from counts of hash
    cells and a rank inside each cell, so no task sorts all vertices."""
    cells = 1024
    h = portable_hash(seed, F.col("vid"))
    v = g.vertices().select("vid", h.alias("h"), F.shiftright(h, 50).cast("int").alias("cell"))  # of 60 bits
    count = v.groupBy("cell").agg(F.count(F.lit(1)).alias("n"))  # 1024 rows at most
    before = F.sum("n").over(Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1))
    base = count.select("cell", F.coalesce(before, F.lit(0)).alias("before"))
    assert cells == 1 << 10
    rank = F.row_number().over(Window.partitionBy("cell").orderBy("h", "vid")) - 1
    return v.join(F.broadcast(base), "cell").select("vid", F.pmod(F.col("before") + rank, F.lit(k)).cast("int").alias("part"))


#: hash cells for n vertices: about two in each, so the random pairs of a round grow with the graph
def n_cells(n: int) -> int:
    return max(1, n // 2)


#: rounds without a cap end when no swap is accepted; one that has not ended by then raises
NEVER = 2000
#: a graph of up to so many edges is swapped in one task, by the same rules: its rounds are shorter than those of jobs
TASK_EDGES = 2_000_000
#: rounds without a swap that end a run
QUIET = 2


def annealed_swap(g: EdgeGraph, k: int, seed: int = 0, most_rounds: int | None = None, alpha: float = 2.0, t0: float = 2.0, delta: float = 0.05, task_edges: int | None = None) -> tuple[DataFrame, list[dict]]:
    """(vid, part) and the history of rounds. Ends at temperature 1 when no swap is accepted in QUIET rounds one
    after the other, or after most_rounds where they are given (the last row of the history then has swaps).
    Graphs of up to task_edges (TASK_EDGES) edges take their rounds in one task."""
    scratch = Scratch(g.spark, "annealed")
    if g.edges.count() <= (TASK_EDGES if task_edges is None else task_edges):
        return _in_one_task(scratch, g, k, seed, most_rounds, alpha, t0, delta)
    half = scratch.store(g.half_edges().select("vid", "nbr"))
    parts = scratch.store(start_parts(g, k, seed), "parts")
    history, t, quiet, n = [], t0, 0, parts.count()
    for i in range(NEVER if most_rounds is None else most_rounds):
        seen = half.join(parts.select(F.col("vid").alias("nbr"), F.col("part").alias("np")), "nbr").groupBy("vid", "np").agg(F.count(F.lit(1)).alias("n"))
        counts = seen.groupBy("vid").agg(F.map_from_entries(F.collect_list(F.struct("np", "n"))).alias("by"))  # k entries at most
        state = scratch.store(parts.join(counts, "vid"), "state")
        # partners: one neighbour by hash, and one vertex of a hash sample by a common cell
        turn = portable_hash(seed + 1 + i, F.col("vid"), F.col("nbr"))
        by_edge = half.groupBy("vid").agg(F.min_by("nbr", turn).alias("mate"))
        cell = F.pmod(portable_hash(seed + 7919 * (i + 1), F.col("vid")), F.lit(n_cells(n)))
        # the next vertex of the cell, and the first after the last; cells hold a few vertices each
        order = Window.partitionBy("cell").orderBy("vid")
        by_sample = parts.select("vid", cell.alias("cell")).withColumn("mate", F.coalesce(F.lead("vid").over(order), F.first("vid").over(order))).select("vid", "mate")
        mates = by_edge.unionByName(by_sample).where("vid != mate")
        a = state.select("vid", F.col("part").alias("p"), F.col("by").alias("a"))
        b = state.select(F.col("vid").alias("mate"), F.col("part").alias("q"), F.col("by").alias("b"))
        got = lambda m, key, power: F.pow(F.coalesce(F.try_element_at(F.col(m), F.col(key)), F.lit(0)).cast("double"), F.lit(power))
        if t <= 1.0:  # edges that a swap spares: a linked pair stays cut, and counts each other
            linked = half.select("vid", F.col("nbr").alias("mate"), F.lit(1).alias("linked"))
            mates, power = mates.join(linked, ["vid", "mate"], "left").withColumn("own", 2 * F.coalesce("linked", F.lit(0))), 1.0
        else:
            mates, power = mates.withColumn("own", F.lit(0)), alpha
        rows = mates.join(a, "vid").join(b, "mate").where("p != q")
        rows = rows.withColumn("gain", (got("a", "q", power) + got("b", "p", power)) * t - (got("a", "p", power) + got("b", "q", power)) - F.col("own")).where("gain > 0")
        pair = rows.select(F.least("vid", "mate").alias("x"), F.greatest("vid", "mate").alias("y"), F.struct(F.round("gain", 6).alias("gain"), portable_hash(seed, F.least("vid", "mate"), F.greatest("vid", "mate")).alias("tie")).alias("value")).distinct()
        pair = scratch.store(pair, "pairs")
        ends = pair.select(F.explode(F.array("x", "y")).alias("vid"), "x", "y", "value")
        best = ends.groupBy("vid").agg(F.max(F.struct("value", "x", "y")).alias("e"))
        agreed = best.groupBy("e").agg(F.count(F.lit(1)).alias("n")).where("n = 2").select("e.x", "e.y", "e")
        if t <= 1.0:
            agreed = scratch.store(agreed, "agreed")
            mine = agreed.select(F.explode(F.array("x", "y")).alias("vid"), "e")
            beside = half.join(mine, "vid").select(F.col("nbr").alias("vid"), F.col("e").alias("other"))
            agreed = agreed.join(mine.join(beside, "vid").where("other > e").select("e").distinct(), "e", "left_anti")
        sides = agreed.join(parts.select(F.col("vid").alias("x"), F.col("part").alias("px")), "x").join(parts.select(F.col("vid").alias("y"), F.col("part").alias("py")), "y")
        moves = scratch.store(sides.select(F.explode(F.array(F.struct(F.col("x").alias("vid"), F.col("py").alias("to")), F.struct(F.col("y").alias("vid"), F.col("px").alias("to")))).alias("m")).select("m.vid", "m.to"), "moves")
        swaps = moves.count() // 2
        parts = scratch.store(parts.join(moves, "vid", "left").select("vid", F.coalesce("to", "part").alias("part")), "parts")
        history.append({"round": i + 1, "temperature": t, "swaps": swaps})
        quiet = quiet + 1 if t <= 1.0 and not swaps else 0
        if quiet == QUIET:
            break
        t = max(1.0, t - delta)
    else:
        if most_rounds is None:
            raise RuntimeError(f"swaps go on after {NEVER} rounds")
    return parts, history


def _in_one_task(scratch: Scratch, g: EdgeGraph, k: int, *options) -> tuple[DataFrame, list[dict]]:
    """annealed_swap() by swap_arrays() in one task; the history comes beside the parts, without a vertex."""

    def run(table: pa.Table) -> pa.Table:
        ids, part, history = swap_arrays(table["src"].to_numpy(), table["dst"].to_numpy(), k, *options)
        kinds = pa.schema([("vid", pa.int64()), ("part", pa.int32()), ("round", pa.int32()), ("temperature", pa.float64()), ("swaps", pa.int32())])
        parts = pa.table({"vid": ids, "part": part.astype(np.int32)})
        return pa.concat_tables([parts, pa.Table.from_pylist(history, pa.schema(list(kinds)[2:]))], promote_options="default").select(kinds.names)

    one = g.edges.select("src", "dst", F.lit(0).alias("all")).groupBy("all")
    rows = scratch.store(one.applyInArrow(run, "vid long, part int, round int, temperature double, swaps int"))
    history = rows.where("vid is null").orderBy("round").select("round", "temperature", "swaps").collect()  # NEVER rows at most
    return rows.where("vid is not null").select("vid", "part"), [r.asDict() for r in history]


def swap_edges(g: EdgeGraph, k: int, seed: int = 0, **options) -> EdgePartitioning:
    """The edge partitioning that annealed swap gives by a coin for each cut edge."""
    parts, history = annealed_swap(g, k, seed, **options)
    p = edges_from_vertices(g, parts, k, seed)
    p.history = [{"changed": h["swaps"]} for h in history]
    return p


def simulate_swap(edges: list[tuple[int, int]], k: int, seed: int = 0, most_rounds: int | None = 350, alpha: float = 2.0, t0: float = 2.0, delta: float = 0.003) -> tuple[dict[tuple[int, int], int], int]:
    """Owners of all edges and the rounds of annealed_swap, in one process (for sweeps)."""
    src, dst = np.array(edges, dtype=np.int64).reshape(-1, 2).T
    owner, rounds = swap_owners(src, dst, k, seed, most_rounds, alpha, t0, delta)
    return dict(zip(edges, owner.tolist(), strict=True)), rounds


def swap_owners(src: np.ndarray, dst: np.ndarray, k: int, seed: int = 0, most_rounds: int | None = 350, alpha: float = 2.0, t0: float = 2.0, delta: float = 0.003) -> tuple[np.ndarray, int]:
    """The same for arrays of ends: the owner of each edge."""
    ids, part, history = swap_arrays(src, dst, k, seed, most_rounds, alpha, t0, delta)
    coin = np.where(Hashes(src, dst)(seed) % 2 == 0, src, dst)
    return part[np.searchsorted(ids, coin)], len(history)


def simulate_parts(edges: list[tuple[int, int]], k: int, seed: int = 0, *options, **named) -> tuple[dict[int, int], list[dict]]:
    """The same as annealed_swap: parts of the vertices, and the history."""
    src, dst = np.array(edges, dtype=np.int64).reshape(-1, 2).T
    ids, part, history = swap_arrays(src, dst, k, seed, *options, **named)
    return dict(zip(ids.tolist(), part.tolist(), strict=True)), history


def swap_arrays(src: np.ndarray, dst: np.ndarray, k: int, seed: int = 0, most_rounds: int | None = None, alpha: float = 2.0, t0: float = 2.0, delta: float = 0.05) -> tuple[np.ndarray, np.ndarray, list[dict]]:
    """The vertices, their parts and the history of annealed_swap, in one process. Vertices are numbered by id."""
    ids, ends = np.unique(np.concatenate((src, dst)), return_inverse=True)
    n, m = len(ids), len(src)
    order = np.argsort(ends, kind="stable")
    mate_of = np.concatenate((ends[m:], ends[:m]))[order]  # the other end of each half-edge, by vertex
    degree = np.bincount(ends, minlength=n)
    begin = np.cumsum(degree) - degree
    half = np.repeat(np.arange(n), degree)
    part = np.empty(n, np.int64)
    part[np.argsort(Hashes(ids)(seed), kind="stable")] = np.arange(n) % k
    count = np.bincount(half * k + part[mate_of], minlength=n * k)
    links = np.sort(half * n + mate_of)
    several = degree > 1  # with one neighbour, that one is the mate
    at = np.flatnonzero(several[half])
    of_half, of_vertex, runs = Hashes(ids[half[at]], ids[mate_of[at]]), Hashes(ids), degree[several]
    only = mate_of[begin[~several]]
    history, t, quiet = [], t0, 0
    for i in range(NEVER if most_rounds is None else most_rounds):
        cell = of_vertex(seed + 7919 * (i + 1)) % n_cells(n)
        by = np.argsort(cell, kind="stable")
        new = np.flatnonzero(np.diff(cell[by], prepend=-1))
        after = np.roll(by, -1)
        after[np.append(new[1:], n)[: len(new)] - 1] = by[new]  # the first after the last
        mate = np.empty(n, np.int64)
        mate[~several] = only
        if len(at):
            turn = of_half(seed + 1 + i)
            starts = np.cumsum(runs) - runs
            least = np.flatnonzero(turn == np.repeat(np.minimum.reduceat(turn, starts), runs))
            mate[several] = mate_of[at[least[np.searchsorted(least, starts)]]]
        x, y = np.concatenate((by, np.arange(n))), np.concatenate((after, mate))
        x, y = np.minimum(x, y), np.maximum(x, y)
        key = distinct((x * n + y)[x != y])
        x, y = key // n, key % n
        p, q = part[x], part[y]
        apart = p != q
        key, x, y, p, q = key[apart], x[apart], y[apart], p[apart], q[apart]
        power = alpha if t > 1.0 else 1.0
        got = lambda v, p: count[v * k + p].astype(float) ** power  # noqa: E731, B023
        gain = (got(x, q) + got(y, p)) * t - (got(x, p) + got(y, q))
        if t <= 1.0 and m:
            gain -= 2.0 * (links[np.minimum(np.searchsorted(links, key), 2 * m - 1)] == key)
        more = gain > 0
        x, y, p, q = x[more], y[more], p[more], q[more]
        gains, which = np.unique(gain[more], return_inverse=True)
        rounded = np.array([round(g, 6) for g in gains.tolist()])
        best, place = np.full(n, -1), np.empty(len(x), np.int64)
        place[np.lexsort((y, x, Hashes(ids[x], ids[y])(seed), rounded[which] if len(x) else which))] = np.arange(len(x))
        np.maximum.at(best, x, place)
        np.maximum.at(best, y, place)
        agreed = (best[x] == place) & (best[y] == place)
        x, y, p, q, place = x[agreed], y[agreed], p[agreed], q[agreed], place[agreed]
        if t <= 1.0 and len(x):
            swaps = np.full(n, -1)
            swaps[x] = swaps[y] = place
            both = np.concatenate((x, y))
            around, of = spans(begin[both], degree[both])
            beside = np.maximum.reduceat(swaps[mate_of[around]], np.cumsum(degree[both]) - degree[both])
            first = (beside[: len(x)] <= place) & (beside[len(x) :] <= place)
            x, y, p, q = x[first], y[first], p[first], q[first]
        both, old, to = np.concatenate((x, y)), np.concatenate((p, q)), np.concatenate((q, p))
        around, of = spans(begin[both], degree[both])
        np.subtract.at(count, mate_of[around] * k + old[of], 1)
        np.add.at(count, mate_of[around] * k + to[of], 1)
        part[both] = to
        history.append({"round": i + 1, "temperature": t, "swaps": len(x)})
        quiet = quiet + 1 if t <= 1.0 and not len(x) else 0
        if quiet == QUIET:
            break
        t = max(1.0, t - delta)
    else:
        if most_rounds is None:
            raise RuntimeError(f"swaps go on after {NEVER} rounds")
    return ids, part, history
