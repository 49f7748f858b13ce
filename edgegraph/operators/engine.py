"""The replica engine: local solves on the parts of an edge partitioning, and a reconcile of replicas.

A program gives the first states of a part's vertices (and of its edges, if these have any), a sequential
solve of one part, and an aggregate that agrees on one state for the replicas of a vertex. The engine
repeats solve and reconcile until nothing changes or the program's goal is reached.

A superstep is one job. Edges and states lie in tables bucketed by part, so neither is exchanged. What
crosses the network are the states of shared vertices that changed, once by vertex to be reconciled and
once by part to be told to the replicas that differ; they come beside the stored states of their part,
and the solve writes the new states.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..model import EdgePartitioning
from ..plans import Scratch


@dataclass
class Local:
    """One part as its solve sees it. Edges are pairs of places a, b in the vertex arrays."""

    a: np.ndarray
    b: np.ndarray
    weight: np.ndarray
    vid: np.ndarray
    copies: np.ndarray  # in how many parts a vertex stands
    value: np.ndarray
    dirty: np.ndarray  # places of vertices whose state came from outside, or starts the solve
    extra: dict[str, np.ndarray] = field(default_factory=dict)
    edge_value: np.ndarray | None = None


@dataclass
class Program:
    """States are single values; a null number is above all.

    setup: (part, vid, n_copies) with columns value and dirty, and those of ``extra`` (a schema string of
    columns that stay as they are); dirty vertices start the first solve.
    solve: one part to its new values, or to new values and new edge states.
    reconcile: the aggregate over states of the replicas of a vertex. As long as states only move one way
    in its order (a minimum, maximum, or), the changed ones tell all; set ``whole`` for an aggregate that
    must see every replica.
    adopt: own and reconciled values to the new ones; by default the smaller one.
    relax: what a value becomes over an edge, as a Column, for parts too large for one worker (a minimum).
    edge_setup: the first state of an edge, as a Column of (part, src, dst, w); a double.
    done: ends the run early, from the statistics of a superstep (changed, shared_changed, superstep).
    """

    name: str
    value_type: str
    setup: Callable[[DataFrame], DataFrame]
    solve: Callable[[Local], np.ndarray | tuple[np.ndarray, np.ndarray]]
    relax: Callable[[Column, Column], Column] | None = None
    reconcile: Callable[[str], Column] = F.min
    whole: bool = False
    adopt: Callable[[np.ndarray, np.ndarray], np.ndarray] = np.minimum
    extra: str = ""
    edge_setup: Column | None = None
    done: Callable[[dict], bool] | None = None


@dataclass
class Outcome:
    states: DataFrame  # vid, value
    supersteps: int  # that changed a state
    moved: list[int]  # rows sent for shared vertices, up and down, by superstep
    edges: DataFrame | None = None  # part, src, dst, edge_value of programs with edge states
    last: DataFrame | None = None  # the states by part and vertex, with the columns of extra


def place(p: EdgePartitioning, weight: str | None = None) -> DataFrame:
    """(part, src, dst, w) of the assigned edges."""
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    return p.assigned.select("part", "src", "dst", w.alias("w"))


def _numbers(column: pa.ChunkedArray) -> np.ndarray:
    value = column.to_numpy(zero_copy_only=False)
    return np.where(np.isnan(value), np.inf, value) if value.dtype.kind == "f" else value.copy()


def _column(value: np.ndarray, kind: pa.DataType) -> pa.Array:
    return pa.array(np.where(np.isinf(value), np.nan, value), from_pandas=True).cast(kind) if value.dtype.kind == "f" else pa.array(value).cast(kind)


def _arrow_solve(program: Program, extra: list[str], most_edges: int, first: bool):
    """Function of a part's edges, and of its states with what its replicas are told (changed: null)."""
    solve, adopt, stateful = program.solve, program.adopt, program.edge_setup is not None

    def run(edges: pa.Table, rows: pa.Table) -> pa.Table:
        if edges.num_rows > most_edges:
            raise ValueError(f"a part has {edges.num_rows} edges, over {most_edges}: raise k, or use local='sql'")
        told = rows["changed"].is_null()
        states, news = rows.filter(pc.invert(told)), rows.filter(told)
        vid = states["vid"].to_numpy()
        order = np.argsort(vid)
        sorted_vid = vid[order]
        find = lambda c: order[np.searchsorted(sorted_vid, c.to_numpy())]
        old = _numbers(states["value"])
        value = old.copy()
        if first:
            dirty = np.flatnonzero(states["changed"].to_numpy(zero_copy_only=False))
        else:
            at = find(news["vid"])
            value[at] = adopt(value[at], _numbers(news["value"]))
            dirty = at[value[at] != old[at]]
        edge_value = _numbers(edges["edge_value"]) if stateful else None
        new = value
        if len(dirty) and edges.num_rows:
            new = solve(Local(find(edges["src"]), find(edges["dst"]), edges["w"].to_numpy(), vid, states["n_copies"].to_numpy(), value.copy(), dirty, {c: states[c].to_numpy(zero_copy_only=False) for c in extra}, edge_value))
            if isinstance(new, tuple):
                new, edge_value = new
        # replicas agreed on what they were told: only what the solve itself changed is news to the others
        changed, heard = new != value, np.zeros(len(new), dtype=bool)
        if not first:
            heard[at] = True
        out = states.drop_columns(["value", "changed", "heard"]).append_column("value", _column(new, states.schema.field("value").type)).append_column("changed", pa.array(changed)).append_column("heard", pa.array(heard))
        if edge_value is None:
            return out
        kept = pa.table({"part": edges["part"], "src": edges["src"], "dst": edges["dst"], "w": edges["w"], "edge_value": pa.array(edge_value)})
        return pa.concat_tables([out, kept], promote_options="default")

    return run


def _news(program: Program, states: DataFrame, where: DataFrame) -> DataFrame:
    """(part, vid, value) for replicas that differ from what all replicas agree on."""
    up = states.where("n_copies >= 2") if program.whole else states.where("n_copies >= 2 and changed")
    per = up.groupBy("vid").agg(program.reconcile("value").alias("agreed"), F.collect_list(F.struct("part", "value")).alias("known"), F.max("changed").alias("any"))
    if program.whole:
        each = per.where("any").select("vid", "agreed", F.explode("known").alias("k")).where("not k.value <=> agreed")
        return each.select("k.part", "vid", F.col("agreed").alias("value"))
    has = F.exists("known", lambda k: (k["part"] == F.col("part")) & k["value"].eqNullSafe(F.col("agreed")))
    return per.hint("merge").join(where, "vid").withColumn("part", F.explode("parts")).where(~has).select("part", "vid", F.col("agreed").alias("value"))


def run_program(p: EdgePartitioning, program: Program, most_supersteps: int = 10_000, local: str = "arrow", weight: str | None = None, most_edges: int = 20_000_000) -> Outcome:
    """Repeats solve and reconcile until nothing changes. local: 'arrow' solves each part in one Python
    worker, 'sql' by joins inside parts (for parts that no worker holds; programs of a minimum only)."""
    spark, k = p.spark, max(1, p.k)
    scratch = Scratch(spark, f"engine-{program.name}")
    edges = place(p, weight)
    if program.edge_setup is not None:
        edges = edges.withColumn("edge_value", program.edge_setup.cast("double"))
    edges = scratch.table(edges.repartition(k, "part"), "part", k)
    by_vid = int(spark.conf.get("spark.sql.shuffle.partitions"))
    extra = [f.name for f in StructType.fromDDL(program.extra)] if program.extra else []
    names = ["part", "vid", "n_copies", *extra, "value", "changed", "heard"]
    # replicas from the stored edges: each part finds its own vertices, so only these are exchanged
    placed = EdgePartitioning(edges.select(*(F.col(c).alias(c) for c in ("src", "dst", "part"))), k)
    states = program.setup(placed.copies()).select(*names[:-3], F.col("value").cast(program.value_type).alias("value"), F.col("dirty").alias("changed"), F.lit(False).alias("heard")).repartition(k, "part")
    kinds = dict(states.dtypes)
    schema = ", ".join(f"{c} {kinds[c]}" for c in names)
    if program.edge_setup is not None:
        schema += ", src long, dst long, w double, edge_value double"
    where = None
    supersteps, moved, first = 0, [], True
    while supersteps <= most_supersteps:
        seen = Observation()
        if first:
            rows = states
        else:
            if where is None and not program.whole:
                shared = states.where("n_copies >= 2").groupBy("vid").agg(F.collect_list("part").alias("parts"))
                where = scratch.table(shared.repartition(by_vid, "vid"), "vid", by_vid)
            news = _news(program, states, where)
            # a row that is told to a replica is one without a mark of change; both sides of the union lie by part
            news = news.select("part", "vid", *(F.lit(None).cast(kinds[c]).alias(c) for c in ("n_copies", *extra)), "value", *(F.lit(None).cast("boolean").alias(c) for c in ("changed", "heard")))
            rows = states.select(*names).unionByName(news.repartition(k, "part"))
        if local == "arrow":
            solved = edges.groupBy("part").cogroup(rows.groupBy("part")).applyInArrow(_guarded(_arrow_solve(program, extra, most_edges, first), schema), schema)
        else:
            solved = _sql_solve(scratch, program, edges, rows, first)
        mine = F.col("vid").isNotNull()
        many = lambda c, name: F.count(F.when(mine & c, 1)).alias(name)
        solved = solved.observe(seen, many(F.col("changed"), "changed"), many(F.col("changed") & (F.col("n_copies") >= 2), "shared_changed"), many(F.col("heard"), "heard"))
        if local != "arrow":
            solved = solved.repartition(k, "part")
        stored = scratch.table(solved, "part", k, "states")
        if program.edge_setup is not None:
            edges = stored.where("vid is null").select(F.col("part").alias("part"), "src", "dst", "w", "edge_value")
        states = stored.where("vid is not null").select(*names) if program.edge_setup is not None else stored
        count = seen.get
        if moved:
            moved[-1] += count["heard"]
        if count["changed"]:
            supersteps += 1
        moved.append(count["shared_changed"])
        first = False
        if not count["shared_changed"] or program.done and program.done(count | {"superstep": supersteps}):
            break
    one = states.groupBy("vid").agg((F.max_by("value", "part") if program.whole else program.reconcile("value")).alias("value"))
    return Outcome(one, supersteps, moved, edges if program.edge_setup is not None else None, states)


def _guarded(solve, schema: str):
    names = [x.split()[0] for x in schema.split(", ")]

    def run(edges: pa.Table, rows: pa.Table) -> pa.Table:
        return solve(edges, rows).select(names)

    return run


def _sql_solve(scratch: Scratch, program: Program, edges: DataFrame, rows: DataFrame, first: bool) -> DataFrame:
    if program.relax is None or program.edge_setup is not None:
        raise ValueError("local='sql' takes programs of a minimum that say how a value passes an edge")
    half = edges.select("part", F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("vid"), F.col("src").alias("nbr")))).alias("h"), "w").select("part", "h.vid", "h.nbr", "w")
    better = lambda c: F.col(c).isNotNull() & (F.col("value").isNull() | (F.col(c) < F.col("value")))
    states = rows.where("changed is not null")
    now = states.withColumns({"dirty": F.col("changed"), "changed": F.lit(False), "heard": F.lit(False)})
    if not first:
        news = rows.where("changed is null").select("part", "vid", F.col("value").alias("news"))
        now = states.join(news, ["part", "vid"], "left").withColumns({"dirty": better("news"), "heard": F.col("news").isNotNull(), "changed": F.lit(False)})
        now = now.withColumn("value", F.when(F.col("dirty"), F.col("news")).otherwise(F.col("value"))).select(*states.columns, "dirty")
    now = scratch.store(now, "inner")
    while True:
        told = now.where("dirty").join(half, ["part", "vid"]).groupBy("part", F.col("nbr").alias("vid")).agg(F.min(program.relax(F.col("value"), F.col("w"))).alias("told"))
        rest = [c for c in now.columns if c not in ("part", "vid", "value", "changed", "dirty")]
        now = now.join(told, ["part", "vid"], "left").select("part", "vid", *rest, F.when(better("told"), F.col("told")).otherwise(F.col("value")).alias("value"), (F.col("changed") | better("told")).alias("changed"), better("told").alias("dirty"))
        now = scratch.store(now, "inner")
        if not now.where("dirty").limit(1).count():
            return now.select(*states.columns)


def spread_parts(p: EdgePartitioning, workers: int) -> DataFrame:
    """(part, n_edges, worker): parts to workers, largest first, dealt back and forth over the workers."""
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("n_edges"), "part")) - 1  # over k rows
    turn, at = F.floor(F.col("r") / workers), F.pmod("r", F.lit(workers))
    worker = F.when(turn % 2 == 0, at).otherwise(workers - 1 - at).cast("int")
    return p.sizes().withColumn("r", rank).select("part", "n_edges", worker.alias("worker"))
