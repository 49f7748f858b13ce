"""Cost and balance measures of partitionings, and summaries of runs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import EdgePartitioning


def balance(p: EdgePartitioning) -> DataFrame:
    """One row: k, m, largest_norm, nstdev, max_size_ev. Sizes are in units of m / k; 0 edges give nulls."""
    share = F.col("n_edges") * F.lit(p.k) / F.sum("n_edges").over(_all())
    rows = p.sizes().withColumn("share", share)
    return rows.agg(
        F.lit(p.k).alias("k"), F.sum("n_edges").alias("m"), F.max("share").alias("largest_norm"), F.sqrt(F.avg(F.pow(F.col("share") - 1, 2))).alias("nstdev"), F.max(F.col("n_edges") + F.col("n_vertices")).alias("max_size_ev")
    )


def _all():
    from pyspark.sql import Window

    return Window.partitionBy(F.lit(0))  # over k rows


def messages(p: EdgePartitioning) -> DataFrame:
    """One row: messages (copies of the vertices that stand in several parts), shared vertices, replication."""
    per = p.replicas().groupBy("vid").agg(F.count(F.lit(1)).alias("n"))
    return per.agg(
        F.coalesce(F.sum(F.when(F.col("n") >= 2, F.col("n"))), F.lit(0)).alias("messages"), F.count(F.when(F.col("n") >= 2, 1)).alias("shared"), (F.sum("n") / F.count(F.lit(1))).alias("replication")
    )


def local_components(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The vertices of some edges and, for each, the smallest vertex of its component."""
    ids, at = np.unique(np.concatenate((src, dst)), return_inverse=True)
    a, b = at[: len(src)], at[len(src) :]
    label = np.arange(len(ids))
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        while True:  # shortcuts
            short = new[new]
            if (short == new).all():
                break
            new = short
        if (new == label).all():
            return ids, ids[label]
        label = new


def disconnected(p: EdgePartitioning) -> DataFrame:
    """(part, pieces): components of each part that has edges, by its own edges alone."""

    def run(table: pa.Table) -> pa.Table:
        _, label = local_components(table["src"].to_numpy(), table["dst"].to_numpy())
        return pa.table({"part": pa.array([table["part"][0].as_py()], pa.int32()), "pieces": pa.array([len(np.unique(label))], pa.int64())})

    return p.assigned.select("part", "src", "dst").groupBy("part").applyInArrow(run, "part int, pieces long")


def disconnected_pct(p: EdgePartitioning) -> DataFrame:
    """One row: the share of the k parts with more than one piece, in per cent."""
    return disconnected(p).agg((100.0 * F.count(F.when(F.col("pieces") > 1, 1)) / p.k).alias("disconnected_pct"))


def part_graph(p: EdgePartitioning) -> DataFrame:
    """(a, b, n_shared): parts that share vertices, with their number."""
    r = p.shared().select("vid", "part")
    return r.withColumnRenamed("part", "a").join(r.withColumnRenamed("part", "b"), "vid").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n_shared"))


def cut_edges(edges: DataFrame, vertex_parts: DataFrame) -> DataFrame:
    """(src, dst, part_src, part_dst) of edges whose ends have different parts. vertex_parts: vid, part."""
    return with_parts(edges, vertex_parts).where("part_src != part_dst")


def with_parts(edges: DataFrame, vertex_parts: DataFrame) -> DataFrame:
    side = lambda e: vertex_parts.select(F.col("vid").alias(e), F.col("part").alias(f"part_{e}"))
    return edges.select("src", "dst").join(side("src"), "src").join(side("dst"), "dst").select("src", "dst", "part_src", "part_dst")


def gain(supersteps: int, rounds: int) -> float:
    """The share of rounds that a partitioning spares; 0 where nothing has to be done."""
    return 1.0 - supersteps / rounds if rounds else 0.0


def summarise(runs: DataFrame) -> DataFrame:
    """Mean and standard deviation over samples of (workload, graph, method, k, metric)."""
    by = ["workload", "graph", "method", "k", "metric"]
    return runs.groupBy(*by).agg(F.count(F.lit(1)).alias("samples"), F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd"))
