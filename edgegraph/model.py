"""Graphs and edge partitionings as DataFrames.

A graph is undirected and simple: edges are (src, dst) with src < dst, each pair once. A pair is its own
identity, so no surrogate id can collide. An edge partitioning gives every edge one part of 0..k-1; a
vertex stands in every part that has an edge of it, and is shared where there are several.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass
class EdgeGraph:
    edges: DataFrame  # src long, dst long

    @classmethod
    def from_pairs(cls, pairs: DataFrame, a: str | Column, b: str | Column) -> EdgeGraph:
        """Direction dropped, loops and rows with a null end left out, each pair once."""
        a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
        both = pairs.select(a.cast("long").alias("a"), b.cast("long").alias("b")).where("a != b")
        return cls(both.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct())

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def half_edges(self) -> DataFrame:
        """(vid, nbr, src, dst): every edge from both of its ends."""
        return self.edges.select("src", "dst", F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("vid"), F.col("src").alias("nbr")))).alias("h")).select("h.vid", "h.nbr", "src", "dst")

    def vertices(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()

    def degrees(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("degree"))

    def induced(self, vertices: DataFrame) -> EdgeGraph:
        """The edges whose ends are both among vertices (vid)."""
        keep = vertices.select("vid").distinct()
        e = self.edges.join(keep.withColumnRenamed("vid", "src"), "src", "left_semi").join(keep.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        return EdgeGraph(e.select("src", "dst"))

    def validate(self) -> None:
        """Raises unless the edges are canonical: no null, src < dst, each pair once."""
        bad = self.edges.where("src is null or dst is null or src >= dst").limit(1).count()
        twice = self.edges.groupBy("src", "dst").count().where("count > 1").limit(1).count()
        if bad or twice:
            raise ValueError("edges must be pairs src < dst, each once")


@dataclass
class EdgePartitioning:
    assigned: DataFrame  # src long, dst long, part int
    k: int
    history: list[dict] | None = None

    @property
    def spark(self) -> SparkSession:
        return self.assigned.sparkSession

    @property
    def rounds(self) -> int | None:
        """Rounds in which an edge was placed."""
        return None if self.history is None else sum(1 for h in self.history if h["changed"])

    def replicas(self) -> DataFrame:
        """(part, vid): the vertices of each part."""
        return self.assigned.select("part", F.explode(F.array("src", "dst")).alias("vid")).distinct()

    def copies(self) -> DataFrame:
        """(part, vid, n_copies): the vertices of each part, with the number of parts that have them."""
        r = self.replicas()
        return r.join(r.groupBy("vid").agg(F.count(F.lit(1)).cast("int").alias("n_copies")), "vid").select("part", "vid", "n_copies")

    def shared(self) -> DataFrame:
        return self.copies().where("n_copies >= 2")

    def sizes(self) -> DataFrame:
        """(part, n_edges, n_vertices) for all k parts, empty ones too."""
        e = self.assigned.groupBy("part").agg(F.count(F.lit(1)).alias("n_edges"))
        v = self.replicas().groupBy("part").agg(F.count(F.lit(1)).alias("n_vertices"))
        parts = self.spark.range(self.k).select(F.col("id").cast("int").alias("part"))
        zero = lambda c: F.coalesce(c, F.lit(0)).alias(c)
        return parts.join(e, "part", "left").join(v, "part", "left").select("part", zero("n_edges"), zero("n_vertices"))

    def validate(self, graph: EdgeGraph) -> None:
        """Raises unless each edge of graph has exactly one part of 0..k-1, and no other edge has one."""
        odd = self.assigned.where(F.col("part").isNull() | (F.col("part") < 0) | (F.col("part") >= self.k)).limit(1).count()
        twice = self.assigned.groupBy("src", "dst").count().where("count > 1").limit(1).count()
        pair = ["src", "dst"]
        missing = graph.edges.join(self.assigned, pair, "left_anti").limit(1).count()
        extra = self.assigned.join(graph.edges, pair, "left_anti").limit(1).count()
        if odd or twice or missing or extra:
            raise ValueError("not a partitioning of the edges of this graph")
