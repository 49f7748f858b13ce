"""What a graph is like: degrees, triangles, clustering, diameter, its giant component, its line graph,
and rewiring at constant size."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import portable_hash
from ..model import EdgeGraph, EdgePartitioning
from ..plans import Scratch
from .baselines import vertex_rounds_distance
from .programs import components, distances
from .triangles import triangle_stats


def triangle_list(g: EdgeGraph) -> DataFrame:
    """(a, b, c) once for each triangle: edges point to the end of higher degree, which bounds what a hub
    sends, and wedges are closed by a join."""
    d = g.degrees()
    e = g.edges.join(d.select(F.col("vid").alias("src"), F.col("degree").alias("ds")), "src").join(d.select(F.col("vid").alias("dst"), F.col("degree").alias("dd")), "dst")
    up = F.struct("ds", "src") < F.struct("dd", "dst")
    out = e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("b"))
    wedge = out.join(out.select("a", F.col("b").alias("c")), "a").where("b < c")
    return wedge.join(g.edges.select(F.col("src").alias("b"), F.col("dst").alias("c")), ["b", "c"]).select("a", "b", "c")


def triangles(g: EdgeGraph) -> DataFrame:
    """(vid, triangles) for every vertex, 0 where there are none."""
    return triangle_stats(g).select("vid", "triangles")


def profile(g: EdgeGraph) -> DataFrame:
    """One row: n, m, and clustering by three conventions beside that of a random graph of the size.

    transitivity: closed wedges over wedges; mean_local: the mean over vertices of degree 2 or more;
    closed_share: triangles over connected triples, each triangle counted once; random: 2 m / (n (n - 1)).
    """
    per = triangle_stats(g)
    wedges = F.col("degree") * (F.col("degree") - 1) / 2
    a = per.agg(F.count(F.lit(1)).alias("n"), (F.sum("degree") / 2).cast("long").alias("m"), F.sum("triangles").alias("t3"), F.sum(wedges).alias("w"), F.avg(F.when(F.col("degree") >= 2, F.col("triangles") / wedges)).alias("local"))
    t = F.col("t3") / 3
    safe = lambda x, y: F.when(y > 0, x / y).otherwise(F.lit(0.0))
    return a.select(
        "n", "m", F.round(safe(F.col("t3"), F.col("w")), 9).alias("transitivity"), F.round(F.coalesce("local", F.lit(0.0)), 9).alias("mean_local"), F.round(safe(t, F.col("w") - 2 * t), 9).alias("closed_share"),
        F.round(random_clustering(F.col("n"), F.col("m")), 12).alias("random"),
    )


def random_clustering(n, m):
    """The clustering expected of a random graph of n vertices and m edges (numbers or columns)."""
    return 2 * m / (n * (n - 1))


def _farthest(g: EdgeGraph, source: int, k: int) -> tuple[int, int]:
    """The largest distance from source, and the smallest vertex that far away."""
    from .baselines import sized_parts

    states = distances(sized_parts(g, k), source).states.where("value is not null")
    row = states.agg(F.min(F.struct(-F.col("value"), F.col("vid"))).alias("far")).first()["far"]
    return (0, source) if row is None else (int(-row[0]), row["vid"])


def diameter(g: EdgeGraph, source: int | None = None, mode: str = "sweep", k: int = 8) -> int:
    """The largest distance in the component of source (or of the smallest vertex): exact from all its
    vertices ('exact', small graphs), or a lower bound by two searches of the replica engine ('sweep')."""
    if source is None:
        source = g.vertices().agg(F.min("vid")).first()[0]
    if source is None:
        return 0
    if mode == "exact":
        inside = vertex_rounds_distance(g, source)[0].where("dist is not null")
        return max((vertex_rounds_distance(g, r["vid"])[1] for r in inside.toLocalIterator()), default=0)
    first, far = _farthest(g, source, k)
    return max(first, _farthest(g, far, k)[0])


def giant_component(g: EdgeGraph, k: int = 8, least: int | None = None) -> EdgeGraph:
    """The largest component (ties to the smaller vertex), or all of at least `least` vertices."""
    from .baselines import hash_edges

    scratch = Scratch(g.spark, "giant")
    edges = scratch.store(g.edges)
    label = components(hash_edges(EdgeGraph(edges), k)).states
    sizes = label.groupBy("value").agg(F.count(F.lit(1)).alias("n"))
    keep = sizes.where(F.col("n") >= least) if least is not None else sizes.orderBy(F.desc("n"), "value").limit(1)
    inside = label.join(F.broadcast(keep.select("value")), "value", "left_semi") if least is None else label.join(keep.select("value"), "value", "left_semi")
    # both ends of an edge lie in one component
    return EdgeGraph(scratch.store(edges.join(inside.select(F.col("vid").alias("src")), "src", "left_semi").select("src", "dst")))


def line_graph(g: EdgeGraph, most_edges: int = 50_000_000) -> DataFrame:
    """((a_src, a_dst), (b_src, b_dst)): edges that share an end. Refuses graphs whose line graph is large."""
    size = g.degrees().agg(F.sum(F.col("degree") * (F.col("degree") - 1) / 2)).first()[0] or 0
    if size > most_edges:
        raise ValueError(f"the line graph has {int(size)} edges, over {most_edges}")
    half = g.half_edges()
    a = half.select("vid", F.col("src").alias("a_src"), F.col("dst").alias("a_dst"))
    b = half.select("vid", F.col("src").alias("b_src"), F.col("dst").alias("b_dst"))
    return a.join(b, "vid").where("a_src < b_src or (a_src = b_src and a_dst < b_dst)").select("a_src", "a_dst", "b_src", "b_dst")


def line_growth(g: EdgeGraph) -> DataFrame:
    """One row: m, line_edges (wedges) and line_growth, their ratio."""
    a = g.degrees().agg((F.sum("degree") / 2).cast("long").alias("m"), F.sum(F.col("degree") * (F.col("degree") - 1) / 2).cast("long").alias("line_edges"))
    return a.select("m", "line_edges", F.round(F.col("line_edges") / F.col("m"), 9).alias("line_growth"))


def _numbered(rows: DataFrame, order: Column, keys: tuple[str, ...], scratch: Scratch) -> DataFrame:
    """rows with n = 0, 1, .. by a 60-bit hash; ranks come from counts of hash cells and a rank inside each."""
    rows = scratch.store(rows.withColumn("h", order).withColumn("cell", F.shiftright("h", 50)))  # 1024 cells
    count = rows.groupBy("cell").agg(F.count(F.lit(1)).alias("size"))
    before = F.sum("size").over(Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1))
    base = count.select("cell", F.coalesce(before, F.lit(0)).alias("before"))
    rank = F.row_number().over(Window.partitionBy("cell").orderBy("h", *keys)) - 1
    return scratch.store(rows.withColumn("rank", rank).join(F.broadcast(base), "cell").withColumn("n", F.col("before") + F.col("rank")).drop("h", "cell", "rank", "before"))


def _sides(g: EdgeGraph, a: str, b: str) -> DataFrame:
    """The edges that lie in a triangle."""
    return triangle_list(g).select(F.explode(F.array(F.array("a", "b"), F.array("b", "c"), F.array("a", "c"))).alias("e")).select(F.array_min("e").alias(a), F.array_max("e").alias(b)).distinct()


def rewire(g: EdgeGraph, fraction: float, seed: int = 0, most_turns: int = 20, exact: bool = False) -> EdgeGraph:
    """A graph of as many edges, of which floor(fraction * m) keep one end and get another, any vertex, by hash.

    Edges of triangles are not chosen. A proposal that would make a loop, a pair twice or a triangle is drawn
    anew in the next turn, so the number of triangles can only be what it was. Edges without a valid end after
    most_turns stay as they were, or with exact=True raise.
    """
    scratch = Scratch(g.spark, "rewire")
    edges = scratch.store(g.edges)
    vertices = _numbered(EdgeGraph(edges).vertices(), portable_hash(seed + 1, F.col("vid")), ("vid",), scratch)
    n, want = vertices.count(), int(fraction * edges.count())
    free = edges.join(_sides(EdgeGraph(edges), "src", "dst"), ["src", "dst"], "left_anti")
    chosen = _numbered(free, portable_hash(seed, F.col("src"), F.col("dst")), ("src", "dst"), scratch).where(F.col("n") < want).select("src", "dst")
    kept = F.when(F.pmod(portable_hash(seed + 3, F.col("src"), F.col("dst")), F.lit(2)) == 0, F.col("src")).otherwise(F.col("dst"))
    now, todo = edges, scratch.store(chosen)
    left = todo.count()
    short = want - left  # where fewer edges than that lie outside triangles
    for turn in range(most_turns):
        if not left:
            break
        drawn = F.pmod(portable_hash(seed + 5 + turn, F.col("src"), F.col("dst")), F.lit(n))
        moved = todo.select("src", "dst", kept.alias("keep"), drawn.alias("n")).join(vertices.withColumnRenamed("vid", "to"), "n").where("keep != to")
        moved = moved.select("src", "dst", F.least("keep", "to").alias("ns"), F.greatest("keep", "to").alias("nd"))
        # pairs of the graph as it was are not proposed, so a moved edge is one that was not there
        for taken in (edges, now):
            moved = moved.join(taken.select(F.col("src").alias("ns"), F.col("dst").alias("nd")), ["ns", "nd"], "left_anti")
        one = scratch.store(moved.groupBy("ns", "nd").agg(F.min(F.struct("src", "dst")).alias("old")).select("ns", "nd", "old.src", "old.dst"))
        while True:  # each pass drops a proposal or ends
            after = scratch.store(now.join(one.select("src", "dst"), ["src", "dst"], "left_anti").union(one.select("ns", "nd")))
            bad = scratch.store(one.join(_sides(EdgeGraph(after), "ns", "nd"), ["ns", "nd"], "left_semi"))
            if not bad.limit(1).count():
                break
            one = scratch.store(one.join(bad.select("ns", "nd"), ["ns", "nd"], "left_anti"))
        now, todo = after, scratch.store(todo.join(one.select("src", "dst"), ["src", "dst"], "left_anti"))
        left = todo.count()
    if exact and left + short:
        raise RuntimeError(f"{left + short} of {want} edges are not rewired after {most_turns} turns")
    return EdgeGraph(now)


def all_in_one(g: EdgeGraph) -> EdgePartitioning:
    return EdgePartitioning(g.edges.select("src", "dst", F.lit(0).alias("part")), 1)
