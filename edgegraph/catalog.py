"""Graphs derived from the given tables. Each rule reads the few columns it needs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import portable_hash, vid
from .model import EdgeGraph
from .sources import load


def _together(rows: DataFrame, group: str, key: str, kind: str) -> EdgeGraph:
    """Keys that occur in one group, pairwise. Rows are dealt by group once, for the distinct and the join; pairs
    are made distinct once, as edges."""
    a = rows.select(group, F.col(key).alias("a")).repartition(group).distinct()
    pairs = a.join(a.select(group, F.col("a").alias("b")), group).where("a < b").select("a", "b")
    return EdgeGraph.from_pairs(pairs, vid(F.col("a"), kind), vid(F.col("b"), kind))


def copurchase(spark: SparkSession, sf_dir: str, since: str | None = None, until: str | None = None) -> EdgeGraph:
    """Parts in one order, of all orders or of those from since up to but not on until."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    if since is not None:
        orders = load(spark, sf_dir, "orders").where((F.col("o_orderdate") >= F.lit(since).cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit(until).cast("timestamp_ntz")))
        lines = lines.join(orders.select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey")
    return _together(lines, "l_orderkey", "l_partkey", "part")


def copurchase_q(spark, sf_dir):
    return copurchase(spark, sf_dir, "1997-01-01", "1997-04-01")


def copurchase_y(spark, sf_dir):
    return copurchase(spark, sf_dir, "1997-01-01", "1998-01-01")


def copurchase_all(spark, sf_dir):
    return copurchase(spark, sf_dir)


def _bought(spark, sf_dir):
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_suppkey")
    return orders.join(lines, "o_orderkey")


def cust_supp(spark, sf_dir):
    return EdgeGraph.from_pairs(_bought(spark, sf_dir), vid(F.col("o_custkey"), "customer"), vid(F.col("l_suppkey"), "supplier"))


def cust_part(spark, sf_dir):
    return EdgeGraph.from_pairs(_bought(spark, sf_dir), vid(F.col("o_custkey"), "customer"), vid(F.col("l_partkey"), "part"))


def supp_part(spark, sf_dir):
    lines = load(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey")
    return EdgeGraph.from_pairs(lines, vid(F.col("l_suppkey"), "supplier"), vid(F.col("l_partkey"), "part"))


def _seconds(ts):
    """Seconds since 1970 of a timestamp without zone, whatever the session's zone."""
    return F.timestamp_diff("SECOND", F.lit("1970-01-01").cast("timestamp_ntz"), ts)


def activity_grid(spark, sf_dir):
    """Cells (12-hour slot, user) with events; linked to the next slot and to the next user."""
    cells = load(spark, sf_dir, "events").select(F.floor(_seconds(F.col("ts")) / 43200).alias("slot"), "user_id").distinct()
    key = lambda s, u: vid(s * (1 << 24) + u, "cell")
    steps = cells.select(key(F.col("slot"), F.col("user_id")).alias("a"), F.explode(F.array(key(F.col("slot") + 1, F.col("user_id")), key(F.col("slot"), F.col("user_id") + 1))).alias("b"))
    own = cells.select(key(F.col("slot"), F.col("user_id")).alias("b"))
    return EdgeGraph.from_pairs(steps.join(own, "b", "left_semi"), "a", "b")


def _followers(e, key: str, range_rows: int):
    """(event_id, next): the next event of the same key, in order of time and id.

    Keys may hold any share of the table, so a window holds one key in one of about n / range_rows
    ranges of time; the last event of a range is followed by the first one of the key's next range.
    """
    n, first, last = e.agg(F.count(F.lit(1)), F.min(_seconds(F.col("ts"))), F.max(_seconds(F.col("ts")))).first()
    width = max(1, ((last or 0) - (first or 0) + 1) * range_rows // max(1, n))
    ranged = e.select(F.col(key).alias("key"), F.floor(_seconds(F.col("ts")) / width).alias("range"), "ts", "event_id")
    within = ranged.withColumn("next", F.lead("event_id").over(Window.partitionBy("key", "range").orderBy("ts", "event_id")))
    heads = ranged.groupBy("key", "range").agg(F.min(F.struct("ts", "event_id")).alias("head"))  # one row a key and range
    stitched = heads.select("key", "range", F.lead("head.event_id").over(Window.partitionBy("key").orderBy("range")).alias("further"))
    ends = within.where("next is null").join(stitched, ["key", "range"]).select("event_id", F.col("further").alias("next"))
    return within.where("next is not null").select("event_id", "next").union(ends.where("next is not null"))


def event_lattice(spark, sf_dir, range_rows: int = 1_000_000):
    """An event, the next one of its user and the next one of its type."""
    e = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    steps = _followers(e, "user_id", range_rows).union(_followers(e, "event_type", range_rows))
    return EdgeGraph.from_pairs(steps, vid(F.col("event_id"), "event"), vid(F.col("next"), "event"))


def _lines(spark, sf_dir, least: int):
    """(doc_id, line) with the first 128 bits of the SHA-256 of a line for its text, which is not exchanged."""
    lines = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= least)
    return lines.select("doc_id", F.unhex(F.substring(F.sha2("line", 256), 1, 32)).alias("line")).distinct()


def shared_line(spark, sf_dir, least: int = 20, most_docs: int = 50):
    """Documents that share a line of at least 20 characters found in 2 to 50 documents."""
    lines = _lines(spark, sf_dir, least)
    some = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).where(F.col("n").between(2, most_docs)).select("line")
    return _together(lines.join(some, "line"), "line", "doc_id", "document")


def shared_line_all(spark, sf_dir, least: int = 20, pairs_up_to: int = 50):
    """Documents that share a line of at least 20 characters, however many have it.

    Pairs of a line in up to pairs_up_to documents are linked; the documents of a more frequent line are
    all linked to the smallest of them, so they stay connected by n - 1 edges.
    """
    lines = _lines(spark, sf_dir, least)
    per = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first")).where("n > 1")
    few = _together(lines.join(per.where(F.col("n") <= pairs_up_to).select("line"), "line"), "line", "doc_id", "document")
    star = lines.join(per.where(F.col("n") > pairs_up_to), "line").select(vid(F.col("first"), "document").alias("a"), vid(F.col("doc_id"), "document").alias("b"))
    return EdgeGraph.from_pairs(few.edges.toDF("a", "b").union(star), "a", "b")


def page_link(spark, sf_dir):
    """Pages and the addresses that they link to."""
    links = load(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("url"))
    return EdgeGraph.from_pairs(links, vid(F.col("page_id"), "page"), vid(F.shiftright(portable_hash(0, F.col("url")), 4), "url"))


def hierarchy(spark, sf_dir):
    """Regions, nations, customers and orders by containment: a forest."""
    levels = [("nation", "n_regionkey", "region", "n_nationkey", "nation"), ("customer", "c_nationkey", "nation", "c_custkey", "customer"), ("orders", "o_custkey", "customer", "o_orderkey", "order")]
    pairs = [load(spark, sf_dir, t).select(vid(F.col(a), ka).alias("a"), vid(F.col(b), kb).alias("b")) for t, a, ka, b, kb in levels]
    return EdgeGraph.from_pairs(pairs[0].union(pairs[1]).union(pairs[2]), "a", "b")


def reply_chain(spark, sf_dir):
    """Turns of a conversation, one after the other."""
    t = load(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    key = lambda turn: vid(F.col("conv_id") * 1000 + turn, "turn")
    nxt = t.select("conv_id", (F.col("turn") + 1).alias("turn")).join(t, ["conv_id", "turn"], "left_semi")
    return EdgeGraph.from_pairs(nxt, key(F.col("turn") - 1), key(F.col("turn")))


def toy(spark, name: str, n: int) -> EdgeGraph:
    """A small graph of known measures: 'path', 'cycle', 'star' or 'clique' of n vertices, 'grid' of n rows and
    columns, or 'barbell', two cliques of n vertices joined by one edge."""
    i = F.col("id")
    later = lambda upto: F.explode(F.sequence(i + 1, upto))
    inner = spark.range(max(0, n - 1))
    if name == "path":
        pairs = inner.select(i.alias("a"), (i + 1).alias("b"))
    elif name == "cycle":
        pairs = spark.range(n).select(i.alias("a"), ((i + 1) % n).alias("b"))
    elif name == "star":
        pairs = inner.select(F.lit(0).cast("long").alias("a"), (i + 1).alias("b"))
    elif name == "clique":
        pairs = inner.select(i.alias("a"), later(F.lit(n - 1)).alias("b"))
    elif name == "grid":
        right = spark.range(n * n).where(i % n < n - 1).select(i.alias("a"), (i + 1).alias("b"))
        pairs = right.union(spark.range(n * (n - 1)).select(i, i + n))
    elif name == "barbell":
        one = inner.select(i.alias("a"), later(F.lit(n - 1)).alias("b"))
        pairs = one.union(one.select(F.col("a") + n, F.col("b") + n)).union(spark.range(1).select(i, i + n))
    else:
        raise ValueError(f"no toy graph {name}")
    return EdgeGraph.from_pairs(pairs, "a", "b")


def knn(spark, sf_dir, k: int = 5, block_rows: int = 2048):
    """Each vector and its k nearest by cosine, exactly: blocks of bounded size meet each other, and a vector
    keeps its k best of a block before what it found in all blocks is ranked."""
    v = load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    blocks = max(1, -(-v.count() // block_rows))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asked, stored = v.select("vec_id", "v", own.alias("i"), every.alias("j")), v.select("vec_id", "v", own.alias("j"), every.alias("i"))

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({"vec_id": pa.array([], pa.int64()), "other": pa.array([], pa.int64()), "cosine": pa.array([], pa.float64())})
        sides = []
        for t in (left, right):
            x = np.array(t["v"].to_pylist(), dtype=np.float64)
            sides += [t["vec_id"].to_numpy(), x, np.sqrt((x * x).sum(axis=1))]
        a, x, n, b, y, m = sides
        cosine = np.round(x @ y.T / (n[:, None] * m), 9)
        cosine[a[:, None] == b] = -np.inf
        order = np.lexsort((np.broadcast_to(b, cosine.shape), -cosine))[:, :k]
        best = np.take_along_axis(cosine, order, axis=1)
        row, at = np.nonzero(best > -np.inf)
        return pa.table({"vec_id": a[row], "other": b[order[row, at]], "cosine": best[row, at]})

    near = asked.groupBy("i", "j").cogroup(stored.groupBy("i", "j")).applyInArrow(meet, "vec_id long, other long, cosine double")
    best = Window.partitionBy("vec_id").orderBy(F.desc("cosine"), "other")
    top = near.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k)
    return EdgeGraph.from_pairs(top, vid(F.col("vec_id"), "vector"), vid(F.col("other"), "vector"))


GRAPHS = {f.__name__: f for f in (copurchase_q, copurchase_y, copurchase_all, cust_supp, supp_part, cust_part, activity_grid, event_lattice, shared_line, shared_line_all, page_link, hierarchy, reply_chain, knn)}

_C = lambda s, u: f"((({s}) * 16777216 + ({u})) * 16 + 11)"


def _sql_together(rows: str, kind: int) -> str:
    return f"with r as ({rows}) select distinct a.k * 16 + {kind} as src, b.k * 16 + {kind} as dst from r a join r b on a.g = b.g and a.k < b.k"


def _sql_pairs(rows: str) -> str:
    return f"select distinct least(a, b) as src, greatest(a, b) as dst from ({rows}) where a <> b"


def _sql_copurchase(since: str, until: str) -> str:
    return _sql_together(f"select distinct l_orderkey g, l_partkey k from lineitem join orders on l_orderkey = o_orderkey where o_orderdate >= '{since}' and o_orderdate < '{until}'", 4)


#: DuckDB twins of the rules above: queries for (src, dst).
SQL = {
    "copurchase_q": _sql_copurchase("1997-01-01", "1997-04-01"),
    "copurchase_y": _sql_copurchase("1997-01-01", "1998-01-01"),
    "copurchase_all": _sql_together("select distinct l_orderkey g, l_partkey k from lineitem", 4),
    "cust_supp": _sql_pairs("select o_custkey * 16 + 2 a, l_suppkey * 16 + 3 b from orders join lineitem on o_orderkey = l_orderkey"),
    "cust_part": _sql_pairs("select o_custkey * 16 + 2 a, l_partkey * 16 + 4 b from orders join lineitem on o_orderkey = l_orderkey"),
    "supp_part": _sql_pairs("select l_suppkey * 16 + 3 a, l_partkey * 16 + 4 b from lineitem"),
    "activity_grid": f"with c as (select distinct floor(epoch(ts) / 43200)::bigint s, user_id u from events) select {_C('c.s', 'c.u')} as src, {_C('d.s', 'd.u')} as dst from c join c d on (d.s = c.s + 1 and d.u = c.u) or (d.s = c.s and d.u = c.u + 1)",
    "event_lattice": _sql_pairs("select event_id * 16 + 6 a, x * 16 + 6 b from (select event_id, unnest([lead(event_id) over (partition by user_id order by ts, event_id), lead(event_id) over (partition by event_type order by ts, event_id)]) x from events) where x is not null"),
    "shared_line": "with l as (select distinct doc_id, trim(x) line from (select doc_id, unnest(string_split(text, chr(10))) x from documents) where length(trim(x)) >= 20), s as (select line from l group by line having count(*) between 2 and 50) select distinct a.doc_id * 16 + 7 as src, b.doc_id * 16 + 7 as dst from l a join s using (line) join l b on a.line = b.line and a.doc_id < b.doc_id",
    "shared_line_all": "with l as (select distinct doc_id, trim(x) line from (select doc_id, unnest(string_split(text, chr(10))) x from documents) where length(trim(x)) >= 20), s as (select line, count(*) n, min(doc_id) f from l group by line having count(*) > 1) select distinct a.doc_id * 16 + 7 as src, b.doc_id * 16 + 7 as dst from l a join s using (line) join l b on a.line = b.line and a.doc_id < b.doc_id where s.n <= 50 or a.doc_id = s.f",
    "page_link": _sql_pairs("select page_id * 16 + 8 a, (('0x' || substr(md5('0|' || u), 1, 15))::bigint >> 4) * 16 + 9 b from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) u from pages)"),
    "hierarchy": _sql_pairs("select n_regionkey::bigint * 16 a, n_nationkey::bigint * 16 + 1 b from nation union all select c_nationkey::bigint * 16 + 1, c_custkey * 16 + 2 from customer union all select o_custkey * 16 + 2, o_orderkey * 16 + 5 from orders"),
    "reply_chain": "with t as (select distinct conv_id c, turn t from conversations) select (a.c * 1000 + a.t) * 16 + 10 as src, (b.c * 1000 + b.t) * 16 + 10 as dst from t a join t b on a.c = b.c and b.t = a.t + 1",
    "knn": _sql_pairs("select vec_id * 16 + 12 a, other * 16 + 12 b from (select x.vec_id, y.vec_id other, row_number() over (partition by x.vec_id order by round(list_cosine_similarity(x.embedding::double[], y.embedding::double[]), 9) desc, y.vec_id) r from embeddings x join embeddings y on x.vec_id <> y.vec_id) where r <= 5"),
}
