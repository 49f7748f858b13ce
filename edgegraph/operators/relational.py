"""Relational operators that graph users need around the engine, as queries on the given tables."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from .. import catalog
from ..plans import Scratch
from ..sources import load, load_partitioning, read_edges, save_partitioning, write_edges
from . import baselines

QUERIES: dict = {}
SQL: dict[str, str] = {}


def _cents(c: str):
    """Money as whole hundredths: sums are exact in any engine and order."""
    return F.round(F.col(c) * 100).cast("long")



def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def _quarter(spark, d, a: str, b: str) -> DataFrame:
    day = lambda x: F.lit(x).cast("timestamp_ntz")
    return load(spark, d, "orders").where((F.col("o_orderdate") >= day(a)) & (F.col("o_orderdate") < day(b)))


def interval_join(left: DataFrame, right: DataFrame, key: str, at: str, other_at: str, width: int) -> DataFrame:
    """Rows of one key whose times (in seconds) lie at most width apart, left no later than right.

    Times fall into cells of the width, so a row meets the right rows of its own and the next cell only.
    """
    a = left.withColumn("cell", F.explode(F.array(F.floor(F.col(at) / width), F.floor(F.col(at) / width) + 1)))
    b = right.withColumn("cell", F.floor(F.col(other_at) / width))
    return a.join(b, [key, "cell"]).where(F.col(other_at).between(F.col(at), F.col(at) + width)).drop("cell")


def asof_join(left: DataFrame, right: DataFrame, key: str, order: list[str], value: str) -> DataFrame:
    """left with the value of the last right row before it by order, of the same key: one sort of both."""
    both = left.withColumn("mine", F.lit(True)).unionByName(right.withColumn("mine", F.lit(False)), allowMissingColumns=True)
    before = Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn("found", F.last(F.when(~F.col("mine"), F.col(value)), ignorenulls=True).over(before)).where("mine").drop("mine")


@query("select l_orderkey, l_linenumber, round(l_extendedprice * 100)::bigint * (100 - round(l_discount * 100)::bigint) revenue from lineitem")
def op_scan_project(spark, d):
    return load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", (_cents("l_extendedprice") * (100 - _cents("l_discount"))).alias("revenue"))


@query("select o_orderkey, o_custkey from orders where o_orderdate >= '1997-01-01' and o_orderdate < '1997-04-01' and o_orderpriority in ('1-URGENT', '2-HIGH') and o_orderstatus like 'O%' and o_totalprice is not null")
def op_filter_pred(spark, d):
    rows = _quarter(spark, d, "1997-01-01", "1997-04-01")
    return rows.where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").like("O%") & F.col("o_totalprice").isNotNull()).select("o_orderkey", "o_custkey")


@query("select r_name, n_name, count(*) n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all")
def op_join_broadcast(spark, d):
    nation, region = load(spark, d, "nation"), load(spark, d, "region")  # 25 and 5 rows at any scale
    c = load(spark, d, "customer").select("c_nationkey").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


_REVENUE = "select o_orderstatus, sum(round(l_extendedprice * 100)::bigint)::bigint revenue, count(*) n from orders join lineitem on o_orderkey = l_orderkey group by all"


def _revenue(spark, d, hint: str) -> DataFrame:
    lines = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), _cents("l_extendedprice").alias("price"))
    rows = load(spark, d, "orders").select("o_orderkey", "o_orderstatus").hint(hint).join(lines, "o_orderkey")
    return rows.groupBy("o_orderstatus").agg(F.sum("price").alias("revenue"), F.count(F.lit(1)).alias("n"))


@query(_REVENUE)
def op_join_merge(spark, d):
    return _revenue(spark, d, "merge")


@query(_REVENUE)
def op_join_shuffle_hash(spark, d):
    return _revenue(spark, d, "shuffle_hash")


_E1, _E2 = catalog._sql_copurchase("1997-01-01", "1997-04-01"), catalog._sql_copurchase("1997-04-01", "1997-07-01")
_DEG = "(select vid, count(*) degree from (select unnest([src, dst]) vid from ({})) group by vid)"


def _two(spark, d):
    return catalog.copurchase(spark, d, "1997-01-01", "1997-04-01").edges, catalog.copurchase(spark, d, "1997-04-01", "1997-07-01").edges


@query(f"select p_partkey, coalesce(degree, 0) degree from part left join {_DEG.format(_E1)} on vid = p_partkey * 16 + 4")
def op_join_left(spark, d):
    deg = catalog.copurchase_q(spark, d).degrees().select(F.shiftright("vid", 4).alias("p_partkey"), "degree")
    return load(spark, d, "part").select("p_partkey").join(deg, "p_partkey", "left").na.fill(0, ["degree"])


@query(f"select coalesce(a.vid, b.vid) vid, coalesce(a.degree, 0) first_q, coalesce(b.degree, 0) second_q from {_DEG.format(_E1)} a full join {_DEG.format(_E2)} b on a.vid = b.vid")
def op_join_full(spark, d):
    a, b = (catalog.EdgeGraph(e).degrees() for e in _two(spark, d))
    return a.withColumnRenamed("degree", "first_q").join(b.withColumnRenamed("degree", "second_q"), "vid", "full").na.fill(0, ["first_q", "second_q"])


@query("select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderdate >= '1997-01-01' and o_orderdate < '1997-04-01')")
def op_join_semi(spark, d):
    return load(spark, d, "customer").select("c_custkey").join(_quarter(spark, d, "1997-01-01", "1997-04-01").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi")


@query("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_orderdate >= '1997-01-01' and o_orderdate < '1997-04-01')")
def op_join_anti(spark, d):
    return load(spark, d, "customer").select("c_custkey").join(_quarter(spark, d, "1997-01-01", "1997-04-01").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query(f"with h as (select src v, dst u from ({_E1}) union all select dst, src from ({_E1})) select x.v vid, count(*) wedges from h x join h y on x.v = y.v and x.u < y.u group by x.v")
def op_join_theta(spark, d):
    h = catalog.copurchase_q(spark, d).half_edges().select("vid", "nbr")
    return h.join(h.withColumnRenamed("nbr", "other"), "vid").where("nbr < other").groupBy("vid").agg(F.count(F.lit(1)).alias("wedges"))


@query("select n_name, r_name from nation join region on n_regionkey <> r_regionkey")
def op_join_cross(spark, d):
    region = load(spark, d, "region")  # 5 rows at any scale
    return load(spark, d, "nation").join(F.broadcast(region), F.col("n_regionkey") != F.col("r_regionkey")).select("n_name", "r_name")


@query("select a.event_id, b.event_id other from events a join events b on a.user_id = b.user_id and a.event_id <> b.event_id and floor(epoch(b.ts))::bigint between floor(epoch(a.ts))::bigint and floor(epoch(a.ts))::bigint + 1800")
def op_join_interval(spark, d):
    e = load(spark, d, "events").select("event_id", "user_id", catalog._seconds(F.col("ts")).alias("at"))
    return interval_join(e, e.select(F.col("event_id").alias("other"), "user_id", F.col("at").alias("other_at")), "user_id", "at", "other_at", 1800).where("event_id != other").select("event_id", "other")


@query("select event_id, coalesce(click, -1) click from (select event_id, event_type, last(case when event_type = 'click' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) click from events where event_type in ('click', 'purchase')) where event_type = 'purchase'")
def op_join_asof(spark, d):
    e = load(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    buys, clicks = e.where("event_type = 'purchase'").drop("event_type"), e.where("event_type = 'click'").select("event_id", "user_id", "ts", F.col("event_id").alias("click"))
    return asof_join(buys, clicks, "user_id", ["ts", "event_id"], "click").select("event_id", F.coalesce("found", F.lit(-1)).alias("click"))


@query(f"with a as ({_E1}), b as ({_E2}) select 'union' op, count(*) n from (select * from a union select * from b) union all select 'union all', count(*) from (select * from a union all select * from b) union all select 'intersect', count(*) from (select * from a intersect select * from b) union all select 'except', count(*) from (select * from a except select * from b) union all select 'except all', count(*) from (select * from a except all select * from b)")
def op_setops(spark, d):
    a, b = _two(spark, d)
    named = {"union": a.union(b).distinct(), "union all": a.union(b), "intersect": a.intersect(b), "except": a.subtract(b), "except all": a.exceptAll(b)}
    out = None
    for name, rows in named.items():
        one = rows.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("op"), "n")
        out = one if out is None else out.union(one)
    return out


@query(f"select * from {_DEG.format(_E1)}")
def op_agg_hash(spark, d):
    return catalog.copurchase_q(spark, d).degrees()


@query("select l_partkey, count(distinct l_suppkey) suppliers from lineitem group by all")
def op_agg_distinct(spark, d):
    return load(spark, d, "lineitem").groupBy("l_partkey").agg(F.count_distinct("l_suppkey").alias("suppliers"))


@query()
def op_agg_approx(spark, d):
    return load(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", [0.5, 0.9]).alias("quantity"))


@query(f"select quantile_cont(degree, 0.5) median, quantile_cont(degree, 0.9) p90 from {_DEG.format(_E1)}")
def op_agg_percentile(spark, d):
    return catalog.copurchase_q(spark, d).degrees().agg(F.percentile("degree", 0.5).alias("median"), F.percentile("degree", 0.9).alias("p90"))


_G = "select l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::bigint g, sum(round(l_extendedprice * 100)::bigint)::bigint revenue from lineitem group by "


def _flags(spark, d):
    return load(spark, d, "lineitem").select("l_returnflag", "l_linestatus", _cents("l_extendedprice").alias("price"))


def _by(groups) -> DataFrame:
    return groups.agg(F.grouping_id().cast("long").alias("g"), F.sum("price").alias("revenue"))


@query(_G + "grouping sets ((l_returnflag), (l_linestatus))")
def op_grouping_sets(spark, d):
    return _by(_flags(spark, d).groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus")).select("l_returnflag", "l_linestatus", "g", "revenue")


@query(_G + "rollup (l_returnflag, l_linestatus)")
def op_rollup(spark, d):
    return _by(_flags(spark, d).rollup("l_returnflag", "l_linestatus"))


@query(_G + "cube (l_returnflag, l_linestatus)")
def op_cube(spark, d):
    return _by(_flags(spark, d).cube("l_returnflag", "l_linestatus"))


_KINDS = ("click", "view", "purchase", "signup", "error")


@query("select user_id, " + ", ".join(f"count(*) filter (event_type = '{k}') as \"{k}\"" for k in _KINDS) + " from events group by user_id")
def op_pivot(spark, d):
    return load(spark, d, "events").groupBy("user_id").pivot("event_type", list(_KINDS)).agg(F.count(F.lit(1))).na.fill(0)


@query(f"select vid, degree, rank() over (order by degree desc) r, dense_rank() over (order by degree desc) dr from {_DEG.format(_E1)}")
def op_window_rank(spark, d):
    """Ranks without one task that sorts all vertices: ranks of the distinct degrees, joined back."""
    deg = catalog.copurchase_q(spark, d).degrees()
    per = deg.groupBy("degree").agg(F.count(F.lit(1)).alias("n"))  # as many rows as distinct degrees
    w = Window.orderBy(F.desc("degree"))
    before = F.coalesce(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return deg.join(per.select("degree", (before + 1).alias("r"), F.row_number().over(w).cast("long").alias("dr")), "degree").select("vid", "degree", "r", "dr")


@query("select event_id, coalesce(lag(event_id) over w, -1) as before, coalesce(lead(event_id) over w, -1) as after, ntile(4) over w as q from events window w as (partition by user_id order by ts, event_id)")
def op_window_analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 1, -1).over(w).alias("after"), F.ntile(4).over(w).cast("long").alias("q"))


@query("with s as (select l_suppkey, l_partkey, l_orderkey, l_linenumber, l_quantity::bigint q from lineitem) select l_orderkey, l_linenumber, sum(q) over (partition by l_suppkey order by l_orderkey, l_linenumber, l_partkey, q rows between 2 preceding and current row)::bigint three, sum(q) over (partition by l_suppkey order by l_orderkey range between 100 preceding and current row)::bigint near from s")
def op_window_frame(spark, d):
    s = load(spark, d, "lineitem").select("l_suppkey", "l_partkey", "l_orderkey", "l_linenumber", F.col("l_quantity").cast("long").alias("q"))
    w = Window.partitionBy("l_suppkey")
    return s.select("l_orderkey", "l_linenumber", F.sum("q").over(w.orderBy("l_orderkey", "l_linenumber", "l_partkey", "q").rowsBetween(-2, 0)).alias("three"), F.sum("q").over(w.orderBy("l_orderkey").rangeBetween(-100, 0)).alias("near"))


@query(f"select vid, degree from {_DEG.format(_E1)} order by degree desc, vid limit 20")
def op_topk_global(spark, d):
    return catalog.copurchase_q(spark, d).degrees().orderBy(F.desc("degree"), "vid").limit(20)


@query(f"with h as (select src v, dst u from ({_E1}) union all select dst, src from ({_E1})), g as {_DEG.format(_E1)} select v vid, u nbr, degree from (select v, u, degree, row_number() over (partition by v order by degree desc, u) r from h join g on g.vid = u) where r <= 3")
def op_topk_group(spark, d):
    """The three neighbours of the highest degree: first among salted parts of a hub, then over them."""
    g = catalog.copurchase_q(spark, d)
    rows = g.half_edges().select("vid", "nbr").join(g.degrees().withColumnRenamed("vid", "nbr"), "nbr").withColumn("salt", F.pmod(F.xxhash64("nbr"), F.lit(8)))
    top = lambda frame, *by: frame.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("degree"), "nbr"))).where("r <= 3").drop("r")
    return top(top(rows, "vid", "salt"), "vid").select("vid", "nbr", "degree")


@query("select o_orderkey, round(o_totalprice * 100)::bigint price from orders order by o_totalprice desc, o_orderkey limit 50")
def op_sort_limit(spark, d):
    return load(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(50).select("o_orderkey", _cents("o_totalprice").alias("price"))


@query("select doc_id, len(string_split(text, chr(10)))::bigint n_lines, length(trim(text))::bigint n_chars, lower(substr(text, 1, 5)) head from documents")
def op_fn_string(spark, d):
    return load(spark, d, "documents").select("doc_id", F.size(F.split("text", "\n")).cast("long").alias("n_lines"), F.length(F.trim("text")).cast("long").alias("n_chars"), F.lower(F.substring("text", 1, 5)).alias("head"))


@query("select floor(epoch(ts) / 43200)::bigint slot, year(ts)::bigint y, quarter(ts)::bigint q, count(*) n from events group by all")
def op_fn_date(spark, d):
    return load(spark, d, "events").groupBy(F.floor(catalog._seconds(F.col("ts")) / 43200).alias("slot"), F.year("ts").cast("long").alias("y"), F.quarter("ts").cast("long").alias("q")).agg(F.count(F.lit(1)).alias("n"))


@query(f"select floor(log2(degree))::bigint bin, count(*) n, max(degree % 7)::bigint rest, min(greatest(degree, 3))::bigint low from {_DEG.format(_E1)} group by all")
def op_fn_math(spark, d):
    deg = catalog.copurchase_q(spark, d).degrees()
    return deg.groupBy(F.floor(F.log2("degree")).alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.max(F.pmod("degree", F.lit(7))).alias("rest"), F.min(F.greatest("degree", F.lit(3))).alias("low"))


@query(f"with h as (select src v, dst u from ({_E1}) union all select dst, src from ({_E1})) select v vid, array_to_string(list_sort(list(u)), ',') nbrs, len(list_filter(list(u), lambda x: x > v))::bigint above from h group by v")
def op_fn_array(spark, d):
    rows = catalog.copurchase_q(spark, d).half_edges().groupBy("vid").agg(F.array_sort(F.collect_list("nbr")).alias("l"))
    return rows.select("vid", F.array_join(F.transform("l", lambda x: x.cast("string")), ",").alias("nbrs"), F.size(F.filter("l", lambda x: x > F.col("vid"))).cast("long").alias("above"))


@query("select user_id, event_type as kind, count(*) n from events group by all")
def op_fn_map(spark, d):
    per = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    maps = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("kind", "n"))


@query("select user_id, sum(cast(json_extract(props, '$.k') as bigint))::bigint k from events group by all")
def op_fn_json(spark, d):
    return load(spark, d, "events").groupBy("user_id").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"))


@query("select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) host, count(*) n from pages group by all")
def op_fn_url(spark, d):
    return load(spark, d, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count(F.lit(1)).alias("n"))


@query("select p_partkey from part where exists (select 1 from lineitem where l_partkey = p_partkey and l_quantity >= 50)")
def op_subquery_exists(spark, d):
    return spark.sql("select p_partkey from {part} where exists (select 1 from {lines} where l_partkey = p_partkey and l_quantity >= 50)", part=load(spark, d, "part"), lines=load(spark, d, "lineitem"))


@query(f"with g as {_DEG.format(_E1)} select vid, degree from g where degree > (select avg(degree) from g)")
def op_subquery_scalar(spark, d):
    return spark.sql("select vid, degree from {degrees} where degree > (select avg(degree) from {degrees})", degrees=catalog.copurchase_q(spark, d).degrees())


@query("with recursive up(vid, above, depth) as (select c_custkey * 16 + 2, c_nationkey::bigint * 16 + 1, 1 from customer union all select up.vid, n_regionkey::bigint * 16, depth + 1 from up join nation on above = n_nationkey::bigint * 16 + 1) select vid, above, depth::bigint depth from up")
def op_cte_recursive(spark, d):
    """The recursion climbs from the nations, and customers take the steps of theirs: Spark ends a recursion of over
    1,000,000 rows with an error."""
    customers, nations = load(spark, d, "customer").select("c_custkey", "c_nationkey"), load(spark, d, "nation").select("n_nationkey", "n_regionkey")
    return spark.sql(
        """
        with recursive climb(start, above, depth) max recursion level 5 as (
            select cast(n_nationkey as bigint) * 16 + 1, cast(n_regionkey as bigint) * 16, 2 from {nations}
            union all select climb.start, cast(n_regionkey as bigint) * 16, depth + 1 from climb join {nations} on above = cast(n_nationkey as bigint) * 16 + 1),
        own as (select c_custkey * 16 + 2 as vid, cast(c_nationkey as bigint) * 16 + 1 as above from {customers})
        select vid, above, cast(1 as bigint) as depth from own
        union all select own.vid, climb.above, cast(climb.depth as bigint) from own join climb on own.above = climb.start""",
        customers=customers,
        nations=nations,
    )


@query(f"select src, dst, xor(src, dst)::bigint mixed from ({_E1})")
def op_udf_arrow(spark, d):
    def mix(batches):
        for b in batches:
            x, y = b["src"].to_numpy(), b["dst"].to_numpy()
            yield pa.RecordBatch.from_arrays([b["src"], b["dst"], pa.array(x ^ y)], ["src", "dst", "mixed"])

    return catalog.copurchase_q(spark, d).edges.mapInArrow(mix, "src long, dst long, mixed long")


@query("select user_id, bit_or(1::bigint << (event_id % 16)::int)::bigint bits from events group by all")
def op_udaf(spark, d):
    """An aggregate of one's own: the replicas' bit sets to the set of all. Equal states are merged before,
    so a group of any size brings 16 rows at most to its task."""

    @pandas_udf("long")
    def agreed(state: pd.Series) -> int:
        return int(np.bitwise_or.reduce(state.to_numpy()))

    states = load(spark, d, "events").select("user_id", F.expr("shiftleft(1L, cast(event_id % 16 as int))").alias("state")).distinct()
    return states.groupBy("user_id").agg(agreed("state").alias("bits"))


@query(f"select src vid, dst nbr from ({_E1}) union all select dst, src from ({_E1})")
def op_udtf(spark, d):
    """A table function of one's own over a table: the neighbours that an edge gives to its ends."""

    @udtf(returnType="vid bigint, nbr bigint")
    class Neighbours:
        def eval(self, src: int, dst: int):
            yield src, dst
            yield dst, src

    edges = catalog.copurchase_q(spark, d).edges
    return edges.lateralJoin(Neighbours(F.col("src").outer(), F.col("dst").outer())).select("vid", "nbr")


@query(f"select src, dst, ((src * 31 + dst) % 8)::bigint part from ({_E1})")
def op_sql_function(spark, d):
    name = f"edge_part_{uuid.uuid4().hex}"
    spark.sql(f"create temporary function {name}(a bigint, b bigint, k int) returns bigint return (a * 31 + b) % k")
    out = spark.sql(f"select src, dst, {name}(src, dst, 8) as part from {{edges}}", edges=catalog.copurchase_q(spark, d).edges)
    spark.sql(f"drop temporary function {name}")
    return out


@query(f"with p as (select count(*) n from ({_E1})) select f.x format, n from p, (select unnest(['parquet by part', 'csv', 'json', 'orc', 'parquet']) x) f")
def op_sink_roundtrip(spark, d):
    p = baselines.hash_edges(catalog.copurchase_q(spark, d), 4)
    folder = Scratch(spark, "sinks").path
    save_partitioning(p.assigned, f"{folder}/parts")
    out = load_partitioning(spark, f"{folder}/parts", [0, 1, 2, 3]).agg(F.count(F.lit(1)).alias("n")).select(F.lit("parquet by part").alias("format"), "n")
    for fmt in ("csv", "json", "orc", "parquet"):
        write_edges(p.assigned, f"{folder}/{fmt}", fmt)
        out = out.union(read_edges(spark, f"{folder}/{fmt}", "src long, dst long, part int", fmt).agg(F.count(F.lit(1)).alias("n")).select(F.lit(fmt), "n"))
    return out
