"""Driver queries of the graph engine and their DuckDB twins."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import functions as F

from . import catalog, experiments
from .functions import portable_hash_sql
from .model import EdgeGraph, EdgePartitioning
from .operators import annealed, baselines, growth, measures, programs, topology
from .plans import Scratch

K, SEED = 20, 0
QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql is not None:
            SQL[name or f.__name__] = sql
        return f

    return add


for _name in catalog.GRAPHS:
    query(catalog.SQL[_name], f"edges_{_name}" + "_top5" * (_name == "knn"))(lambda spark, d, f=catalog.GRAPHS[_name]: f(spark, d).edges)

_Q = f"e as ({catalog.SQL['copurchase_q']}), h as (select src a, dst b from e union all select dst, src from e), deg as (select a vid, count(*) degree from h group by a)"
_SP = f"e as ({catalog.SQL['supp_part']})"
_PART = f"p as (select src, dst, (({portable_hash_sql(SEED, 'src', 'dst')}) % {K})::int part from e)"
_REP = "r as (select distinct part, unnest([src, dst]) vid from p)"
_COPY = "c as (select part, vid, count(*) over (partition by vid) n_copies from r)"
_HASHED = f"with {_SP}, {_PART}, {_REP}, {_COPY}"
_COMPONENTS = "recursive {graph}, t(vid, c) using key (vid) as (select vid, vid c from (select distinct a vid from h) union select vid, min(c) c from (select h.b vid, t.c from t join h on h.a = t.vid join recurring.t r on r.vid = h.b where t.c < r.c) group by vid)"
_DISTANCE = "recursive {graph}, s as (select vid from deg order by {order}, vid limit {sources}), t(vid, d) using key (vid) as (select vid, 0 d from s union select h.b vid, min(t.d) + 1 d from t join h on h.a = t.vid left join recurring.t r on r.vid = h.b where r.vid is null or t.d + 1 < r.d group by h.b)"


def _q(spark, d, rule=catalog.copurchase_q) -> EdgeGraph:
    return EdgeGraph(Scratch(spark, "graph").store(rule(spark, d).edges))


def _hashed(spark, d) -> EdgePartitioning:
    return baselines.hash_edges(catalog.supp_part(spark, d), K, SEED)


# ------------------------------------------------------------ what graphs are like


def _profile_sql(graph: str) -> str:
    return f"""with e as ({catalog.SQL[graph]}), h as (select src a, dst b from e union all select dst, src from e), deg as (select a vid, count(*)::double degree from h group by a),
        tri as (select x.src v1, x.dst v2, y.dst v3 from e x join e y on x.dst = y.src join e z on z.src = x.src and z.dst = y.dst),
        tv as (select vid, count(*)::double t from (select unnest([v1, v2, v3]) vid from tri) group by vid),
        g as (select count(*) n, (sum(degree) / 2)::bigint m, coalesce(sum(t), 0) t3, sum(degree * (degree - 1) / 2) w, avg(case when degree >= 2 then coalesce(t, 0) / (degree * (degree - 1) / 2) end) l from deg left join tv using (vid))
        select n, m, round(case when w > 0 then t3 / w else 0 end, 9) transitivity, round(coalesce(l, 0), 9) mean_local,
            round(case when w - 2 * t3 / 3 > 0 then (t3 / 3) / (w - 2 * t3 / 3) else 0 end, 9) closed_share, round(2.0 * m / (n * (n - 1)), 12) random from g"""


for _name in ("copurchase_q", "copurchase_all", "shared_line", "shared_line_all", "activity_grid", "event_lattice"):
    query(_profile_sql(_name), f"graph_profile_{_name}")(lambda spark, d, f=catalog.GRAPHS[_name]: topology.profile(EdgeGraph(Scratch(spark, "graph").store(f(spark, d).edges))))


@query(f"with {_Q} select degree, count(*) n_vertices from deg group by degree")
def degree_histogram(spark, d, rule=catalog.copurchase_q):
    return rule(spark, d).degrees().groupBy("degree").agg(F.count(F.lit(1)).alias("n_vertices"))


@query(f"with {_Q}, tri as (select x.src v1, x.dst v2, y.dst v3 from e x join e y on x.dst = y.src join e z on z.src = x.src and z.dst = y.dst), tv as (select vid, count(*) t from (select unnest([v1, v2, v3]) vid from tri) group by vid) select vid, coalesce(t, 0) triangles from deg left join tv using (vid)")
def triangles_per_vertex(spark, d, rule=catalog.copurchase_q):
    return topology.triangles(_q(spark, d, rule))


@query(f"with {_COMPONENTS.format(graph=_Q)}, big as (select c from t group by c order by count(*) desc, c limit 1) select vid from t join big using (c)")
def giant_component_vertices(spark, d, rule=catalog.copurchase_q):
    return topology.giant_component(_q(spark, d, rule)).vertices()


@query(f"with {_SP}, deg as (select vid, count(*) g from (select unnest([src, dst]) vid from e) group by vid) select (sum(g) / 2)::bigint m, sum(g * (g - 1) / 2)::bigint line_edges, round(sum(g * (g - 1) / 2) / (sum(g) / 2), 9) line_growth from deg")
def line_graph_growth(spark, d):
    return topology.line_growth(catalog.supp_part(spark, d))


@query(f"with e as ({catalog.SQL['reply_chain']}), h as (select src a, src, dst from e union all select dst, src, dst from e) select x.src a_src, x.dst a_dst, y.src b_src, y.dst b_dst from h x join h y on x.a = y.a and (x.src, x.dst) < (y.src, y.dst)")
def line_graph_edges(spark, d):
    return topology.line_graph(catalog.reply_chain(spark, d))


_STEP = "using key (vid) as (select vid, 0 d from {start} union select h.b vid, min({t}.d) + 1 d from {t} join h on h.a = {t}.vid left join recurring.{t} r on r.vid = h.b where r.vid is null or {t}.d + 1 < r.d group by h.b)"


def _diameter_sql(graph: str) -> str:
    first, second = _STEP.format(start="s", t="t"), _STEP.format(start="f", t="u")
    return f"""with recursive e as ({catalog.SQL[graph]}), h as (select src a, dst b from e union all select dst, src from e), s as (select min(a) vid from h),
        t(vid, d) {first}, f as (select min(vid) vid from t where d = (select max(d) from t)), u(vid, d) {second}
        select greatest((select max(d) from t), (select max(d) from u))::bigint diameter"""


for _name in ("copurchase_q", "cust_supp", "supp_part", "shared_line", "hierarchy"):

    @query(_diameter_sql(_name), f"diameter_{_name}")
    def _diameter(spark, d, f=catalog.GRAPHS[_name]):
        """Q13: the lower bound of two searches, from the smallest vertex and from the farthest one of it."""
        return spark.createDataFrame([(topology.diameter(_q(spark, d, f)),)], "diameter long")


# ------------------------------------------------------------ partitionings and measures


@query(f"with {_SP} select row_number() over (order by {portable_hash_sql(SEED, 'src', 'dst')}, src, dst) - 1 as part, src, dst from e order by part limit {K}")
def seed_edges_k20(spark, d):
    rows = growth.pick_seeds(catalog.supp_part(spark, d), K, SEED)
    return spark.createDataFrame([(i, *e) for i, e in enumerate(rows)], "part long, src long, dst long")


@query(f"with {_SP}, v as (select distinct unnest([src, dst]) vid from e), s as (select vid from v order by {portable_hash_sql(SEED, 'vid')}, vid limit {K}) select distinct (min({{'h': {portable_hash_sql(SEED, 'src', 'dst')}, 'src': src, 'dst': dst}})).src src, (min({{'h': {portable_hash_sql(SEED, 'src', 'dst')}, 'src': src, 'dst': dst}})).dst dst from s join e on vid = src or vid = dst group by vid")
def seed_vertices_k20(spark, d):
    return spark.createDataFrame(growth.pick_seeds(catalog.supp_part(spark, d), K, SEED, "vertex"), "src long, dst long")


@query(f"with {_SP}, {_PART} select * from p")
def hash_edge_parts(spark, d):
    return _hashed(spark, d).assigned


@query(f"with {_SP} select src, dst, ((({portable_hash_sql(SEED, 'src')}) % 4) * 5 + ({portable_hash_sql(SEED, 'dst')}) % 5)::int part from e")
def grid_edge_parts(spark, d):
    return baselines.grid_hash_edges(catalog.supp_part(spark, d), K, SEED).assigned


@query(f"{_HASHED} select part, vid from r")
def hash_replicas(spark, d):
    return _hashed(spark, d).replicas()


@query(f"{_HASHED} select part, vid, n_copies::int n_copies from c where n_copies >= 2")
def hash_shared_vertices(spark, d):
    return _hashed(spark, d).shared()


@query(f"{_HASHED} select k.part::int part, coalesce(a.n, 0) n_edges, coalesce(b.n, 0) n_vertices from range({K}) k(part) left join (select part, count(*) n from p group by part) a using (part) left join (select part, count(*) n from r group by part) b using (part)")
def hash_sizes(spark, d):
    return _hashed(spark, d).sizes()


@query(f"{_HASHED}, s as (select k.part, coalesce(a.n, 0) n, coalesce(b.n, 0) v from range({K}) k(part) left join (select part, count(*) n from p group by part) a using (part) left join (select part, count(*) n from r group by part) b using (part)) select {K} k, sum(n)::bigint m, round(max(n) * {K}.0 / sum(n), 9) largest_norm, round((select sqrt(avg(pow(x.n * {K}.0 / (select sum(n) from s) - 1, 2))) from s x), 9) nstdev, max(n + v) max_size_ev from s")
def hash_balance(spark, d):
    return measures.balance(_hashed(spark, d)).withColumns({c: F.round(c, 9) for c in ("largest_norm", "nstdev")})


@query(f"{_HASHED}, n as (select vid, count(*) n from r group by vid) select sum(n) filter (n >= 2)::bigint messages, count(*) filter (n >= 2) shared, round(sum(n) / count(*), 9) replication from n")
def hash_messages(spark, d):
    return measures.messages(_hashed(spark, d)).withColumn("replication", F.round("replication", 9))


@query("with " + _COMPONENTS.format(graph=f"e0 as ({catalog.SQL['activity_grid']}), p as (select src, dst, (({portable_hash_sql(SEED, 'src', 'dst')}) % {K})::int part from e0), h as (select part * 1000000000000 + src a, part * 1000000000000 + dst b from p union all select part * 1000000000000 + dst, part * 1000000000000 + src from p)").replace("select distinct a vid", "select distinct a vid") + f" select 100.0 * count(*) filter (n > 1) / {K} disconnected_pct from (select c // 1000000000000 part, count(distinct c) n from t group by 1)")
def hash_disconnected(spark, d):
    return measures.disconnected_pct(baselines.hash_edges(catalog.activity_grid(spark, d), K, SEED))


@query(f"{_HASHED}, s as (select * from c where n_copies >= 2) select x.part a, y.part b, count(*) n_shared from s x join s y on x.vid = y.vid and x.part < y.part group by all")
def part_meta_graph(spark, d):
    return measures.part_graph(_hashed(spark, d))


@query(f"{_HASHED}, s as (select k.part::int part, coalesce(n, 0) n from range({K}) k(part) left join (select part, count(*) n from p group by part) using (part)), o as (select part, n, row_number() over (order by n desc, part) - 1 i from s) select part, n n_edges, (case when (i // 4) % 2 = 0 then i % 4 else 3 - i % 4 end)::int worker from o")
def parts_to_workers(spark, d):
    from .operators.engine import spread_parts

    return spread_parts(_hashed(spark, d), 4)


_VP = f"vp as (select vid, (({portable_hash_sql(SEED, 'vid')}) % {K})::int part from (select distinct unnest([src, dst]) vid from e))"


@query(f"with {_SP}, {_VP}, deg as (select vid, count(*) g from (select unnest([src, dst]) vid from e) group by vid) select k.part::int part, coalesce(count(vid), 0) n_vertices, coalesce(sum(g), 0)::bigint n_edge_ends from range({K}) k(part) left join vp on vp.part = k.part left join deg using (vid) group by k.part")
def vertex_hash_balance(spark, d):
    g = catalog.supp_part(spark, d)
    return baselines.vertex_balance(g, baselines.hash_vertices(g, K, SEED), K)


@query(f"with {_SP}, {_VP} select src, dst, a.part part_src, b.part part_dst from e join vp a on a.vid = src join vp b on b.vid = dst where a.part <> b.part")
def cut_edges(spark, d):
    g = catalog.supp_part(spark, d)
    return measures.cut_edges(g.edges, baselines.hash_vertices(g, K, SEED))


@query(f"with {_SP}, {_VP} select src, dst, case when ({portable_hash_sql(SEED, 'src', 'dst')}) % 2 = 0 then a.part else b.part end part from e join vp a on a.vid = src join vp b on b.vid = dst")
def coin_conversion(spark, d):
    g = catalog.supp_part(spark, d)
    return baselines.edges_from_vertices(g, baselines.hash_vertices(g, K, SEED), K, SEED).assigned


# ------------------------------------------------------------ growth and swap: certificates


def _line_graph(spark, d, rule=catalog.shared_line) -> EdgeGraph:
    return topology.giant_component(EdgeGraph(Scratch(spark, "graph").store(rule(spark, d).edges)))


_GIANT_M = f"with {_COMPONENTS.format(graph=f'e as ({catalog.SQL["shared_line"]}), h as (select src a, dst b from e union all select dst, src from e)')}, big as (select c from t group by c order by count(*) desc, c limit 1), ge as (select src, dst from e join t on t.vid = src join big using (c))"
_CERT = f"{_GIANT_M} select count(*) n_edges, 0::bigint missing, 0::bigint twice, 0::bigint outside from ge"


def _certificate(g: EdgeGraph, p: EdgePartitioning):
    per = p.assigned.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"), F.min("part").alias("least"), F.max("part").alias("most"))
    both = g.edges.join(per, ["src", "dst"], "full")
    return both.agg(
        F.count(F.lit(1)).alias("n_edges"), F.count(F.when(F.col("n").isNull(), 1)).alias("missing"), F.count(F.when(F.col("n") > 1, 1)).alias("twice"), F.count(F.when((F.col("least") < 0) | (F.col("most") >= p.k), 1)).alias("outside")
    )


@query(_CERT)
def growth_certificate(spark, d, rule=catalog.shared_line):
    g = _line_graph(spark, d, rule)
    return _certificate(g, growth.funded_growth(g, 4, SEED, rate=0.5))


@query(_CERT)
def growth_takeover_certificate(spark, d, rule=catalog.shared_line):
    g = _line_graph(spark, d, rule)
    return _certificate(g, growth.funded_growth(g, 4, SEED, rate=0.5, takeover=True))


@query(f"{_GIANT_M} select count(*) n_edges, 0::bigint differ from ge")
def growth_mirrored_equals_edge(spark, d, rule=catalog.shared_line):
    g = _line_graph(spark, d, rule)
    grow = inheritable_thread_target(spark)(lambda p: growth.funded_growth(g, 4, SEED, plan=p, rate=0.5).assigned)
    with ThreadPoolExecutor(2) as pool:  # rounds are short jobs one after the other, so the plans run beside each other
        a, b = pool.map(grow, ("edge", "mirrored"))
    both = a.join(b.withColumnRenamed("part", "other"), ["src", "dst"], "full")
    return both.agg(F.count(F.lit(1)).alias("n_edges"), F.count(F.when(~F.col("part").eqNullSafe(F.col("other")), 1)).alias("differ"))


@query(f"{_GIANT_M}, n as (select count(*) n from (select distinct unnest([src, dst]) from ge)) select p.part::int part, (n // 4 + (p.part < n % 4)::int)::bigint n_vertices from range(4) p(part), n")
def swap_certificate(spark, d, rule=catalog.shared_line):
    g = _line_graph(spark, d, rule)
    parts, _ = annealed.annealed_swap(g, 4, SEED)
    start, end = (measures.cut_edges(g.edges, p).count() for p in (annealed.start_parts(g, 4, SEED), parts))
    if end > start:
        raise RuntimeError(f"{end} edges are cut after swaps, {start} before")
    return parts.groupBy("part").agg(F.count(F.lit(1)).alias("n_vertices"))


# ------------------------------------------------------------ programs


def _distance_sql(graph: str, sources: int = 1) -> str:
    return f"with {_DISTANCE.format(graph=graph, order=portable_hash_sql(SEED, 'vid'), sources=sources)} select deg.vid, coalesce(t.d, -1)::int dist from deg left join t using (vid)"


@query(_distance_sql(_Q))
def distances_engine(spark, d, rule=catalog.copurchase_q):
    g = _q(spark, d, rule)
    out = programs.distances(baselines.sized_parts(g, 8, SEED), baselines.pick_source(g, SEED))
    return out.states.select("vid", F.coalesce(F.col("value"), F.lit(-1)).cast("int").alias("dist"))


@query(_distance_sql(_Q))
def distances_engine_sql_local(spark, d, rule=catalog.copurchase_q):
    g = _q(spark, d, rule)
    out = programs.distances(baselines.grid_hash_edges(g, 8, SEED), baselines.pick_source(g, SEED), local="sql")
    return out.states.select("vid", F.coalesce(F.col("value"), F.lit(-1)).cast("int").alias("dist"))


@query(_distance_sql(_Q))
def distances_vertex_rounds(spark, d, rule=catalog.copurchase_q):
    g = _q(spark, d, rule)
    return baselines.vertex_rounds_distance(g, baselines.pick_source(g, SEED))[0].na.fill(-1, ["dist"])


@query(_distance_sql(_Q, 3))
def distances_multi_source(spark, d, rule=catalog.copurchase_q):
    from .functions import portable_hash

    g = _q(spark, d, rule)
    sources = [r["vid"] for r in g.vertices().orderBy(portable_hash(SEED, F.col("vid")), "vid").limit(3).collect()]
    return programs.distances(baselines.sized_parts(g, 8, SEED), sources).states.select("vid", F.coalesce(F.col("value"), F.lit(-1)).cast("int").alias("dist"))


_WEIGHT = "(1 + (src * 7 + dst) % 5)::double"


@query(f"with recursive {_Q}, w as (select src a, dst b, {_WEIGHT} w from e union all select dst, src, {_WEIGHT} from e), s as (select vid from deg order by {portable_hash_sql(SEED, 'vid')}, vid limit 1), t(vid, d) using key (vid) as (select vid, 0::double d from s union select w.b vid, min(t.d + w.w) d from t join w on w.a = t.vid left join recurring.t r on r.vid = w.b where r.vid is null or t.d + w.w < r.d group by w.b) select deg.vid, coalesce(t.d, -1) dist from deg left join t using (vid)")
def distances_weighted(spark, d, rule=catalog.copurchase_q):
    g = _q(spark, d, rule)
    p = baselines.hash_edges(g, 8, SEED)
    weighted = EdgePartitioning(p.assigned.withColumn("cost", 1 + (F.col("src") * 7 + F.col("dst")) % 5), p.k)
    return programs.distances(weighted, baselines.pick_source(g, SEED), weight="cost").states.select("vid", F.coalesce("value", F.lit(-1.0)).alias("dist"))


_H = f"e as ({catalog.SQL['hierarchy']}), h as (select src a, dst b from e union all select dst, src from e)"


@query(f"with {_COMPONENTS.format(graph=_H)} select vid, c comp from t")
def components_engine(spark, d):
    g = EdgeGraph(Scratch(spark, "graph").store(catalog.hierarchy(spark, d).edges))
    return programs.components(baselines.hash_edges(g, 8, SEED)).states.select("vid", F.col("value").alias("comp"))


@query(f"with {_COMPONENTS.format(graph=_H)} select vid, c comp from t")
def components_vertex_rounds(spark, d):
    return baselines.vertex_rounds_components(catalog.hierarchy(spark, d))[0]


@query(f"with {_Q} select count(*) n_vertices, 0::bigint linked, 0::bigint addable from deg")
def mis_certificate(spark, d, rule=catalog.copurchase_q):
    g = _q(spark, d, rule)
    chosen, _ = programs.maximal_independent_set(baselines.sized_parts(g, 8, SEED), SEED)
    side = lambda c: chosen.select(F.col("vid").alias(c), F.col("in_set").alias(f"in_{c}"))
    e = g.edges.join(side("src"), "src").join(side("dst"), "dst")
    near = e.select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("in_dst").alias("near")), F.struct(F.col("dst").alias("vid"), F.col("in_src").alias("near")))).alias("x")).select("x.*")
    per = chosen.join(near.groupBy("vid").agg(F.max("near").alias("near")), "vid", "left")
    return per.agg(F.count(F.lit(1)).alias("n_vertices"), F.count(F.when(F.col("in_set") & F.col("near"), 1)).alias("linked"), F.count(F.when(~F.col("in_set") & ~F.col("near"), 1)).alias("addable"))


@query()
def betweenness_sampled(spark, d, rule=catalog.shared_line):
    g = _line_graph(spark, d, rule)
    return programs.betweenness(baselines.hash_edges(g, 4, SEED), [baselines.pick_source(g, s) for s in range(2)]).withColumn("score", F.round("score", 6))


@query(f"with {_DISTANCE.format(graph=_Q, order=portable_hash_sql(SEED, 'vid'), sources=1)} select max(d)::bigint vertex_rounds, true as not_negative from t")
def gain_nonnegative(spark, d, rule=catalog.copurchase_q):
    """Rounds of the vertex baseline (the source's eccentricity), and whether the engine takes no more."""
    g = _q(spark, d, rule)
    source = baselines.pick_source(g, SEED)
    _, rounds = baselines.vertex_rounds_distance(g, source)
    out = programs.distances(baselines.sized_parts(g, 4, SEED), source)
    return spark.createDataFrame([(rounds, measures.gain(out.supersteps, rounds) >= 0)], "vertex_rounds long, not_negative boolean")


@query(f"with e as ({catalog.SQL['activity_grid']}) select count(*) n_edges, 0::bigint triangles, 0::bigint loops_or_twice from e")
def rewire_certificate(spark, d):
    base = EdgeGraph(Scratch(spark, "graph").store(catalog.activity_grid(spark, d).edges))
    g = topology.rewire(base, 0.05, SEED, exact=True)
    moved, want = g.edges.join(base.edges, ["src", "dst"], "left_anti").count(), int(0.05 * base.edges.count())
    if moved != want:
        raise RuntimeError(f"{moved} edges were moved instead of {want}")
    bad = g.edges.count() - g.edges.where("src < dst").distinct().count()
    return g.edges.agg(F.count(F.lit(1)).alias("n_edges")).withColumn("triangles", F.lit(topology.triangle_list(g).count())).withColumn("loops_or_twice", F.lit(bad).cast("long"))


for _f in (growth_certificate, growth_takeover_certificate, growth_mirrored_equals_edge, swap_certificate, betweenness_sampled):
    _name = _f.__name__
    query(SQL[_name].replace(catalog.SQL["shared_line"], catalog.SQL["shared_line_all"]) if _name in SQL else None, f"{_name}_line_all")(lambda spark, d, f=_f: f(spark, d, catalog.shared_line_all))


#: the same over all orders: the twins above are of one quarter
for _f in (degree_histogram, triangles_per_vertex, giant_component_vertices, distances_engine, distances_engine_sql_local, distances_vertex_rounds, distances_multi_source, mis_certificate, gain_nonnegative):
    _name = _f.__name__
    query(SQL[_name].replace(catalog.SQL["copurchase_q"], catalog.SQL["copurchase_all"]), f"{_name}_all")(lambda spark, d, f=_f: f(spark, d, catalog.copurchase_all))


# ------------------------------------------------------------ sweeps


W2_FRACTIONS = (0.0, 0.01, 0.02, 0.05, 0.1, 0.2)
W1_GRAPHS = ("copurchase_q", "activity_grid", "shared_line", "shared_line_all")
W3_GRAPHS = ("copurchase_q", "cust_supp", "activity_grid", "shared_line", "shared_line_all")
SEEDS = range(5)


def _giant(g: EdgeGraph):
    """The edges of the giant component: they go to the driver anyway, so it is found there."""
    return experiments.giant_array(experiments.edge_array(g))


def _giants(spark, d, names) -> dict:
    """The giant components of whole graphs."""
    return {n: _giant(catalog.GRAPHS[n](spark, d)) for n in names}


def _rewired_grids(spark, d) -> dict:
    base = _giant(catalog.activity_grid(spark, d))
    g = EdgeGraph(Scratch(spark, "graph").store(experiments.frame_of(spark, base)))
    return {f"rewired {f}": _giant(topology.rewire(g, f, SEED, exact=True)) if f else base for f in W2_FRACTIONS}


def _rounded(runs):
    return measures.summarise(runs).withColumns({c: F.round(c, 6) for c in ("mean", "sd")})


@query()
def ksweep_summary(spark, d):
    return _rounded(experiments.sweep(spark, "ksweep", _giants(spark, d, W1_GRAPHS), ("growth", "takeover"), (2, 4, 8, 16, 32), SEEDS))


@query()
def diameter_sweep_summary(spark, d):
    return _rounded(experiments.sweep(spark, "diameter", _rewired_grids(spark, d), ("growth", "takeover"), (K,), SEEDS))


@query()
def compare_summary(spark, d):
    return _rounded(experiments.sweep(spark, "compare", _giants(spark, d, W3_GRAPHS), ("growth", "takeover", "swap", "hash"), (K,), SEEDS))


W5_GRAPHS = ("copurchase_q", "activity_grid")


@query()
def engine_vs_vertex_rounds(spark, d):
    """W5: steps, gain and seconds of the distance program on funded parts and of the vertex baseline."""
    rows = []
    for name in W5_GRAPHS:
        g = EdgeGraph(Scratch(spark, "graph").store(experiments.frame_of(spark, _giant(catalog.GRAPHS[name](spark, d)))))
        rows += [(name, *r) for r in experiments.engine_against_vertex_rounds(g, (2, 8), SEED)]
    return spark.createDataFrame(rows, "graph string, method string, k int, steps int, gain double, differ long, seconds double")


_SIZES = [(n, catalog.SQL[n]) for n in catalog.GRAPHS]


@query("with " + ", ".join(f"g{i} as ({q})" for i, (_, q) in enumerate(_SIZES)) + " " + " union all ".join(f"select '{n}' graph, (select count(*) from (select distinct unnest([src, dst]) from g{i})) n, (select count(*) from g{i}) m" for i, (n, _) in enumerate(_SIZES)))
def dataset_sizes(spark, d):
    """W6: vertices and edges of every graph of the catalog."""
    out = None
    for name, rule in catalog.GRAPHS.items():
        g = EdgeGraph(Scratch(spark, "graph").store(rule(spark, d).edges))
        row = g.edges.agg(F.lit(name).alias("graph"), F.count(F.lit(1)).alias("m")).crossJoin(g.vertices().agg(F.count(F.lit(1)).alias("n")))
        out = row if out is None else out.unionByName(row)
    return out.select("graph", "n", "m")


def flagship(spark, d):
    """Purchases of one quarter: giant component, four funded regions, distances, vertices by distance."""
    g = topology.giant_component(_q(spark, d))
    p = growth.funded_growth(g, 4, SEED, rate=0.5)
    found = programs.distances(p, baselines.pick_source(g, SEED))
    return found.states.groupBy(F.col("value").cast("int").alias("dist")).agg(F.count(F.lit(1)).alias("n_vertices"))
