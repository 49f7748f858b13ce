"""Hand-computed examples, invariants and brute force for the graph engine."""

import random
from collections import deque

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from edgegraph.experiments import measure, supersteps_of
from edgegraph.functions import portable_hash, portable_hash_py, portable_hash_sql
from edgegraph.model import EdgeGraph, EdgePartitioning
from edgegraph.operators import annealed, baselines, growth, measures, programs, topology

TRIANGLES = [(0, 1, 0), (0, 2, 0), (1, 2, 0), (2, 3, 1), (2, 4, 1), (3, 4, 1)]
PATH = [(i, i + 1) for i in range(8)]
#: rows of (edges with parts, k, source): largest, nstdev, messages, rounds, supersteps, disconnected
EXAMPLES = {
    "two triangles": (TRIANGLES, 2, 0, (1.0, 0.0, 2, 2, 2, 0.0)),
    "path in halves": ([(a, b, int(a >= 4)) for a, b in PATH], 2, 0, (1.0, 0.0, 2, 8, 2, 0.0)),
    "path 6 and 2": ([(a, b, int(a >= 6)) for a, b in PATH], 2, 0, (1.5, 0.5, 2, 8, 2, 0.0)),
    "alternating path": ([(a, b, a % 2) for a, b in PATH], 2, 0, (1.0, 0.0, 14, 8, 8, 100.0)),
    "star": ([(0, i, (i - 1) // 2) for i in range(1, 7)], 3, 0, (1.0, 0.0, 3, 1, 1, 0.0)),
    "empty part": ([(0, 1, 0), (1, 2, 0), (2, 3, 0)], 2, 0, (2.0, 1.0, 0, 3, 1, 0.0)),
}


def parted(spark, rows, k):
    return EdgePartitioning(spark.createDataFrame(rows, "src long, dst long, part int").repartition(2), k)


def graph(spark, pairs):
    return EdgeGraph.from_pairs(spark.createDataFrame(pairs, "a long, b long"), "a", "b")


def random_pairs(n, m, seed):
    rng = random.Random(seed)
    return [(rng.randrange(n), rng.randrange(n)) for _ in range(m)]


def bfs(pairs, source):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    dist, queue = {source: 0}, deque([source])
    while queue:
        u = queue.popleft()
        for v in near[u]:
            if v not in dist:
                dist[v] = dist[u] + 1
                queue.append(v)
    return {v: dist.get(v) for v in near}


@pytest.mark.parametrize("name", EXAMPLES)
def test_examples_by_simulation(name):
    rows, k, source, (largest, nstdev, messages, rounds, steps, apart) = EXAMPLES[name]
    owner = {(a, b): p for a, b, p in rows}
    got = measure(sorted(owner), owner, k, 0, 0)
    assert (got["largest_norm"], got["nstdev"], got["messages"], got["disconnected_pct"]) == (largest, nstdev, messages, apart)
    assert supersteps_of(owner, source) == steps and supersteps_of({e: i for i, e in enumerate(owner)}, source) == rounds


@pytest.mark.parametrize("name", ["two triangles", "alternating path", "empty part"])
def test_examples_on_frames(spark, name):
    rows, k, source, (largest, nstdev, messages, rounds, steps, apart) = EXAMPLES[name]
    p = parted(spark, rows, k)
    b = measures.balance(p).first()
    assert (b.largest_norm, b.nstdev) == (largest, nstdev) and measures.messages(p).first().messages == messages
    assert measures.disconnected_pct(p).first()[0] == apart
    out = programs.distances(p, source)
    assert out.supersteps == steps
    assert {r.vid: r.value for r in out.states.collect()} == bfs([x[:2] for x in rows], source)


def test_hash_is_portable(spark):
    df = spark.range(200).select("id", portable_hash(17, F.col("id")).alias("h"))
    want = dict(duckdb.sql(f"select i, {portable_hash_sql(17, 'i')} from range(200) t(i)").fetchall())
    assert {r.id: r.h for r in df.collect()} == want and want[42] == portable_hash_py(17, 42) == 414709739408650216


def test_from_pairs_and_validate(spark):
    g = graph(spark, [(1, 2), (2, 1), (3, 3), (None, 4), (2, 5)])
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 5)]
    g.validate()
    p = baselines.hash_edges(g, 3)
    p.validate(g)
    with pytest.raises(ValueError):
        EdgePartitioning(p.assigned.limit(1), 3).validate(g)


def test_programs_match_brute_force(spark):
    pairs = random_pairs(60, 70, 1)
    g = graph(spark, pairs)
    p = baselines.hash_edges(g, 3)
    real = [(a, b) for a, b in pairs if a != b]
    source = baselines.pick_source(g)
    want = bfs(real, source)
    assert {r.vid: r.value for r in programs.distances(p, source).states.collect()} == want
    comp = {r.vid: r.value for r in programs.components(p).states.collect()}
    assert comp == {v: min(u for u, d in bfs(real, v).items() if d is not None) for v in want}
    chosen = {r.vid for r in programs.maximal_independent_set(p)[0].collect() if r.in_set}
    greedy = set()
    for v in sorted(want, key=lambda v: (portable_hash_py(0, v), v)):
        if not any((v, u) in real or (u, v) in real for u in greedy):
            greedy.add(v)
    assert chosen == greedy


@pytest.mark.parametrize("takeover", [False, True])
def test_growth_equals_its_simulation_in_both_plans(spark, takeover):
    pairs = random_pairs(40, 90, 2) + [(100, 101), (101, 102)]  # two components
    g = graph(spark, pairs)
    edges = sorted({(min(e), max(e)) for e in pairs if e[0] != e[1]})
    owner, history = growth.simulate(edges, growth.Rules(k=3, seed=5, rate=0.3, takeover=takeover))
    for plan in ("edge", "mirrored"):
        p = growth.funded_growth(g, 3, 5, plan=plan, rate=0.3, takeover=takeover)
        p.validate(g)
        assert {(r.src, r.dst): r.part for r in p.assigned.collect()} == owner
        assert [h["units"] for h in p.history] == [h["units"] for h in history]


def test_growth_conserves_money_and_degenerate_cases():
    edges = sorted({(min(e), max(e)) for e in random_pairs(50, 120, 3) if e[0] != e[1]})
    _, history = growth.simulate(edges, growth.Rules(k=4, unreached="fill"))
    start = growth.Rules(k=4).credits(len(edges)) * growth.CREDIT * 4
    paid = granted = 0
    for h in history:
        paid += h["changed"] * growth.CREDIT
        granted += h["granted"]
        assert h["units"] + paid == start + granted
    assert growth.simulate([], growth.Rules(k=3)) == ({}, [])
    assert growth.simulate([(1, 2)], growth.Rules(k=3))[0] == {(1, 2): 0}
    assert set(growth.simulate([(1, 2), (2, 3)], growth.Rules(k=1))[0].values()) == {0}
    with pytest.raises(RuntimeError):
        growth.simulate(edges, growth.Rules(k=4, most_rounds=1))


def test_swap_keeps_sizes_and_rewire_keeps_the_graph_simple(spark):
    g = graph(spark, random_pairs(40, 100, 4))
    before = sorted(r["n"] for r in annealed.start_parts(g, 4).groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect())
    after = annealed.annealed_swap(g, 4, most_rounds=3, delta=0.5)[0]
    assert sorted(r["n"] for r in after.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()) == before
    h = topology.rewire(g, 0.3)
    h.validate()
    assert h.edges.count() == g.edges.count() and topology.triangle_list(h).count() == topology.triangle_list(g).count()


def test_printed_random_clustering():
    for n, m, want in ((17903, 196972, 1.23e-3), (33696, 180811, 3.19e-4), (126146, 161950, 2.03e-5), (75606, 231622, 8.10e-5), (317080, 1049866, 2.09e-5), (1134890, 2987624, 4.64e-6), (400727, 2349869, 2.93e-5)):
        assert abs(topology.random_clustering(n, m) / want - 1) < 0.01


def test_entry_lists_every_sql():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_sweeps_cover_the_whole_giants(spark, sf):
    from edgegraph import queries

    graphs = queries._giants(spark, sf, queries.W3_GRAPHS)
    assert set(graphs) >= {"copurchase_q", "cust_supp", "activity_grid", "shared_line"}
    sizes = {"copurchase_q": duckdb_giant(sf, "copurchase_q"), "activity_grid": duckdb_giant(sf, "activity_grid")}
    assert {n: len(graphs[n]) for n in sizes} == sizes and sizes["activity_grid"] == 497
    assert queries.W2_FRACTIONS == (0.0, 0.01, 0.02, 0.05, 0.1, 0.2) and len(queries.SEEDS) == 5
    assert set(queries.W1_GRAPHS) >= {"copurchase_q", "activity_grid"}


def duckdb_giant(sf, name):
    from edgegraph import catalog

    con = duckdb.connect()
    for t in ("events", "orders", "lineitem"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    edges = con.sql(catalog.SQL[name]).fetchall()
    left, most = {v for e in edges for v in e}, 0
    while left:
        inside = {v for v, d in bfs(edges, min(left)).items() if d is not None}
        left -= inside
        if len(inside) > most:
            most, n_edges = len(inside), sum(a in inside for a, _ in edges)
    return n_edges


def test_frequent_lines_link_their_documents(spark, tmp_path):
    from edgegraph import catalog

    line, other = "a line that sixty documents have", "another line that two of them have"
    rows = [(i, line + (f"\n{other}" if i in (7, 9) else "")) for i in range(60)] + [(60, "a line of its own, nobody else")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted(tuple(r) for r in catalog.shared_line_all(spark, str(tmp_path)).edges.collect())
    assert got == sorted([(7, i * 16 + 7) for i in range(1, 60)] + [(7 * 16 + 7, 9 * 16 + 7)])
    few = catalog.shared_line_all(spark, str(tmp_path), pairs_up_to=60).edges.count()
    assert few == 60 * 59 // 2


def test_rewire_moves_the_fraction_asked_for(spark):
    g = graph(spark, [(i, i + 1) for i in range(300)])
    h = topology.rewire(g, 0.2, exact=True)
    h.validate()
    old, new = ({tuple(r) for r in x.edges.collect()} for x in (g, h))
    assert len(new) == 300 and len(new - old) == len(old - new) == 60 and not topology.triangle_list(h).count()
    full = graph(spark, [(i, j) for i in range(5) for j in range(i)])
    with pytest.raises(RuntimeError):
        topology.rewire(full, 0.5, exact=True)


def test_whole_table_queries_see_orders_of_every_date(spark, tmp_path):
    from datetime import datetime

    orders = [(i, datetime(1992 + i, 6, 1)) for i in range(4)]
    lines = [(i, p) for i in range(4) for p in (i, i + 1)]
    spark.createDataFrame(orders, "o_orderkey long, o_orderdate timestamp_ntz").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    queries = __spark_entry__.queries()
    assert sorted(map(tuple, queries["degree_histogram_all"](spark, str(tmp_path)).collect())) == [(1, 2), (2, 3)]
    got = {r.vid: r.dist for r in queries["distances_engine_all"](spark, str(tmp_path)).collect()}
    pairs = [(i * 16 + 4, i * 16 + 20) for i in range(4)]
    assert got == bfs(pairs, baselines.pick_source(graph(spark, pairs)))


def test_swap_equals_its_simulation_and_many_pairs_swap(spark):
    pairs = random_pairs(60, 120, 6)
    edges = sorted({(min(e), max(e)) for e in pairs if e[0] != e[1]})
    want, history = annealed.simulate_parts(edges, 3, 2, most_rounds=4, delta=0.5)
    got, rows = annealed.annealed_swap(graph(spark, pairs), 3, 2, most_rounds=4, delta=0.5)
    assert {r.vid: r.part for r in got.collect()} == want and rows == history
    many = sorted({(min(e), max(e)) for e in random_pairs(3000, 6000, 7) if e[0] != e[1]})
    assert annealed.simulate_parts(many, 8, most_rounds=1)[1][0]["swaps"] > 64
    part, history = annealed.simulate_parts(edges, 3, 2)
    assert [h["swaps"] for h in history[-annealed.QUIET :]] == [0] * annealed.QUIET


def test_engine_on_odd_graphs_and_moves_only_what_changed(spark):
    none = EdgePartitioning(spark.createDataFrame([], "src long, dst long, part int"), 3)
    assert programs.distances(none, 1).states.count() == 0 and programs.components(none).states.count() == 0
    p = parted(spark, [(i, i + 1, 0 if i < 50 else 1) for i in range(100)] + [(500, 501, 2)], 4)
    out = programs.distances(p, 0)
    # vertex 50 is the only one in two parts: its distance goes up once and down once
    assert out.supersteps == 2 and out.moved == [2, 0]
    assert {r.vid: r.value for r in out.states.collect()} == {i: i for i in range(101)} | {500: None, 501: None}
    again = programs.distances(p, 0, local="sql")
    assert again.supersteps == 2 and again.moved == [2, 0]


def test_superstep_exchanges_neither_edges_nor_states(spark, monkeypatch):
    """Plan of a later superstep: one exchange by vertex, one by part, and only changed rows in them."""
    from edgegraph.plans import Scratch

    plans, plain = [], Scratch.table

    def seen(self, frame, key, buckets, name=None):
        if name == "states":
            plans.append(frame._jdf.queryExecution().sparkPlan().toString())
            plans[-1] = frame._jdf.queryExecution().executedPlan().toString()
        return plain(self, frame, key, buckets, name)

    monkeypatch.setattr(Scratch, "table", seen)
    g = graph(spark, random_pairs(60, 120, 8))
    programs.distances(baselines.hash_edges(g, 4), baselines.pick_source(g))
    assert len(plans) > 2 and all(x.count("Exchange hashpartitioning") == 2 for x in plans[1:])
    assert all("changed#" in x and "Bucketed: true" in x for x in plans[1:])


def test_weighted_distances_match_brute_force(spark):
    import heapq

    rng = random.Random(9)
    edges = {(min(e), max(e)): rng.randint(1, 9) / 2 for e in random_pairs(50, 110, 9) if e[0] != e[1]}
    rows = [(a, b, w, (a * 7 + b) % 3) for (a, b), w in edges.items()]
    p = EdgePartitioning(spark.createDataFrame(rows, "src long, dst long, cost double, part int"), 3)
    start = min(edges)[0]
    best, heap = {}, [(0.0, start)]
    while heap:
        d, u = heapq.heappop(heap)
        if u not in best:
            best[u] = d
            for (a, b), w in edges.items():
                if u in (a, b):
                    heapq.heappush(heap, (d + w, b if u == a else a))
    for local in ("arrow", "sql"):
        got = {r.vid: r.value for r in programs.distances(p, start, weight="cost", local=local).states.collect()}
        assert {v: d for v, d in got.items() if d is not None} == best


def test_goal_and_edge_states(spark):
    """A program whose edges count how often a part was solved, and which ends after two supersteps."""
    from edgegraph.operators.engine import Program, run_program

    p = parted(spark, [(i, i + 1, i % 4 // 2) for i in range(40)], 2)
    def setup(c):
        return c.select("part", "vid", "n_copies", F.col("vid").cast("double").alias("value"), F.lit(True).alias("dirty"))

    def solve(part):
        value = part.value.copy()
        np.minimum.at(value, part.a, part.value[part.b])
        np.minimum.at(value, part.b, part.value[part.a])
        return value, part.edge_value + 1

    program = Program("count", "double", setup, solve, edge_setup=F.col("w") * 10, done=lambda x: x["superstep"] >= 2)
    out = run_program(p, program)
    assert out.supersteps == 2 and {r.edge_value for r in out.edges.collect()} == {12.0} and out.edges.count() == 40
    full = run_program(p, Program("least", "double", setup, lambda x: solve(x)[0] if x.edge_value is not None else _spread(x)))
    assert {r.value for r in full.states.collect()} == {0.0}


def _spread(part):
    value = part.value.copy()
    while True:
        before = value.copy()
        np.minimum.at(value, part.a, before[part.b])
        np.minimum.at(value, part.b, before[part.a])
        if (value == before).all():
            return value


def test_mean_reconcile_sees_every_replica(spark):
    from edgegraph.operators.engine import Program, run_program

    p = parted(spark, [(0, 1, 0), (0, 2, 1), (0, 3, 2)], 3)
    setup = lambda c: c.select("part", "vid", "n_copies", F.lit(0.0).alias("value"), F.lit(True).alias("dirty"))
    # each part proposes a value for vertex 0 once; the replicas agree on the mean of all three
    solve = lambda x: np.where((x.vid == 0) & (x.value == 0), x.vid[x.b[0]] * 3.0, x.value)
    out = run_program(p, Program("mean", "double", setup, solve, reconcile=F.avg, whole=True, adopt=lambda own, told: told))
    assert {r.vid: r.value for r in out.states.collect()}[0] == 6.0


def test_betweenness_matches_brute_force(spark):
    pairs = random_pairs(30, 45, 11)
    g = graph(spark, pairs)
    near = {}
    for a, b in {(min(e), max(e)) for e in pairs if e[0] != e[1]}:
        near.setdefault(a, set()).add(b), near.setdefault(b, set()).add(a)
    sources = sorted(near)[:3]
    want = dict.fromkeys(near, 0.0)
    for s in sources:
        dist = {v: d for v, d in bfs([(a, b) for a in near for b in near[a] if a < b], s).items() if d is not None}
        paths = {s: 1}
        for v in sorted(dist, key=dist.get):
            if v != s:
                paths[v] = sum(paths[u] for u in near[v] if dist[u] == dist[v] - 1)
        owed = dict.fromkeys(dist, 0.0)
        for v in sorted(dist, key=dist.get, reverse=True):
            for u in near[v]:
                if dist[u] == dist[v] - 1:
                    owed[u] += paths[u] / paths[v] * (1 + owed[v])
            if v != s:
                want[v] += owed[v]
    got = {r.vid: r.score for r in programs.betweenness(baselines.hash_edges(g, 3), sources).collect()}
    assert got.keys() == want.keys() and all(abs(got[v] - want[v]) < 1e-9 for v in want)


def test_toy_graphs_and_their_diameters(spark):
    from edgegraph import catalog, experiments

    want = {("path", 7): (6, 6), ("cycle", 9): (9, 4), ("star", 6): (5, 2), ("clique", 5): (10, 1), ("grid", 4): (24, 6), ("barbell", 4): (13, 3)}
    for (name, n), (m, far) in want.items():
        g = catalog.toy(spark, name, n)
        edges = experiments.edge_list(g)
        assert len(edges) == m and len(set(edges)) == m
        assert max(max(x for x in bfs(edges, v).values()) for v in {v for e in edges for v in e}) == far
        assert experiments.diameter_bound(edges) == far
    assert topology.diameter(catalog.toy(spark, "barbell", 4)) == 3 and topology.diameter(catalog.toy(spark, "path", 7), source=2) == 6
    assert topology.diameter(catalog.toy(spark, "path", 3), mode="exact") == 2
    assert topology.diameter(catalog.toy(spark, "path", 1)) == 0
    with pytest.raises(ValueError):
        catalog.toy(spark, "wheel", 4)


def test_sweep_reports_the_diameter_and_trends_follow_it(spark):
    from edgegraph import catalog, experiments

    graphs = {"long": experiments.edge_list(catalog.toy(spark, "path", 60)), "square": experiments.edge_list(catalog.toy(spark, "grid", 6))}
    rows = measures.summarise(experiments.sweep(spark, "w", graphs, ("growth",), (2, 4), range(2))).collect()
    assert {(r["graph"], r["mean"]) for r in rows if r["metric"] == "diameter"} == {("long", 59.0), ("square", 10.0)}
    made = [{"graph": g, "method": "x", "k": k, "metric": m, "mean": v} for g, d in (("a", 3), ("b", 9)) for k in (2, 4) for m, v in (("rounds", d * 10 / k), ("diameter", d), ("flat", 1.0))]
    assert experiments.trends(made, "rounds", "k") < 0 < experiments.trends(made, "rounds", "diameter")
    assert experiments.trends(made, "flat", "k") == 0.0


def test_recursion_rows_do_not_grow_with_the_customers(spark, sf):
    """Spark ends a recursion of over 1,000,000 rows with an error; here of over 100, with more customers."""
    n = spark.read.parquet(f"{sf}/customer.parquet").count()
    spark.conf.set("spark.sql.cteRecursionRowLimit", "100")
    try:
        assert n > 100 and __spark_entry__.queries()["op_cte_recursive"](spark, sf).count() == 2 * n
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")


def test_parts_grow_in_number_with_the_edges(spark, sf, monkeypatch):
    """A part is solved in one Python worker, so large graphs get more parts; results stay the same."""
    run, seen = programs.run_program, []
    monkeypatch.setattr(programs, "run_program", lambda p, *a, **o: seen.append(p) or run(p, *a, **o))
    q = __spark_entry__.queries()
    for name in ("diameter_supp_part", "distances_multi_source"):
        want = sorted(map(tuple, q[name](spark, sf).collect()))
        seen.clear()
        monkeypatch.setattr(baselines, "PART_EDGES", 200, raising=False)
        assert sorted(map(tuple, q[name](spark, sf).collect())) == want
        monkeypatch.undo()
        monkeypatch.setattr(programs, "run_program", lambda p, *a, **o: seen.append(p) or run(p, *a, **o))
        if name == "diameter_supp_part":
            m = seen[0].assigned.count()
            assert m > 200 * 8 and seen[0].k == -(-m // 200)


def test_simulated_growth_does_not_scan_a_hub_for_each_of_its_edges():
    import time

    began = time.process_time()
    owner, _ = growth.simulate([(0, i) for i in range(1, 4001)] + [(i, i + 1) for i in range(4000, 4200)], growth.Rules(k=2))
    assert len(owner) == 4200 and time.process_time() - began < 20


def _cut(edges, part):
    return sum(part[a] != part[b] for a, b in edges)


def test_swaps_end_where_pairs_could_swap_for_ever(spark):
    """Cliques that share vertices: by squares of neighbours some pairs always swapped, and 2,000 rounds ended in an error."""
    rng = random.Random(12)
    edges = sorted({(min(e), max(e)) for c in [rng.sample(range(70), 14) for _ in range(14)] for i, a in enumerate(c) for e in [(a, b) for b in c[:i]]})
    part, history = annealed.simulate_parts(edges, 4, 0)
    assert [h["swaps"] for h in history[-annealed.QUIET :]] == [0] * annealed.QUIET and len(history) < 300
    hot = next(i for i, h in enumerate(history) if h["temperature"] <= 1.0)
    cuts = [_cut(edges, annealed.simulate_parts(edges, 4, 0, most_rounds=i)[0]) for i in range(hot, len(history) + 1)]
    assert all(b <= a - h["swaps"] for a, b, h in zip(cuts, cuts[1:], history[hot:])) and any(h["swaps"] for h in history[hot:])


@pytest.mark.parametrize("task_edges", [0, 1000])
def test_swaps_in_jobs_and_in_one_task_are_alike(spark, task_edges):
    pairs = random_pairs(30, 70, 13)
    edges = sorted({(min(e), max(e)) for e in pairs if e[0] != e[1]})
    want, history = annealed.simulate_parts(edges, 3, 1, delta=0.5)
    got, rows = annealed.annealed_swap(graph(spark, pairs), 3, 1, delta=0.5, task_edges=task_edges)
    assert any(h["swaps"] for h in history if h["temperature"] <= 1.0)
    assert {r.vid: r.part for r in got.collect()} == want and rows == history


def test_triangles_by_colours_match_brute_force_and_exchange_no_wedges(spark):
    from edgegraph.operators.triangles import triangle_stats

    pairs = random_pairs(50, 260, 14) + [(60, i) for i in range(50)] + [(70, 71)]  # a hub, and an edge far off
    near = {}
    for a, b in {(min(e), max(e)) for e in pairs if e[0] != e[1]}:
        near.setdefault(a, set()).add(b), near.setdefault(b, set()).add(a)
    want = {v: (len(u), sum(len(near[x] & u) for x in u) // 2) for v, u in near.items()}
    assert max(t for _, t in want.values()) > 100
    for task_edges in (None, 200, 20):  # 1, 4 and 10 colours or so
        got = triangle_stats(graph(spark, pairs), task_edges)
        assert {r.vid: (r.degree, r.triangles) for r in got.collect()} == want
    plan = topology.triangles(graph(spark, pairs))._jdf.queryExecution().sparkPlan().toString()
    assert "Join" not in plan and triangle_stats(graph(spark, [])).count() == 0


def test_replicas_are_found_inside_the_stored_parts(spark, monkeypatch):
    """Before, both ends of every edge were exchanged by part and vertex to find them."""
    from edgegraph.plans import Scratch

    plans, plain = [], Scratch.table

    def seen(self, frame, key, buckets, name=None):
        if name == "states":
            plans.append(frame._jdf.queryExecution().toString())
        return plain(self, frame, key, buckets, name)

    monkeypatch.setattr(Scratch, "table", seen)
    rows = [(i, i + 1, i // 20) for i in range(60)]
    out = programs.distances(parted(spark, rows, 3), 0)
    assert {r.vid: r.value for r in out.states.collect()} == {i: i for i in range(61)}
    first = plans[0][plans[0].index("== Physical Plan ==") :]
    assert not [x for x in first.splitlines() if "Exchange hashpartitioning(part#" in x and "vid#" in x.split("hashpartitioning(")[1].split(")")[0]]


def test_arrays_are_hashed_as_single_keys_are():
    from edgegraph.functions import Hashes, portable_hash_py

    rng = random.Random(4)
    a, b = ([rng.randrange(10 ** rng.randint(1, 18)) for _ in range(500)] + [0, 9, 10, 2**63 - 1] for _ in range(2))
    hashed = Hashes(a, b, 7)
    for seed in (0, 9, 12345, 3):
        assert hashed(seed).tolist() == [portable_hash_py(seed, x, y, 7) for x, y in zip(a, b, strict=True)]
    assert Hashes([-1, 5])(2).tolist() == [portable_hash_py(2, -1), portable_hash_py(2, 5)] and Hashes([])(0).tolist() == []


def test_a_sample_takes_little_memory_for_each_edge():
    """Before, a sample of cust_supp at sf0.1 took over 1.3 GB in a Python worker, and two run in an executor."""
    import tracemalloc

    from edgegraph import experiments

    edges = np.array(sorted({(i, 10_000 + (i * 7919 + j * j) % 400) for i in range(2000) for j in range(20)}))
    for method in ("growth", "takeover", "hash"):
        pairs = edges if isinstance(experiments.assign(edges[:50], "hash", 2, 0)[0], np.ndarray) else list(map(tuple, edges.tolist()))
        tracemalloc.start()
        owner, rounds = experiments.assign(pairs, method, 20, 0)
        found = experiments.measure(pairs, owner, 20, 0, rounds)
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert len(owner) == len(edges) and found["vertex_rounds"] > 1 and peak < 900 * len(edges)


def test_rounds_of_samples_of_long_and_of_dense_graphs_are_short():
    import time

    from edgegraph import experiments

    long = sorted([(i * 60 + j, i * 60 + j + 1) for i in range(200) for j in range(59)] + [(i * 60 + j, i * 60 + j + 60) for i in range(199) for j in range(60)])
    dense = sorted({(i, 10_000 + (i * 7919 + j * j) % 400) for i in range(2000) for j in range(20)})
    for edges, method in ((long, "growth"), (dense, "swap")):
        began = time.process_time()
        owner, rounds = experiments.assign(edges, method, 20, 0)
        assert len(owner) == len(edges) and time.process_time() - began < 10


def test_a_task_takes_one_sample(spark):
    """Samples were dealt by hash, so that some tasks took several and others none."""
    from edgegraph import experiments

    graphs = {"path": [(i, i + 1) for i in range(9)], "star": [(0, i) for i in range(1, 9)]}
    runs = experiments.sweep(spark, "w", graphs, ("growth", "hash"), (2, 3), range(5))
    assert {r["count"] for r in runs.groupBy(F.spark_partition_id().alias("task")).count().collect()} == {8} and runs.count() == 8 * 40


def test_vertex_rounds_of_a_sample_are_those_of_single_edges():
    rng = random.Random(6)
    for _ in range(20):
        edges = sorted({(min(e), max(e)) for e in (rng.sample(range(30), 2) for _ in range(40))})
        found = measure(edges, dict.fromkeys(edges, 0), 1, 3, 0)
        source = min({v for e in edges for v in e}, key=lambda v: (portable_hash_py(3, v), v))
        far = max(d for d in bfs(edges, source).values() if d is not None)
        assert found["vertex_rounds"] == far == supersteps_of({e: i for i, e in enumerate(edges)}, source)


@pytest.mark.parametrize("front_rows", [0, 12, 10_000])
def test_a_vertex_round_reads_the_last_two_frontiers_only(spark, monkeypatch, front_rows):
    """Rounds with frontiers on the driver, in tables, and by turns, on graphs of two components, hubs and odd cycles."""
    from edgegraph import catalog

    monkeypatch.setattr(baselines, "FRONT_ROWS", front_rows)
    rng = random.Random(5)
    edges = sorted({(min(e), max(e)) for e in (rng.sample(range(25), 2) for _ in range(40))} | {(30 + i, 31 + i) for i in range(4)} | {(0, 100 + i) for i in range(15)})
    for pairs, source in ((edges, 0), (edges, 32), (edges, 999), ([(1, 2)], 1)):
        states, rounds = baselines.vertex_rounds_distance(EdgeGraph(spark.createDataFrame(pairs, "src long, dst long")), source)
        want = bfs(pairs, source) if source != 999 else {v: None for e in pairs for v in e}
        assert {r["vid"]: r["dist"] for r in states.collect()} == want
        assert rounds == max((d for d in want.values() if d is not None), default=0)
    if front_rows > 12:
        jobs = lambda: spark.sparkContext.statusTracker().getJobIdsForGroup("rounds")
        spark.sparkContext.setJobGroup("rounds", "rounds")
        try:
            _, rounds = baselines.vertex_rounds_distance(catalog.toy(spark, "path", 60), 0)
            assert rounds == 59 and len(jobs()) < 59 + 12
        finally:
            spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def test_large_graphs_swap_in_one_task_of_little_memory(spark):
    """Graphs of over 200,000 edges took a dozen jobs a round, and in one process over 1 kB an edge."""
    import tracemalloc

    n = 70_000
    edges = [(i, i + d) for i in range(n) for d in (1, 2, 5)]
    tracemalloc.start()
    part, _ = annealed.simulate_parts(edges, 4, most_rounds=2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 500 * len(edges)
    i = F.col("id")
    g = EdgeGraph(spark.range(n).select(i.alias("src"), F.explode(F.array(i + 1, i + 2, i + 5)).alias("dst")))
    spark.sparkContext.setJobGroup("swaps", "swaps")
    try:
        parts, history = annealed.annealed_swap(g, 4, most_rounds=2)
        assert len(history) == 2 and len(spark.sparkContext.statusTracker().getJobIdsForGroup("swaps")) < 12
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert {r["vid"]: r["part"] for r in parts.collect()} == part
