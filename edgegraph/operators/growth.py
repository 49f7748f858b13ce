"""Funded growth: a distributed edge partitioner driven by a funding model, in two versions.

start from one edge each. In a round, the vertices of a region offer its funds to edges around them; a
free edge goes to the region that offers most, for one credit; other offers go back, and what the owner
paid too much is halved between the ends of its edge. Small regions are topped up more. Amounts are whole
units (2**20 to a credit), so no round depends on the order of sums. In the *takeover* version a region that
is far smaller than the mean may also buy edges of regions larger than the mean.

Half-edges, funds, offers and settlements lie in tables bucketed by vertex, so a vertex meets its funds, its
edges and its money without an exchange. Two plans give the same result: ``edge`` settles each edge once (its
offers are exchanged by edge, and what comes of them by vertex), ``mirrored`` sends every offer to both ends of
its edge, which both settle it alike, so that offers and settlements cost one exchange together. The gifts of
a round take two more in either plan: the first border vertices of each part, and their gifts by vertex.
simulate() runs the same rules in one process, for sweeps over many samples.
"""

from __future__ import annotations

import functools
import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import Hashes, portable_hash, spans
from ..model import EdgeGraph, EdgePartitioning
from ..plans import Scratch

CREDIT = 1 << 20


@dataclass(frozen=True)
class Rules:
    k: int
    seed: int = 0
    spread: str = "affordable"  # or 'even'
    initial_credits: int | None = None
    cap: int = 10
    rate: float = 0.02  # share of the mean size that a region of mean size is given in a round
    takeover: bool = False
    poor_ratio: float = 2.0
    most_rounds: int = 10_000
    unreached: str = "reseed"  # or 'fill', 'error'
    seed_kind: str = "edge"  # or 'vertex'
    gifts: str = "border"  # or 'holders': who gets the credits of a round

    def credits(self, m: int) -> int:
        return self.initial_credits if self.initial_credits is not None else max(1, m // self.k)

    def grants(self, sizes: list[int], alive: list[bool]) -> list[int]:
        """Credits for each region after a round."""
        mean = sum(sizes) / self.k
        step = max(1, math.ceil(self.rate * mean))
        return [step * min(self.cap, math.ceil(mean / s)) if a and s else 0 for s, a in zip(sizes, alive, strict=True)]

    def poor_rich(self, sizes: list[int]) -> tuple[list[bool], list[bool]]:
        mean = sum(sizes) / self.k
        return [self.takeover and s < mean / self.poor_ratio for s in sizes], [self.takeover and s > mean for s in sizes]


def pick_seeds(g: EdgeGraph, k: int, seed: int = 0, kind: str = "edge") -> list[tuple[int, int]]:
    """The k start edges: those of the smallest hashes, or the first edges of the k vertices of the
    smallest hashes (fewer where these meet). k rows reach the driver."""
    h = portable_hash(seed, F.col("src"), F.col("dst"))
    if kind == "edge":
        return [(r["src"], r["dst"]) for r in g.edges.orderBy(h, "src", "dst").limit(k).collect()]
    first = g.half_edges().groupBy("vid").agg(F.min(F.struct(h.alias("h"), F.col("src"), F.col("dst"))).alias("e"))
    rows = first.orderBy(portable_hash(seed, F.col("vid")), "vid").limit(k).collect()
    return list(dict.fromkeys((r["e"]["src"], r["e"]["dst"]) for r in rows))


# ---------------------------------------------------------------- one process


def simulate(edges: list[tuple[int, int]], rules: Rules) -> tuple[dict[tuple[int, int], int], list[dict]]:
    """Owners of all edges and the history of rounds, for a graph that fits one process."""
    edges = sorted(edges)
    owner, history = grow_arrays(*np.array(edges, dtype=np.int64).reshape(-1, 2).T, rules)
    return dict(zip(edges, owner.tolist(), strict=True)), history


#: half-edges that are looked at together, where a region cannot pay for all edges of a vertex
SPAN_ROWS = 1_000_000


def grow_arrays(src: np.ndarray, dst: np.ndarray, rules: Rules) -> tuple[np.ndarray, list[dict]]:
    """The same for the ends of edges in order. Vertices are numbered by id. Half-edges lie by vertex and owner, so
    the free edges of a vertex, and those of a part at it, are a span; funds are (vertex * k + part, units) in order."""
    m, k = len(src), rules.k
    owner = np.full(m, -1)
    if not m:
        return owner, []
    if k == 1:
        return np.zeros(m, np.int64), []
    ids, ends = np.unique(np.concatenate((src, dst)), return_inverse=True)
    a, b, n = ends[:m], ends[m:], len(ids)
    h = Hashes(src, dst)(rules.seed)
    order = np.argsort(ends, kind="stable")
    half_at, half_edge = ends[order], order % m
    degree = np.bincount(ends, minlength=n)
    begin = np.cumsum(degree) - degree
    edge_places, vertex_places = _Places(rules.seed, src, dst), _Places(rules.seed, ids)
    start = rules.credits(m) * CREDIT

    def by_owner() -> tuple[np.ndarray, np.ndarray]:
        """The half-edges by vertex and owner, free ones first, and these two as one number."""
        key = half_at * (k + 1) + owner[half_edge] + 1
        at = np.argsort(key, kind="stable")
        return half_edge[at], key[at]

    def total(*some: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        where, units = (np.concatenate(x) for x in zip(*some, strict=True))
        where, units = where[units > 0], units[units > 0]
        at = np.argsort(where, kind="stable")
        where, units = where[at], units[at]
        first = np.flatnonzero(np.diff(where, prepend=-1))
        return where[first], np.add.reduceat(units, first) if len(first) else units

    def planted(e: np.ndarray, i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        owner[e] = i
        return np.concatenate((a[e] * k + i, b[e] * k + i)), np.repeat([start - start // 2, start // 2], len(e))

    if rules.seed_kind == "edge":
        seeds = np.argsort(h, kind="stable")[:k]
    else:
        some = np.argsort(Hashes(ids)(rules.seed), kind="stable")[:k].tolist()
        seeds = np.array(list(dict.fromkeys(min(half_edge[begin[v] : begin[v] + degree[v]].tolist(), key=lambda e: (h[e], e)) for v in some)))
    funds, units = total(planted(seeds, np.arange(len(seeds))))
    sizes = np.bincount(owner[seeds], minlength=k)
    alive = [i < len(seeds) for i in range(k)]
    half_edge, key = by_owner()
    history: list[dict] = []
    while (free := m - int(sizes.sum())) > 0:
        if len(history) >= rules.most_rounds:
            raise RuntimeError(f"{free} edges are free after {rules.most_rounds} rounds")
        poor, rich = (np.array(x) for x in rules.poor_rich(sizes.tolist()))
        v, i = funds // k, funds % k
        # offers: the edges that each fund is spread over
        even, whole = rules.spread != "affordable", units // CREDIT
        free_from, free_to = begin[v], np.searchsorted(key, v * (k + 1), "right")
        own_from, own_to = np.searchsorted(key, v * (k + 1) + i + 1), np.searchsorted(key, v * (k + 1) + i + 1, "right")
        n_buy, n_own = free_to - free_from, own_to - own_from
        plain = ~poor[i]
        buying = plain & (even | (whole > 0)) & (n_buy > 0)
        chosen = [(half_edge[at], of) for at, of in (
            _rows(buying & (even | (whole >= n_buy)), free_from, n_buy),
            _rows(plain & (even | ~buying), own_from, n_own),
        )]
        limited = buying & (not even) & (whole < n_buy)
        span_from, span = np.where(limited, free_from, begin[v]), np.where(limited, n_buy, degree[v])
        rows = np.flatnonzero(limited | ~plain)
        for some in np.split(rows, np.flatnonzero(np.diff(np.cumsum(span[rows]) // SPAN_ROWS)) + 1) if len(rows) else ():
            at, of = spans(span_from[some], span[some])
            e, of = half_edge[at], some[of]
            at = owner[e]
            can = (at < 0) | (poor[i[of]] & rich[at] & (at != i[of]))
            if even:
                take = can | (at == i[of])
                chosen.append((e[take], of[take]))
                continue
            can_pay = np.zeros(len(v), bool)
            can_pay[of[can]] = True
            can_pay &= whole > 0
            own = (at == i[of]) & ~can_pay[of]
            chosen.append((e[own], of[own]))
            can &= can_pay[of]
            e, of = e[can], of[can]
            by = np.argsort((of << 32) | edge_places(e, i[of]))
            e, of = e[by], of[by]
            first = np.flatnonzero(np.diff(of, prepend=-1))
            nth = np.arange(len(of)) - np.repeat(first, np.diff(np.append(first, len(of))))
            chosen.append((e[nth < whole[of]], of[nth < whole[of]]))
        e, of = (np.concatenate(x) for x in zip(*chosen, strict=True))
        n_chosen = np.bincount(of, minlength=len(v))
        share = units // np.maximum(n_chosen, 1) * (n_chosen > 0)
        left = funds, units - share * n_chosen
        e, of = e[share[of] > 0], of[share[of] > 0]
        # each edge settled: sides are what a part offers for an edge, from one or both ends
        side = e * k + i[of]
        by = np.argsort(side, kind="stable")
        side, of, e = side[by], of[by], e[by]
        first = np.flatnonzero(np.diff(side, prepend=-1))
        paid = share[of]
        offered = np.add.reduceat(paid, first) if len(first) else paid
        from_src = np.add.reduceat(np.where(v[of] == a[e], paid, 0), first) if len(first) else paid
        e, who = side[first] // k, side[first] % k
        at = owner[e]
        bid = np.flatnonzero((who != at) & ((at < 0) | (poor[who] & rich[at])) & (offered >= CREDIT))
        if len(bid):
            first = np.flatnonzero(np.diff(e[bid], prepend=-1))
            most = np.maximum.reduceat(offered[bid], first)
            bid = bid[offered[bid] == np.repeat(most, np.diff(np.append(first, len(bid))))]
            again = e[bid][1:] == e[bid][:-1]
            tied = np.append(again, False) | np.append(False, again)
            tie = np.zeros(len(bid), np.int64)
            tie[tied] = Hashes(src[e[bid[tied]]], dst[e[bid[tied]]], who[bid[tied]])(rules.seed)
            bid = bid[np.lexsort((who[bid], tie, e[bid]))]
            bid = bid[np.flatnonzero(np.diff(e[bid], prepend=-1))]
        lost = at[bid]
        sizes = sizes + np.bincount(who[bid], minlength=k) - np.bincount(lost[lost >= 0], minlength=k)
        owner[e[bid]] = who[bid]
        changed = len(bid)
        offered[bid] -= CREDIT
        mine = owner[e] == who
        to_src = np.where(mine, offered - offered // 2, from_src)
        to_dst = np.where(mine, offered // 2, offered - from_src)
        funds, units = total(left, (a[e] * k + who, to_src), (b[e] * k + who, to_dst))
        if changed:
            half_edge, key = by_owner()
        free, granted = m - int(sizes.sum()), 0
        if free:
            here = key[np.flatnonzero(np.diff(key, prepend=-1))]
            at, part = here // (k + 1), here % (k + 1) - 1
            is_open = np.zeros(n, bool)
            is_open[at[part < 0]] = True
            border = (part >= 0) & is_open[at]
            at, part = at[border], part[border]
            gifts = [(funds, units)]
            for i, credits in enumerate(rules.grants(sizes.tolist(), alive)):
                if not credits:
                    continue
                to, held = at[part == i], funds[funds % k == i] // k
                if rules.gifts == "border" and len(to):
                    if len(to) > credits:
                        to = to[np.argpartition(vertex_places(to, np.full(len(to), i)), credits)[:credits]]
                elif len(held):
                    to = held
                if len(to):
                    gift = credits * CREDIT
                    granted += gift
                    each = np.full(len(to), gift // len(to))
                    each[to.argmin()] += gift % len(to)
                    gifts.append((to * k + i, each))
            funds, units = total(*gifts)
        history.append({"round": len(history) + 1, "free": free, "changed": changed, "smallest": int(sizes.min()), "largest": int(sizes.max()), "units": int(units.sum()), "granted": granted})
        if not changed and free:
            touched = np.zeros(n, bool)
            touched[a[owner >= 0]] = touched[b[owner >= 0]] = True
            rest = np.flatnonzero(owner < 0)
            if not (touched[a[rest]] | touched[b[rest]]).any():
                least = min(range(k), key=lambda i: (sizes[i], i))
                if rules.unreached == "error":
                    raise RuntimeError(f"{free} edges cannot be reached from any seed")
                if rules.unreached == "fill":
                    owner[rest] = least
                    sizes[least] += free
                else:
                    funds, units = total((funds, units), planted(rest[[h[rest].argmin()]], np.array([least])))
                    sizes[least] += 1
                half_edge, key = by_owner()
                alive[least] = True
    return owner, history


def _rows(chosen: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """spans() of the chosen rows, with their numbers among all rows."""
    at, of = spans(start[chosen], size[chosen])
    return at, np.flatnonzero(chosen)[of]


class _Places:
    """The place of an item (all of its keys) in a part's order: by hash of the keys and the part, then by its number."""

    def __init__(self, seed: int, *keys: np.ndarray) -> None:
        self.seed, self.keys, self.held = seed, keys, {}

    def __call__(self, item: np.ndarray, part: np.ndarray) -> np.ndarray:
        out = np.empty(len(item), np.int64)
        by = np.argsort(part, kind="stable")
        bounds = np.flatnonzero(np.diff(part[by], append=-1)) + 1
        for some in np.split(by, bounds[:-1]) if len(by) else ():
            i = int(part[some[0]])
            if i not in self.held:
                place = np.empty(len(self.keys[0]), np.int32)
                place[np.argsort(Hashes(*self.keys, i)(self.seed), kind="stable")] = np.arange(len(place), dtype=np.int32)
                self.held[i] = place
            out[some] = self.held[i][item[some]]
        return out


# ---------------------------------------------------------------- on DataFrames


def spread_funds(half: DataFrame, funds: DataFrame, levels: DataFrame, rules: Rules) -> DataFrame:
    """Offers (src, dst, owner, part, vid, amount, can_buy) of all funds (vid, part, units); what is not
    offered stays. half: (vid, src, dst, owner) with owner null for free edges; levels: (part, poor,
    rich), k rows."""
    rows = funds.where("units > 0").join(half, "vid")
    if rules.takeover:
        lv = F.broadcast(levels)  # k rows, a parameter
        rows = rows.join(lv.select("part", "poor"), "part").join(lv.select(F.col("part").alias("owner"), "rich"), "owner", "left")
        take = F.col("poor") & F.coalesce("rich", F.lit(False)) & (F.col("owner") != F.col("part"))
    else:
        take = F.lit(False)
    rows = rows.withColumn("can_buy", F.col("owner").isNull() | take).where(F.col("can_buy") | (F.col("owner") == F.col("part")))
    mine = Window.partitionBy("vid", "part")
    rows = rows.withColumn("buy", F.count(F.when(F.col("can_buy"), 1)).over(mine)).withColumn("all", F.count(F.lit(1)).over(mine))
    if rules.spread == "affordable":
        whole = F.floor(F.col("units") / CREDIT)
        buying = (F.col("buy") > 0) & (whole > 0)
        order = mine.orderBy(F.desc("can_buy"), portable_hash(rules.seed, F.col("src"), F.col("dst"), F.col("part")), "src", "dst")
        n = F.when(buying, F.least("buy", whole)).otherwise(F.col("all") - F.col("buy"))
        rows = rows.withColumn("n", n).withColumn("place", F.row_number().over(order)).where(F.when(buying, F.col("place") <= F.col("n")).otherwise(~F.col("can_buy")))
    else:
        rows = rows.withColumn("n", F.col("all"))
    return rows.withColumn("amount", F.expr("units div n")).where("amount > 0").select("src", "dst", "owner", "part", "vid", "amount", "can_buy")


def auction(offers: DataFrame, rules: Rules, at: tuple[str, ...] = ()) -> DataFrame:
    """Each edge settled: (at.., src, dst, owner, part, new_owner, bought, to_src, to_dst) for every part that
    offered. at: further keys that tell mirrored copies of an edge apart."""
    keys = [*at, "src", "dst"]
    sides = offers.groupBy(*keys, "part").agg(
        F.max("owner").alias("owner"), F.max("can_buy").alias("can_buy"), F.sum("amount").alias("total"), F.sum(F.when(F.col("vid") == F.col("src"), F.col("amount")).otherwise(0)).alias("from_src")
    )
    bid = F.when(F.col("can_buy") & (F.col("total") >= CREDIT), F.struct(F.col("total"), (-portable_hash(rules.seed, F.col("src"), F.col("dst"), F.col("part"))).alias("tie"), F.col("part").alias("who")))
    best = F.max(bid).over(Window.partitionBy(*keys))
    rows = sides.withColumn("best", best).withColumn("new_owner", F.coalesce("best.who", "owner"))
    mine, bought = F.col("new_owner").eqNullSafe(F.col("part")), F.col("best").isNotNull()
    pot = F.col("total") - F.when(bought, F.lit(CREDIT)).otherwise(0)
    rows = rows.withColumn("pot", pot).withColumn("half", F.expr("pot div 2"))
    return rows.select(
        *keys, "owner", "part", "new_owner", bought.alias("bought"),
        F.when(mine, F.col("pot") - F.col("half")).otherwise(F.col("from_src")).alias("to_src"),
        F.when(mine, F.col("half")).otherwise(F.col("total") - F.col("from_src")).alias("to_dst"),
    )


def top_up(funds: DataFrame, half: DataFrame, grants: list[int], rules: Rules) -> DataFrame:
    """Gifts (vid, part, units) of each part's grant: a credit to each of the first vertices, by hash, that have an
    edge of the part and a free one ('border'; evenly if these are fewer), or else evenly to the vertices
    where the part holds funds ('holders'; those at the border where there are none)."""
    table = F.broadcast(funds.sparkSession.createDataFrame([(i, g, g * CREDIT) for i, g in enumerate(grants) if g], "part int, credits int, gift long"))  # k rows
    border = half.groupBy("vid").agg(F.collect_set("owner").alias("owners"), F.max(F.col("owner").isNull()).alias("open")).where("open").select("vid", F.explode("owners").alias("part"))
    order = Window.partitionBy("part").orderBy(portable_hash(rules.seed, F.col("vid"), F.col("part")), "vid")
    first = border.withColumn("place", F.row_number().over(order)).where(F.col("place") <= max(grants))
    held = funds.select("vid", "part")
    if rules.gifts == "border":
        first = first.join(table, "part").where("place <= credits").select("vid", "part")
        to = first.unionByName(held.join(border.select("part").distinct(), "part", "left_anti"))
    else:
        to = held.unionByName(border.join(held.select("part").distinct(), "part", "left_anti"))
    counts = to.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.min("vid").alias("least")).join(table, "part")
    given = to.join(F.broadcast(counts), "part").select("vid", "part", (F.expr("gift div n") + F.when(F.col("vid") == F.col("least"), F.expr("gift % n")).otherwise(0)).alias("units"))
    return given


def funded_growth(g: EdgeGraph, k: int, seed: int = 0, plan: str = "edge", **options) -> EdgePartitioning:
    """Partitions the edges of g into k regions; see Rules for the options."""
    rules = Rules(k=k, seed=seed, **options)
    spark = g.spark
    scratch = Scratch(spark, "growth")
    edges = scratch.store(g.edges.select("src", "dst"))
    m = edges.count()
    if m == 0 or k == 1:
        return EdgePartitioning(edges.withColumn("part", F.lit(0)), k, [])
    seeds = pick_seeds(EdgeGraph(edges), k, seed, rules.seed_kind)
    start = rules.credits(m) * CREDIT

    def planted(rows: list[tuple[int, int, int]]) -> tuple[DataFrame, DataFrame]:
        own = spark.createDataFrame(rows, "src long, dst long, fresh int")
        money = [(v, i, u) for a, b, i in rows for v, u in ((a, start - start // 2), (b, start // 2))]
        return own, spark.createDataFrame(money, "vid long, part int, units long")

    own, funds = planted([(a, b, i) for i, (a, b) in enumerate(seeds)])
    funds = funds.groupBy("vid", "part").agg(F.sum("units").alias("units"))
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def by_vertex(frame: DataFrame, name: str, lies: bool = False) -> DataFrame:
        """frame, stored in buckets of its vertices; lies: it lies by vertex already."""
        return scratch.table(frame if lies else frame.repartition(buckets, "vid"), "vid", buckets, name)

    def owned(half: DataFrame, sold: DataFrame) -> DataFrame:
        """half with the owner of those that are sold, (vid, src, dst, fresh): by a union that stays in its buckets."""
        none = F.lit(None).cast("int")
        both = half.select("vid", "src", "dst", "owner", none.alias("fresh")).unionByName(sold.select("vid", "src", "dst", none.alias("owner"), "fresh"))
        return both.groupBy("vid", "src", "dst").agg(F.coalesce(F.max("fresh"), F.max("owner")).alias("owner"))

    def total(*parts: DataFrame) -> DataFrame:
        return functools.reduce(DataFrame.unionByName, (x.select("vid", "part", "units") for x in parts)).groupBy("vid", "part").agg(F.sum("units").alias("units")).where("units > 0")

    # the half-edges carry the owner of their edge; both halves of an edge always agree
    half = EdgeGraph(edges).half_edges().select("vid", "src", "dst").join(F.broadcast(own), ["src", "dst"], "left").select("vid", "src", "dst", F.col("fresh").alias("owner"))
    half, funds = by_vertex(half, "half"), by_vertex(funds, "funds")
    sizes = [0] * k
    for i in range(len(seeds)):
        sizes[i] = 1
    alive = [i < len(seeds) for i in range(k)]
    history: list[dict] = []
    while sum(sizes) < m:
        if len(history) >= rules.most_rounds:
            raise RuntimeError(f"{m - sum(sizes)} edges are free after {rules.most_rounds} rounds")
        poor, rich = rules.poor_rich(sizes)
        levels = spark.createDataFrame([(i, poor[i], rich[i]) for i in range(k)], "part int, poor boolean, rich boolean")
        offers = by_vertex(spread_funds(half, funds, levels, rules).select("src", "dst", "owner", F.col("part").cast("int").alias("part"), "vid", "amount", "can_buy"), "offers", True)
        if plan == "mirrored":
            both = offers.withColumn("at", F.explode(F.array("src", "dst"))).repartition(buckets, "at")
            settled = auction(both, rules, ("at",)).select(F.col("at").alias("vid"), "src", "dst", "owner", "part", "new_owner", "bought", F.when(F.col("at") == F.col("src"), F.col("to_src")).otherwise(F.col("to_dst")).alias("units"))
            settled = by_vertex(settled, "settled", True)
        else:
            ends = F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("to_src").alias("units")), F.struct(F.col("dst").alias("vid"), F.col("to_dst").alias("units"))))
            settled = auction(offers, rules).withColumn("x", ends).select("x.vid", "src", "dst", "owner", "part", "new_owner", "bought", "x.units")
            settled = by_vertex(settled, "settled")
        sold = settled.where("bought and part = new_owner").select("vid", "src", "dst", F.col("new_owner").alias("fresh"), "owner")
        moves = sold.where("vid = src").groupBy(F.col("owner").alias("lost"), F.col("fresh").alias("won")).agg(F.count(F.lit(1)).alias("n")).collect()  # k * k rows at most
        changed = sum(r["n"] for r in moves)
        for r in moves:
            sizes[r["won"]] += r["n"]
            if r["lost"] is not None:
                sizes[r["lost"]] -= r["n"]
        half = by_vertex(owned(half, sold), "half", True)
        funds = total(funds, offers.withColumn("units", -F.col("amount")), settled)
        grants = rules.grants(sizes, alive) if sum(sizes) < m else [0] * k
        if any(grants):
            funds = by_vertex(funds, "unfunded", True)
            funds = total(funds, top_up(funds, half, grants, rules).repartition(buckets, "vid"))
        funds = by_vertex(funds, "funds", True)
        history.append({"round": len(history) + 1, "free": m - sum(sizes), "changed": changed, "smallest": min(sizes), "largest": max(sizes), "units": funds.agg(F.sum("units")).first()[0] or 0})
        if not changed and sum(sizes) < m:
            reach = half.groupBy("vid").agg(F.max(F.col("owner").isNull()).alias("open"), F.max(F.col("owner").isNotNull()).alias("taken")).where("open and taken").limit(1).count()
            if not reach:
                least = min(range(k), key=lambda i: (sizes[i], i))
                if rules.unreached == "error":
                    raise RuntimeError(f"{m - sum(sizes)} edges cannot be reached from any seed")
                if rules.unreached == "fill":
                    half = by_vertex(half.withColumn("owner", F.coalesce("owner", F.lit(least))), "half")
                    sizes[least] += m - sum(sizes)
                else:
                    e = half.where("owner is null").orderBy(portable_hash(seed, F.col("src"), F.col("dst")), "src", "dst").first()
                    own, money = planted([(e["src"], e["dst"], least)])
                    half = by_vertex(half.join(F.broadcast(own), ["src", "dst"], "left").select("vid", "src", "dst", F.coalesce("fresh", "owner").alias("owner")), "half")
                    funds = by_vertex(total(funds, money), "funds")
                    sizes[least] += 1
                alive[least] = True
    assigned = scratch.store(half.where("vid = src").select("src", "dst", F.col("owner").cast("int").alias("part")))
    return EdgePartitioning(assigned, k, history)
