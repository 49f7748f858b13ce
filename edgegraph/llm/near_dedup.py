"""Near-duplicate classes by ProbMinHash, banding and verification.

*Signature.* A document is a weighted set of word shingles, the weight being how often a shingle occurs.
Each shingle is a Poisson process whose rate is its weight: its arrivals, drawn from its hash alone,
fall into random registers, and a register keeps the shingle that came first. Two documents agree on a
register with the probability Jaccard similarity. Shingles leave the race once their next arrival
comes later than the last register was taken (early termination).

*Banding.* ``bands`` keys of ``rows`` registers each. Documents with the same sequence of words are one
node from the start, so copies never meet in a bucket.

*Verification.* Candidates are compared by the exact probability Jaccard of their shingles. A bucket does
not list its pairs: each document is first compared with the smallest centre of its buckets, verified
links are joined to classes, and only buckets that still hold several classes go on: small ones with all
pairs across classes, large ones with two random centres a member. Large buckets that are still mixed end
exactly. A document leaves there if the shingles that it shares with any other make up less than the
threshold of its weight. The rest form zones, joined by their buckets. In a zone, blocks of the documents
outside its largest class meet blocks of all its documents; a block is bounded in bytes and rows, overlaps
are sums of products over shingles, and only links leave a task, one a document and class.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exact import shared_folder
from .links import components, roots, store
from .rolling import Prefix, digest, joined, mix, text_bytes, words

_U = np.uint64
_STEP = _U(0xD1342543DE82EF95)


def shingles(data: np.ndarray, off: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, tuple]:
    """(document, hash, count) of the distinct shingles of each row, sorted, and where the words stand (see
    words()). A row of fewer words than width has one shingle of them all."""
    found = starts, ends, first = words(data, off)
    sums = Prefix(Prefix.of_bytes(data).at(starts, ends))
    n = np.diff(first)
    doc = np.repeat(np.arange(len(n)), n)
    left = first[1:][doc] - np.arange(len(starts))
    at = np.flatnonzero(left >= width)
    short = np.flatnonzero((n > 0) & (n < width))
    who = np.concatenate((doc[at], short))
    key = np.concatenate((sums.at(at, at + width), sums.at(first[:-1][short], first[1:][short])))
    order = np.lexsort((key, who))
    who, key = who[order], key[order]
    new = np.ones(len(key), dtype=bool)
    new[1:] = (key[1:] != key[:-1]) | (who[1:] != who[:-1])
    places = np.flatnonzero(new)
    count = np.diff(np.append(places, len(key)))
    return who[places], key[places], count, found


def signatures(who: np.ndarray, key: np.ndarray, weight: np.ndarray, rows: int, registers: int) -> np.ndarray:
    """rows x registers shingle hashes; rows without shingles hold zeros."""
    came = np.full(rows * registers, np.inf)
    first = np.zeros(rows * registers, dtype=np.uint64)
    state, time, rate = mix(key ^ _U(0x5851F42D4C957F2D)), np.zeros(len(key)), 1.0 / weight
    while len(who):
        state = state + _STEP
        draw = mix(state)
        time = time - np.log(((draw >> _U(11)).astype(np.float64) + 0.5) * 2.0**-53) * rate
        place = who * registers + ((mix(draw) >> _U(32)) * _U(registers) >> _U(32)).astype(np.int64)
        sooner = time < came[place]
        p, t, k = place[sooner], time[sooner], key[sooner]
        order = np.lexsort((k, t, p))
        p, t, k = p[order], t[order], k[order]
        head = np.ones(len(p), dtype=bool)
        head[1:] = p[1:] != p[:-1]
        came[p[head]], first[p[head]] = t[head], k[head]
        still = time < came.reshape(rows, registers).max(axis=1)[who]
        who, key, state, time, rate = who[still], key[still], state[still], time[still], rate[still]
    return first.reshape(rows, registers)


def probability_jaccard(pair: np.ndarray, a: np.ndarray, b: np.ndarray, pairs: int) -> np.ndarray:
    """Probability Jaccard of each pair of weighted sets: for each pair and element of either set, the
    weights a and b (0 where it is missing).

    The sum over shared x of 1 / sum over y of max(a_y / a_x, b_y / b_x). With elements ordered by a / b,
    the maximum is the first for those from x on, the second for those before.
    """
    with np.errstate(divide="ignore"):
        ratio = np.where(b > 0, a / np.maximum(b, 1e-300), np.inf)
    order = np.lexsort((ratio, pair))
    pair, a, b = pair[order], a[order], b[order]
    start = np.searchsorted(pair, np.arange(pairs + 1))
    above, below = np.concatenate(([0.0], np.cumsum(a))), np.concatenate(([0.0], np.cumsum(b)))
    i = np.flatnonzero((a > 0) & (b > 0))
    lo, hi = start[pair[i]], start[pair[i] + 1]
    total = (above[hi] - above[i]) / a[i] + (below[i] - below[lo]) / b[i]
    return np.bincount(pair[i], weights=1.0 / total, minlength=pairs)


def similarities(a: tuple, b: tuple, pairs: int) -> np.ndarray:
    """Probability Jaccard of the p-th set of a and the p-th of b; each is (pair, shingle, count) arrays."""
    who, key, count = (np.concatenate(x) for x in zip(a, b, strict=True))
    first = np.arange(len(who)) < len(a[0])
    order = np.lexsort((key, who))
    who, key, count, first = who[order], key[order], count[order].astype(float), first[order]
    new = np.ones(len(who), dtype=bool)
    new[1:] = (key[1:] != key[:-1]) | (who[1:] != who[:-1])
    group = np.cumsum(new) - 1
    sides = (np.bincount(group, weights=count * x) if len(group) else np.zeros(0) for x in (first, ~first))
    return probability_jaccard(who[new], *sides, pairs)


def _spans(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each of the ranges, one after the other."""
    ends = np.cumsum(length)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - length - start, length)


def shared_weights(q: tuple, t: tuple, nq: int, nt: int, chunk: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Two nq x nt tables: the weight of each set of q, and of t, that lies in shingles both have.

    q, t: (set, shingle, count) arrays. Shingles of many sets are summed by products of dense tables, the
    others by their pairs of sets; both go in chunks of bounded size.
    """
    both = np.intersect1d(q[1], t[1])
    sides = []
    for who, key, count in (q, t):
        at = np.minimum(np.searchsorted(both, key), max(0, len(both) - 1))
        keep = both[at] == key if len(both) else np.zeros(len(key), dtype=bool)
        order = np.argsort(at[keep], kind="stable")
        sides.append((who[keep][order], at[keep][order], count[keep][order].astype(np.float32)))
    (qw, qk, qc), (tw, tk, tc) = sides
    dq, dt = np.bincount(qk, minlength=len(both)), np.bincount(tk, minlength=len(both))
    out = np.zeros((nq, nt)), np.zeros((nq, nt))
    dense = dq * dt * 64 >= nq * nt
    names = np.flatnonzero(dense)
    step = max(1, chunk // max(nq, nt, 1))
    for at in range(0, len(names), step):
        lo, hi = names[at], names[min(at + step, len(names)) - 1]
        tables = []
        for who, key, count, n in ((qw, qk, qc, nq), (tw, tk, tc, nt)):
            part = slice(*np.searchsorted(key, (lo, hi + 1)))
            on = dense[key[part]]
            x = np.zeros((n, min(step, len(names) - at)), dtype=np.float32)
            x[who[part][on], np.searchsorted(names, key[part][on]) - at] = count[part][on]
            tables.append(x)
        x, y = tables
        out[0][:] += x @ (y > 0).astype(np.float32).T
        out[1][:] += (x > 0).astype(np.float32) @ y.T
    first = np.cumsum(dt) - dt
    rows = np.flatnonzero(~dense[qk])
    ends = np.cumsum(dt[qk[rows]])
    at = 0
    while at < len(rows):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + chunk, side="right")))
        mine = np.repeat(rows[at:to], dt[qk[rows[at:to]]])
        other = _spans(first[qk[rows[at:to]]], dt[qk[rows[at:to]]])
        cell = qw[mine] * nt + tw[other]
        for table, weight in zip(out, (qc[mine], tc[other]), strict=True):
            table += np.bincount(cell, weights=weight, minlength=nq * nt).reshape(nq, nt)
        at = to
    return out


def close_pairs(q: tuple, t: tuple, nq: int, nt: int, threshold: float, chunk: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Places (i, j) of all pairs of a set of q and one of t whose probability Jaccard reaches the threshold.

    With A, B the weights of two sets and S, T the parts of them in shared shingles, it is at most
    1 / (A / S + B / T - 1), and just that where all counts are 1. Pairs below it are out; the others are computed.
    """
    s, u = shared_weights(q, t, nq, nt, chunk)
    a, b = np.bincount(q[0], weights=q[2], minlength=nq), np.bincount(t[0], weights=t[2], minlength=nt)
    with np.errstate(divide="ignore", invalid="ignore"):
        i, j = np.nonzero(1.0 / (a[:, None] / s + b[None, :] / u - 1.0) >= threshold - 1e-9)
    plain = [np.bincount(x[0], weights=x[2] > 1, minlength=n) == 0 for x, n in ((q, nq), (t, nt))]
    good = plain[0][i] & plain[1][j]
    check = np.flatnonzero(~good)
    starts = [np.searchsorted(x[0], np.arange(n + 1)) for x, n in ((q, nq), (t, nt))]
    length = [np.diff(x) for x in starts]
    ends = np.cumsum(length[0][i[check]] + length[1][j[check]])
    at = 0
    while at < len(check):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + chunk, side="right")))
        sides = []
        for x, first, n, place in ((q, starts[0], length[0], i), (t, starts[1], length[1], j)):
            these = place[check[at:to]]
            rows = _spans(first[these], n[these])
            sides.append((np.repeat(np.arange(to - at), n[these]), x[1][rows], x[2][rows]))
        good[check[at:to]] = similarities(*sides, to - at) >= threshold - 1e-9
        at = to
    return i[good], j[good]


def _slices(table, size: int):
    """Pieces of a batch whose texts hold about size bytes."""
    data, off = text_bytes(table["text"])
    at = 0
    while at < table.num_rows:
        to = max(at + 1, int(np.searchsorted(off, off[at] + size, side="right")) - 1)
        yield table.slice(at, to - at), data[off[at] : off[to]], off[at : to + 1] - off[at]
        at = to


def sketch(docs: DataFrame, width: int, bands: int, rows: int, slice_bytes: int) -> DataFrame:
    """(doc_id, seq, again, keys): 128 bits of the SHA-256 of the words joined by one space, and the band keys."""

    def run(batches):
        for batch in batches:
            for part, data, off in _slices(batch, slice_bytes):
                who, key, weight, (starts, ends, first) = shingles(data, off, width)
                n = np.diff(first)
                spaced, into = joined(data, starts, ends)
                seq, again = digest(memoryview(spaced), into[first[:-1]], np.maximum(into[first[1:]] - 1, into[first[:-1]])).T.copy()
                z = signatures(who, key, weight.astype(float), len(n), bands * rows).reshape(len(n), bands, rows)
                keys = np.full((len(n), bands), 0, dtype=np.uint64)
                keys += np.arange(1, bands + 1, dtype=np.uint64) * _STEP
                for r in range(rows):
                    keys = mix(keys ^ z[:, :, r])
                ends = np.concatenate(([0], np.where(n > 0, bands, 0).cumsum())).astype(np.int32)
                flat = pa.ListArray.from_arrays(ends, keys[n > 0].reshape(-1).view(np.int64))
                yield pa.RecordBatch.from_arrays([part["doc_id"], pa.array(seq.view(np.int64)), pa.array(again.view(np.int64)), flat], ["doc_id", "seq", "again", "keys"])

    return docs.mapInArrow(run, "doc_id long, seq long, again long, keys array<long>")


def verify(pairs: DataFrame, width: int, threshold: float, slice_bytes: int) -> DataFrame:
    """The rows (a, b) of pairs (a, text_a, b, text_b) whose probability Jaccard reaches the threshold."""

    def run(batches):
        for batch in batches:
            a_data, a_off = text_bytes(batch["text_a"])
            b_data, b_off = text_bytes(batch["text_b"])
            at, n = 0, batch.num_rows
            while at < n:
                to = max(at + 1, int(np.searchsorted(a_off + b_off, a_off[at] + b_off[at] + slice_bytes, side="right")) - 1)
                sides = [shingles(d[o[at] : o[to]], o[at : to + 1] - o[at], width)[:3] for d, o in ((a_data, a_off), (b_data, b_off))]
                ok = similarities(*sides, to - at) >= threshold - 1e-9
                yield pa.RecordBatch.from_arrays([batch["a"].slice(at, to - at).filter(pa.array(ok)), batch["b"].slice(at, to - at).filter(pa.array(ok))], ["a", "b"])
                at = to

    return pairs.mapInArrow(run, "a long, b long")


def lone_weight(texts: DataFrame, width: int, slice_bytes: int) -> DataFrame:
    """(rep, lone, whole): the weight of each document in shingles that no other of texts (rep, text) has."""

    def run(batches):
        for batch in batches:
            for part, data, off in _slices(batch, slice_bytes):
                who, key, count, *_ = shingles(data, off, width)
                whole = np.bincount(who, weights=count, minlength=part.num_rows).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), part["rep"].take(pa.array(who)), pa.array(count.astype(np.int32)), pa.array(whole[who])], ["shingle", "rep", "weight", "whole"])

    rows = texts.mapInArrow(run, "shingle long, rep long, weight int, whole long")
    one = rows.groupBy("shingle").agg(F.count(F.lit(1)).alias("n"), F.min("rep").alias("rep"), F.min("weight").alias("weight"), F.min("whole").alias("whole")).where("n = 1")
    return one.groupBy("rep").agg(F.sum("weight").alias("lone"), F.min("whole").alias("whole"))


def zone_links(members: DataFrame, width: int, threshold: float, block_bytes: int, block_rows: int) -> DataFrame:
    """Verified links (a, b) of members (zone, rep, label, text) between classes of a zone: all that there
    are up to one a document and other class, by blocks of bounded size."""
    sized = members.withColumn("bytes", F.octet_length("text"))
    per_class = sized.groupBy("zone", "label").agg(F.count(F.lit(1)).alias("n"), F.sum("bytes").alias("bytes"))
    parts = lambda n, size: F.greatest(F.ceil(n / block_rows), F.ceil(size / block_bytes)).cast("int")
    zones = per_class.groupBy("zone").agg(F.max_by("label", F.struct("n", "label")).alias("major"), F.max(F.struct("n", "label", "bytes")).alias("m"), F.sum("n").alias("n"), F.sum("bytes").alias("bytes"))
    zones = zones.select("zone", "major", parts(F.col("n") - F.col("m.n"), F.col("bytes") - F.col("m.bytes")).alias("gq"), parts(F.col("n"), F.col("bytes")).alias("gt")).where("gq > 0")
    placed = sized.drop("bytes").hint("merge").join(zones, "zone")
    own = lambda g, seed: F.pmod(F.xxhash64("rep", F.lit(seed)), F.col(g)).cast("int")
    every = lambda g: F.explode(F.sequence(F.lit(0), F.col(g) - 1))
    query = placed.where("label != major").select("zone", own("gq", 1).alias("i"), every("gt").alias("j"), F.lit(True).alias("query"), "rep", "label", "text")
    target = placed.select("zone", every("gq").alias("i"), own("gt", 2).alias("j"), F.lit(False).alias("query"), "rep", "label", "text")

    def run(table):
        asks = table["query"].to_numpy(zero_copy_only=False)
        sides, ids, labels = [], [], []
        for side in (asks, ~asks):
            part = table.filter(pa.array(side)).combine_chunks()
            data, off = text_bytes(part["text"])
            sides.append(shingles(data, off, width)[:3])
            ids.append(part["rep"].to_numpy()), labels.append(part["label"].to_numpy())
        i, j = close_pairs(*sides, len(ids[0]), len(ids[1]), threshold)
        other = labels[0][i] != labels[1][j]
        i, j = i[other], j[other]
        one = np.unique(np.stack((ids[0][i], labels[1][j])), axis=1, return_index=True)[1] if len(i) else np.zeros(0, dtype=int)
        a, b = ids[0][i[one]], ids[1][j[one]]
        return pa.table({"a": np.minimum(a, b).astype(np.int64), "b": np.maximum(a, b).astype(np.int64)})

    # one key, for else the rows of a zone, dealt by zone already, would all stay in one task
    cells = query.unionByName(target).withColumn("cell", F.struct("zone", "i", "j")).drop("zone", "i", "j")
    return cells.groupBy("cell").applyInArrow(run, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, width: int = 5, threshold: float = 0.8, bands: int = 24, rows: int = 5, small: int = 10, slice_bytes: int = 400_000, turns: int = 1, block_bytes: int = 1_000_000, block_rows: int = 700) -> DataFrame:
    """(doc_id, class_id, class_size, kept, copies) - one row per input row.

    class_id: the smallest doc_id that a document is linked to, over any number of links; documents are
    linked where the probability Jaccard of their shingles of ``width`` words, weighted by count, is the
    threshold or more. class_size counts rows; kept marks the rows of the smallest id. copies counts the rows
    of the same sequence of words. Words are the runs without ASCII white space; fewer than ``width`` words
    make one shingle, and a text without words (null, empty) is linked to none. Rows without a doc_id are
    classes of their own (class_id null, kept). Rows of the same doc_id are one document. A pair at the
    threshold shares a band with probability 1 - (1 - threshold**rows)**bands, 0.9999 by default. All links of
    pairs that share a band take effect. small, turns and the blocks change the work, not the classes.
    """
    spark = docs.sparkSession
    folder = shared_folder(spark, "near-duplicates")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    marks = store(sketch(docs, width, bands, rows, slice_bytes), f"{folder}/marks")
    worded = marks.where(F.col("doc_id").isNotNull() & (F.size("keys") > 0))
    copies = worded.groupBy("seq", "again").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.first("keys").alias("keys"))
    copies = store(copies, f"{folder}/copies")
    banded = copies.select("rep", F.explode("keys").alias("key"))
    crowded = banded.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("rep").alias("centre"), F.max("rep").alias("last")).where("centre != last")
    buckets = store(banded.hint("merge").join(crowded.select("key", "n", "centre"), "key"), f"{folder}/buckets")
    # the representatives that meet any other, with their texts
    involved = buckets.select(F.col("rep").alias("doc_id")).distinct()
    texts = store(docs.where(F.col("doc_id").isNotNull()).hint("merge").join(involved, "doc_id"), f"{folder}/texts")
    a, b = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b"))

    def compared(pairs: DataFrame, name: str) -> DataFrame:
        pairs = pairs.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        return store(verify(pairs.hint("merge").join(a, "a").hint("merge").join(b, "b"), width, threshold, slice_bytes), f"{folder}/{name}")

    # first every member meets one centre, the smallest of its buckets: links of a forest
    nearest = buckets.groupBy("rep").agg(F.min("centre").alias("centre")).where("rep != centre")
    links = compared(nearest.select(F.col("centre").alias("a"), F.col("rep").alias("b")), "links0")
    labels = roots(links)

    def merged(found: DataFrame, name: str) -> DataFrame:
        """labels after the classes that found joins have become one."""
        of = lambda end: labels.select(F.col("node").alias(end), F.col("label").alias(f"l{end}"))
        between = found.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b"))
        joined = components(between)
        known = labels.unionByName(found.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(labels.select("node"), "node", "left_anti").withColumn("label", F.col("node")))
        return store(known.join(joined.select(F.col("node").alias("label"), F.col("label").alias("further")), "label", "left").select("node", F.coalesce("further", "label").alias("label")), f"{folder}/{name}")

    def mixed(name: str, among: DataFrame, *more) -> DataFrame:
        """The rows of among in buckets that hold several classes."""
        classed = among.hint("merge").join(labels.select(F.col("node").alias("rep"), "label"), "rep", "left").select("key", "rep", "n", F.coalesce("label", "rep").alias("label"))
        split = classed.groupBy("key").agg(F.min("label").alias("least"), F.max("label").alias("most"), *more).where("least != most").drop("least", "most")
        return store(classed.hint("merge").join(split, "key"), f"{folder}/{name}")

    for turn in range(1, turns + 1):
        # a member of a large bucket meets two centres of other classes in a turn
        rest = mixed(f"rest{turn}", buckets, *(F.min_by(F.struct("rep", "label"), F.xxhash64("rep", F.lit(2 * turn + i))).alias(f"c{i}") for i in (0, 1)))
        large = rest.where(F.col("n") > small).select("rep", "label", F.explode(F.array("c0", "c1")).alias("c")).where("c.label != label")
        order = F.xxhash64("rep", "c.rep", F.lit(turn))
        two = large.groupBy("rep").agg(F.min_by("c.rep", order).alias("x"), F.max_by("c.rep", order).alias("y"))
        pairs = two.select(F.explode(F.array("x", "y")).alias("a"), F.col("rep").alias("b"))
        if turn == 1:
            few = rest.where(F.col("n") <= small).select("key", "rep", "label")
            other = few.select("key", F.col("rep").alias("b"), F.col("label").alias("other"))
            pairs = pairs.unionByName(few.hint("merge").join(other, "key").where("rep < b and label != other").select(F.col("rep").alias("a"), "b"))
        labels = merged(compared(pairs, f"links{turn}"), f"labels{turn}")
    # the exact end of large buckets
    rest = mixed("open", buckets.where(F.col("n") > small)).select("key", "rep", "n")
    reps = rest.select("rep").distinct()
    lone = lone_weight(texts.withColumnRenamed("doc_id", "rep").hint("merge").join(reps, "rep"), width, slice_bytes).where(F.col("whole") - F.col("lone") < (threshold - 1e-9) * F.col("whole"))
    rest = mixed("linkable", rest.join(store(lone.select("rep"), f"{folder}/lone"), "rep", "left_anti"))
    if not rest.isEmpty():
        zones = components(rest.join(rest.groupBy("key").agg(F.min("rep").alias("centre")), "key").select(F.col("centre").alias("a"), F.col("rep").alias("b")).distinct())
        members = zones.select(F.col("node").alias("rep"), F.col("label").alias("zone")).join(rest.select("rep", "label").distinct(), "rep")
        found = zone_links(members.hint("merge").join(texts.withColumnRenamed("doc_id", "rep"), "rep"), width, threshold, block_bytes, block_rows)
        labels = merged(store(found, f"{folder}/zone-links"), "labels-end")
    classes = copies.join(labels.select(F.col("node").alias("rep"), "label"), "rep", "left").select("seq", "again", "copies", F.coalesce("label", "rep").alias("class_id"))
    sizes = classes.groupBy("class_id").agg(F.sum("copies").alias("class_size"))
    known = worded.select("doc_id", "seq", "again").join(classes, ["seq", "again"]).join(sizes, "class_id").select("doc_id", "class_id", "class_size", "copies")
    alone = marks.where(F.col("doc_id").isNull() | (F.size("keys") == 0)).select("doc_id", F.col("doc_id").alias("class_id"), F.lit(1).cast("long").alias("class_size"), F.lit(1).cast("long").alias("copies"))
    return known.unionByName(alone).select("doc_id", "class_id", "class_size", F.col("doc_id").eqNullSafe(F.col("class_id")).alias("kept"), "copies")
