import random

import numpy as np
import pytest

from edgegraph.llm import near_dedup as N
from edgegraph.llm.links import components


def weighted(text, width=5):
    w = text.split()
    out = {}
    for s in [tuple(w[i : i + width]) for i in range(len(w) - width + 1)] or ([tuple(w)] if w else []):
        out[s] = out.get(s, 0) + 1
    return out


def jaccard(a, b):
    keys = a.keys() | b.keys()
    return sum(1 / sum(max(a.get(y, 0) / a[x], b.get(y, 0) / b[x]) for y in keys) for x in a.keys() & b.keys())


def test_probability_jaccard_matches_its_definition():
    rng = random.Random(1)
    sets = [{i: rng.randint(1, 4) for i in rng.sample(range(12), rng.randint(1, 9))} for _ in range(40)]
    pair, a, b, want = [], [], [], []
    for p in range(20):
        x, y = sets[2 * p], sets[2 * p + 1]
        want.append(jaccard(x, y))
        for k in x.keys() | y.keys():
            pair.append(p), a.append(x.get(k, 0)), b.append(y.get(k, 0))
    got = N.probability_jaccard(np.array(pair), np.array(a, float), np.array(b, float), 20)
    assert np.allclose(got, want)


def test_signatures_estimate_it():
    rng = np.random.default_rng(0)
    ids, w = np.arange(300), rng.integers(1, 5, 300)
    sets = [(ids[:250], w[:250]), (ids[40:], w[40:])]
    who = np.concatenate([np.full(len(x), i) for i, (x, _) in enumerate(sets)])
    key = N.mix(np.concatenate([x for x, _ in sets]).astype(np.uint64) + np.uint64(99))
    z = N.signatures(who, key, np.concatenate([y for _, y in sets]).astype(float), 2, 4000)
    want = jaccard(*(dict(zip(x.tolist(), y.tolist())) for x, y in sets))
    assert abs((z[0] == z[1]).mean() - want) < 4 * (want * (1 - want) / 4000) ** 0.5


def test_components(spark):
    rng = random.Random(2)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(160)] + [(1000 + i, 1001 + i) for i in range(40)]
    parent = {}
    find = lambda x: x if parent.setdefault(x, x) == x else find(parent[x])
    for a, b in links:
        if a != b:
            a, b = find(a), find(b)
            parent[max(a, b)] = min(a, b)
    got = {r.node: r.label for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: find(x) for x in got} and set(got) == {x for p in links if p[0] != p[1] for x in p}


def brute(rows, threshold):
    label = {d: d for d, _ in rows}
    find = lambda x: x if label[x] == x else find(label[x])
    sets = [(d, weighted(t or "")) for d, t in rows]
    for i, (d, a) in enumerate(sets):
        for e, b in sets[:i]:
            if a and b and (a == b or jaccard(a, b) >= threshold):
                x, y = find(d), find(e)
                label[max(x, y)] = min(x, y)
    return {d: find(d) for d, _ in rows}


@pytest.mark.parametrize("seed", [1, 2])
def test_classes_match_brute_force(spark, seed):
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(900)]
    text = lambda k: [rng.choice(vocab) for _ in range(k)]
    rows, n = [], 0
    for _ in range(14):
        base = text(rng.randint(3, 160))
        for _ in range(rng.randint(1, 9)):
            w = list(base)
            for _ in range(rng.choice([0, 0, 1, 1, 2, 6])):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            rows.append((n := n + 1, rng.choice([" ", "\n"]).join(w)))
    common = text(60)  # a passage that many different texts share
    rows += [(n := n + 1, " ".join(common + text(45))) for _ in range(25)]
    rng.shuffle(rows)
    rows += [(9001, None), (9002, ""), (9003, " \n"), (9004, "a b"), (9005, "a  b")]
    docs = spark.createDataFrame([(d, t, 1, "k") for d, t in rows], "doc_id long, text string, class_id int, keys string")
    got = N.near_duplicates(docs).collect()
    want = brute(rows, 0.8)
    assert {r.doc_id: r.class_id for r in got} == want and len(got) == len(rows)
    sizes = {c: sum(x == c for x in want.values()) for c in want.values()}
    assert all(r.class_size == sizes[r.class_id] and r.kept == (r.doc_id == r.class_id) for r in got)


def test_close_pairs_match_the_definition():
    rng = random.Random(4)
    sets = [{i: rng.choice([1, 1, 1, 3]) for i in range(20) if rng.random() < 0.93} for _ in range(90)] + [{i: 1 for i in range(20 + k % 3)} for k in range(30)]
    sides = []
    for part in (sets[:50], sets[50:]):
        flat = [(i, k, v) for i, x in enumerate(part) for k, v in sorted(x.items())]
        sides.append((np.array([f[0] for f in flat]), np.array([f[1] for f in flat], dtype=np.uint64), np.array([f[2] for f in flat])))
    want = {(i, j) for i, a in enumerate(sets[:50]) for j, b in enumerate(sets[50:]) if jaccard(a, b) >= 0.8}
    for chunk in (60, 1 << 20):
        got = N.close_pairs(*sides, 50, len(sets) - 50, 0.8, chunk)
        assert set(zip(*(x.tolist() for x in got))) == want and 0 < len(want) < 50 * 70


def test_shared_weights_of_rare_and_frequent_shingles():
    rng = np.random.default_rng(3)
    x = (rng.random((150, 400)) < np.where(np.arange(400) < 20, 0.6, 0.01)) * rng.integers(1, 4, (150, 400))
    sides = []
    for part in (x[:70], x[70:]):
        who, key = np.nonzero(part)
        sides.append((who, key.astype(np.uint64), part[who, key]))
    s, u = N.shared_weights(*sides, 70, 80, 2000)
    assert np.array_equal(s, x[:70] @ (x[70:] > 0).T) and np.array_equal(u, (x[:70] > 0) @ x[70:].T)


def test_a_large_group_of_chained_copies_matches_brute_force(spark):
    rng = random.Random(7)
    vocab = [f"w{i}" for i in range(500)]
    base = [rng.choice(vocab) for _ in range(70)]
    family = [base]
    while len(family) < 110:  # edits of edits: many pairs on either side of the threshold
        w = list(rng.choice(family[-40:]))
        for _ in range(rng.choice([1, 1, 2])):
            w[rng.randrange(len(w))] = rng.choice(vocab[:9])
        family.append(w)
    rows = [(i, " ".join(w)) for i, w in enumerate(rng.sample(family, len(family)))]
    want = brute(rows, 0.8)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for blocks in ({}, {"block_rows": 16, "turns": 0, "small": 1}):
        assert {r.doc_id: r.class_id for r in N.near_duplicates(docs, **blocks).collect()} == want
    assert 1 < len(set(want.values())) < len(rows)


def test_odd_rows(spark):
    t = "one two three four five six seven"
    docs = spark.createDataFrame([(None, t), (1, t), (1, t), (2, t + "\n")], "doc_id long, text string")
    assert sorted((str(r.doc_id), str(r.class_id), r.class_size) for r in N.near_duplicates(docs).collect()) == [("1", "1", 3), ("1", "1", 3), ("2", "1", 3), ("None", "None", 1)]
    assert N.near_duplicates(docs.limit(0)).count() == 0
