import zlib

import numpy as np
from pyspark.sql import functions as F

from edgegraph.llm import ann, quality

ODD = "vec_id long, embedding array<float>, rank int, score string"


def test_recall_and_exact_scores(spark, sf):
    v = spark.read.parquet(f"{sf}/embeddings.parquet")
    ask = F.col("vec_id") % 20 == 0
    got = {(r.query_id, r.vec_id): r.score for r in ann.nearest(v, ask, block_rows=200).collect()}
    want = {(r.query_id, r.vec_id): r.score for r in ann.brute_force(v, ask).collect()}
    assert len(got) == len(want) and len(got.keys() & want.keys()) / len(want) >= 0.9
    assert all(abs(got[k] - want[k]) < 1e-12 for k in got.keys() & want.keys())


def _plain(x: np.ndarray, ids: np.ndarray, q: int, k: int) -> list[int]:
    score = np.where(np.arange(len(ids)) == q, -np.inf, (x * x[q]).sum(axis=1))
    return ids[np.lexsort((ids, -score))[:k]].tolist()


def test_brute_force_against_plain_products(spark):
    rng = np.random.default_rng(5)
    x, ids = rng.standard_normal((90, 6)).astype(np.float32).astype(float), np.arange(90)
    table = spark.createDataFrame([(int(i), x[i].tolist()) for i in ids], "vec_id long, embedding array<double>")
    got = ann.brute_force(table, F.col("vec_id") % 20 == 0, k=7, block_rows=40, query_rows=2).orderBy("query_id", "rank").collect()
    assert [r.vec_id for r in got] == [i for q in range(0, 90, 20) for i in _plain(x, ids, q, 7)]


def test_collisions_spare_products(spark):
    """On vectors of one length and of many lengths most of a block is never verified, and recall holds."""
    rng = np.random.default_rng(11)
    for spread in (0.0, 0.3):
        x = rng.standard_normal((6_000, 64))
        x *= np.exp(spread * rng.standard_normal((6_000, 1))) / np.linalg.norm(x, axis=1, keepdims=True)
        ids, largest = np.arange(6_000), float(np.linalg.norm(x, axis=1).max())
        block = ann.Block(ids, x, largest, np.random.default_rng(7).standard_normal((65, 512)), 48, 0.3, 0.95)
        hits = sum(len({*_plain(x, ids, q, 20)} & {*block.search(q, x[q], 20, 1.1)[0].tolist()}) for q in range(0, 1_000, 20))
        assert hits >= 0.9 * 50 * 20
        assert block.verified < (0.4 if spread == 0 else 0.9) * block.searched


def test_ties_repeats_and_odd_vectors(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((60, 8)).round(3)
    rows = [(i, x[i].tolist()) for i in range(60)] + [(100 + i, x[0].tolist()) for i in range(50)]
    rows += [(300, None), (301, [0.0] * 8), (302, [float("nan")] + [1.0] * 7), (303, [None] + [1.0] * 7), (304, []), (305, [1.0] * 3), (None, x[1].tolist()), (7, x[7].tolist()), (306, [float("inf")] * 8)]
    table = spark.createDataFrame([(i, v, 1, "s") for i, v in rows], ODD)
    ask = F.col("vec_id") % 20 == 0
    got = ann.nearest(table, ask, k=20, block_rows=40, sure=0.999).collect()
    want = ann.brute_force(table, ask, k=20).collect()
    first = sorted((r["rank"], r.vec_id) for r in got if r.query_id == 0)
    assert first == [(i + 1, 100 + i) for i in range(20)]
    assert {r.query_id for r in got} == {r.query_id for r in want} and max(r["rank"] for r in got) == 20
    few = table.where("vec_id in (0, 1, 2)")
    assert ann.nearest(few, ask).count() == 2
    assert ann.nearest(table.limit(0), ask).count() == 0


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality.fit_on(docs, labels, sample=1500)
    got = quality.quality_scores(docs.join(labels.select("doc_id"), "doc_id"), model).join(labels, "doc_id").where("held_out").collect()
    assert all(zlib.crc32(str(r.doc_id).encode()) % 4 == 2 for r in got)
    good, bad = [r.score for r in got if r.quality == 1], [r.score for r in got if r.quality == 0]
    auc = np.mean([(g > b) + 0.5 * (g == b) for g in good[:400] for b in bad])
    assert auc > 0.98 and np.mean([(r.predicted == 1) == (r.quality == 1) for r in got]) > 0.95


def test_odd_texts_and_no_labels(spark):
    docs = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (None, "a b", "x"), (3, " \n ", "x"), (3, "word " * 30_000, "x")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(1, None), (None, 1)], "doc_id long, quality int")
    model = quality.fit_on(docs, labels)
    got = quality.quality_scores(docs, model, carry=("score",)).collect()
    assert len(got) == 5 and all(0 <= r[2] <= 1 for r in got)
    assert quality.quality_scores(docs.limit(0), model).count() == 0


def test_votes_match_brute_force(spark):
    """Every score against all labelled vectors one by one, and the fit against the fit on one machine."""
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = quality.fit_on(docs, labels)
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    known = sorted((r.doc_id, texts[r.doc_id], r.quality) for r in labels.collect() if zlib.crc32(str(r.doc_id).encode()) % 4 != 2)
    alone = quality.fit([t for _, t, _ in known], [float(q) for _, _, q in known])
    assert alone.vocabulary == model.vocabulary and np.allclose(alone.idf, model.idf) and alone.prior == model.prior
    got = {r.doc_id: r.score for r in quality.quality_scores(docs, model).collect()}
    for d in sorted(texts)[::7]:
        v = model.embed([texts[d]])[0]
        near = sorted(((float(v @ w), float(y)) for w, y in zip(model.vectors, model.labels)), reverse=True)[: model.neighbours]
        weight = [max(c, 0.0) ** model.sharpness for c, _ in near]
        want = (sum(w * y for w, (_, y) in zip(weight, near)) + 1e-3 * model.prior) / (sum(weight) + 1e-3)
        assert abs(got[d] - want) < 1e-3
        assert abs(got[d] - alone.score([texts[d]])[0]) < 0.05


def test_shapes_and_facts_hold_for_any_length():
    assert quality.shape("Aa9!" * 5) == "Aa9!" * 5
    few, many = (quality._facts(t, t.split())[0] for t in ("a b " * 30, "a b " * 3000))
    assert few.startswith("\nrepeated words 1") and many.startswith("\nrepeated words 1")
