"""The stages of the corpus pipeline on odd rows, and run() against plain Python for all but the classifier."""

import random
import re

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as P
from edgegraph.llm import near_dedup

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def rows():
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 8)))
    text = lambda n: " ".join(word() for _ in range(n))
    shared, base = text(60), text(120).split()
    near = list(base)
    near[60] = "changed"
    out = [(1, " ".join(base)), (2, " ".join(near)), (3, " ".join(base)), (4, text(30) + "\n" + shared + "\n" + text(30)), (5, text(40) + " " + shared), (6, text(50))]
    out += [(7, None), (8, ""), (9, " \n "), (None, "no id at all"), (None, "no id at all"), (10, "long " + "x" * 200_000), (11, text(50)), (11, out[5][1]), (6, out[5][1])]
    return [(d, t, "en", None if d == 6 else "web", 0 if t is None else len(t)) for d, t in out]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA)


def test_every_stage_on_odd_rows_and_empty_tables(spark, sf, docs):
    for name, stage in P.STAGES:
        none = stage(spark, docs.limit(0), sf)
        some = stage(spark, docs.withColumns({"hash": F.lit("x"), "score": F.lit(1), "key": F.lit(None).cast("string")}), sf)
        assert none.count() == 0 and none.columns == some.columns
        if name != "packing":
            assert some.columns == list(P.COLUMNS) and some.count() <= docs.count()
        else:
            assert some.where("start = 0").count() == docs.count()


def test_exact_stage(spark, sf, docs):
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    kept = {(d, norm(t)) for d, t, *_ in rows()}
    least = {}
    for d, t in kept:
        least.setdefault(t, []).append(d)
    want = {(min((x for x in ids if x is not None), default=None), t) for t, ids in least.items()}
    got = [(r.doc_id, norm(r.text)) for r in P.drop_copies(spark, docs, sf).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)


def test_near_and_substring_stages(spark, sf, docs):
    kept = P.drop_near_copies(spark, docs, sf).select("doc_id").collect()
    gone = {r.doc_id for r in near_dedup.near_duplicates(docs).where("not kept").collect()}
    assert {2, 3} <= gone and {r.doc_id for r in kept} == {d for d, *_ in rows()} - gone
    cut = {r.doc_id: r for r in P.cut_passages(spark, docs.where("doc_id in (4, 5, 7, 10)"), sf).collect()}
    own = {d: t for d, t, *_ in rows()}
    assert cut[4].text == own[4] and cut[5].text == " ".join(own[5].split()[:40]) and cut[5].n_chars == len(cut[5].text)
    assert cut[10].text == own[10] and cut[7].text == ""


def test_run_equals_its_stages_one_by_one(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    table = [tuple(r) for r in docs.collect()]
    for _, stage in P.STAGES[:-1]:
        frame = stage(spark, spark.createDataFrame(table, docs.schema) if table else docs.limit(0), sf)
        table = [tuple(r) for r in frame.collect()]
    got = P.run(spark, sf).collect()
    per = {}
    for r in got:
        per.setdefault(r.doc_id, []).append((r.start, r.length, r.doc_tokens))
    assert per.keys() == {r[0] for r in table}
    for d, pieces in per.items():
        pieces.sort()
        assert pieces[0][0] == 0 and sum(n for _, n, _ in pieces) == pieces[0][2] and all(a + n == b for (a, n, _), (b, _, _) in zip(pieces, pieces[1:]))
