"""Texts made to collide under polynomial hashes modulo a power of two."""

from edgegraph.llm.near_dedup import near_duplicates
from edgegraph.llm.rolling import Prefix
from edgegraph.llm.substring import repeated_passages
from edgegraph.llm.suffix import repeated_spans
import numpy as np


def twins(n=2048):
    """Two different words of two letters whose difference has the form of a Thue-Morse word."""
    signs = [bin(i).count("1") & 1 for i in range(n)]
    return "".join("ab"[s] for s in signs), "".join("ba"[s] for s in signs)


def test_hashes_tell_them_apart():
    a, b = (Prefix.of_bytes(np.frombuffer(t.encode(), dtype=np.uint8)).every(2048)[0] for t in twins())
    assert a != b


def test_nothing_is_removed_or_merged(spark):
    a, b = twins()
    tail = " ".join(f"word{i}" for i in range(49))
    docs = spark.createDataFrame([(1, f"{a} {tail}"), (2, f"{b} {tail}"), (3, a), (4, b)], "doc_id long, text string")
    assert {r.doc_id: r.n_removed for r in repeated_passages(docs, digest=True).collect()} == {1: 0, 2: 0, 3: 0, 4: 0}
    near = near_duplicates(docs.where("doc_id > 2")).collect()
    assert {(r.doc_id, r.class_id, r.copies) for r in near} == {(3, 3, 1), (4, 4, 1)}
    # shingles: 45 of 46 are shared by 1 and 2, so they are near copies but no copies
    assert {r.copies for r in near_duplicates(docs).collect()} == {1}


def test_spans_of_them(spark):
    from .test_repeats import brute_bytes

    a, b = twins()
    rows = [(1, a), (2, b), (3, "x" + a[:700])]
    got = [tuple(r) for r in repeated_spans(spark.createDataFrame(rows, "doc_id long, text string"), digest=True).collect()]
    assert sorted(got) == sorted(brute_bytes(rows, 200))
