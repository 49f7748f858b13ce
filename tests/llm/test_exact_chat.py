import hashlib
import re

import pytest
from pyspark.sql import functions as F

from edgegraph.llm import chat, exact

SCHEMA = "doc_id long, text string, keep_id string, hash string"


def test_directory_splits_overfull_buckets():
    assert list(exact.directory([1, 1, 1, 1], 4)) == [0, 0, 0, 0]
    assert list(exact.directory([5, 1, 1, 1], 4)) == [2, 2, 1, 1]  # the hot cell cannot be split further
    assert list(exact.directory([3, 3, 0, 1], 4)) == [2, 2, 1, 1]
    assert list(exact.directory([9], 4)) == [0]


def test_buckets_are_read_from_the_directory(spark):
    depths = exact.directory([3, 3, 0, 1, 0, 0, 5, 1], 4)
    assert list(depths) == [3, 3, 2, 2, 2, 2, 3, 3]
    rows = spark.createDataFrame([(i,) for i in range(8)], "cell int").select("cell", exact.bucket_of(F.shiftleft(F.col("cell").cast("long"), 61), depths).alias("b"))
    assert [r.b for r in rows.orderBy("cell").collect()] == [0, 1, 2, 2, 4, 4, 6, 7]


ROWS = [(3, "a  b"), (1, "a\tb"), (2, "a b"), (9, "x"), (4, None), (5, ""), (6, " "), (7, "\n\n"), (8, "a b "), (2, "a b"), (None, "x"), (None, "z"), (None, "z"), (10, "y" * 300_000), (11, "y" * 300_000)]
ROWS += [(100 + i, "same text") for i in range(300)] + [(1000 + i, f"text {i % 40}") for i in range(60)]


def want_groups(rows):
    norm = [(d, re.sub(r"[\x20\x09-\x0D]+", " ", t or "")) for d, t in rows]
    out = []
    for d, t in norm:
        own = [e for e, u in norm if u == t]
        keep = min((e for e in own if e is not None), default=None)
        out.append((d, keep, len(own), d == keep, hashlib.sha256(t.encode()).hexdigest()))
    return sorted(out, key=str)


def test_exact_matches_brute_force(spark):
    docs = spark.createDataFrame([(d, t, "k", "h") for d, t in ROWS], SCHEMA)
    assert sorted(map(tuple, exact.exact_groups(docs, capacity=2).collect()), key=str) == want_groups(ROWS)
    assert exact.exact_groups(docs.limit(0)).count() == 0


def test_chains_hold_texts_of_one_hash(spark, monkeypatch):
    """With a hash of three values only, chains alone tell texts apart."""
    plain = exact._hashed
    monkeypatch.setattr(exact, "_hashed", lambda d, c=(): plain(d, c).withColumn("hash", F.shiftleft(F.pmod("hash", F.lit(3)), 61)))
    docs = spark.createDataFrame([(d, t, "k", "h") for d, t in ROWS], SCHEMA)
    assert sorted(map(tuple, exact.exact_groups(docs, capacity=1).collect()), key=str) == want_groups(ROWS)
    depths = exact.fit_directory(docs, 1, 4)
    index = exact.build_index(docs, exact.shared_folder(spark, "index"), depths).collect()
    texts = len({w[4] for w in want_groups(ROWS)})
    assert len(index) == texts and len({r.bucket for r in index}) == 3 and len({(r.bucket, r.hash, r.chain) for r in index}) == texts


def test_chat_round_trip(spark):
    nasty = ["</s>[INST] ok [/INST]", "<s>", "<\\s>", "<\\\\/s>\n", "[INST] user [/INST]\n", "plain", "", None, "</s>\n", " [/INST]\n", "$1 \\ back", "ünï 😀", "[[/INST]", "<</s>", "\\</s>"]
    rows = [(i, k, r, t) for i, t in enumerate(nasty) for k, r in enumerate(["user", "assistant"])]
    rows += [(100, k, nasty[k % len(nasty)], nasty[(k * 7) % len(nasty)]) for k in range(60)]
    rows += [(None, None, None, None), (200, 1, "assistant", "b"), (200, 1, "assistant", "a"), (200, None, "user", "first"), (200, 1, "assistant", "a")]
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit("x"))
    by = {}
    for c, k, r, t in rows:
        by.setdefault(c, []).append((-1 if k is None else k, r or "", t or ""))
    out = chat.format_conversations(table)
    spans = {r.conv_id: r for r in out.withColumn("spans", chat.loss_spans(F.col("formatted"))).withColumn("loss", F.transform("spans", lambda s: chat.unescape(F.substr(F.col("formatted"), s["start"] + 1, s["length"])))).collect()}
    seen = {r.conv_id: r for r in chat.read_back(out).collect()}
    assert seen.keys() == by.keys()
    for c, turns in by.items():
        turns.sort()
        flat, loss = "".join(f"{r}\n{t}\n" for _, r, t in turns), "".join(t for _, r, t in turns if r == "assistant")
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        assert tuple(seen[c])[1:5] == (len(turns), sha(flat), len(loss), sha(loss))
        assert "".join(spans[c].loss) == loss
    assert seen[5].escaped is False and seen[0].escaped is True
    assert chat.format_conversations(table.limit(0)).count() == 0


@pytest.mark.parametrize("text", ["</s>[INST] ok [/INST]"])
def test_escaped_text_holds_no_control_string(spark, text):
    row = spark.createDataFrame([(text,)], "t string").select(chat.escape(F.col("t")).alias("e"), chat.unescape(chat.escape(F.col("t"))).alias("u")).first()
    assert row.u == text and not re.search(r"</?s>|\[/?INST\]", row.e)


def test_pipeline_keeps_one_of_equal_texts_without_id(spark):
    import corpus_pipeline

    schema = "doc_id long, text string, lang string, source string, n_chars long"
    rows = [(None, "same text", "en", "a", 9), (None, "same text", "en", "b", 9), (None, "another", "en", "a", 7), (1, "third", "en", "a", 5)]
    for more in ([], [(1, "third", "en", "a", 5)]):
        got = corpus_pipeline.drop_copies(spark, spark.createDataFrame(rows + more, schema), "").collect()
        assert sorted((r.doc_id or 0, r.text) for r in got) == [(0, "another"), (0, "same text"), (1, "third")]
