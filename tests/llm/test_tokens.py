"""Encoder, counts and packing against the tokenizers library."""

import hashlib

import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
import public_tokenizers as P
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from edgegraph.llm import bpe, packing, token_counts

PATH = P.path("byte_bpe_50k.json")
PARTS = ["a", "b", " ", "  ", "\n", "\t", "'s", "'ll", "é", "ß", "²", "½", "１", "中文", "😀", " ", " ", "\x1c", "\x85", "<|endoftext|>", "_", "-", "!!", "1", "23", "the", " the", "Ⅷ", "é", "\x00", "ª", "​", "'S", "x" * 30]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def cases(n, seed=0):
    rng = random.Random(seed)
    return ["".join(rng.choice(PARTS) for _ in range(rng.randint(0, 40))) for _ in range(n)]


def test_encoders_match_the_library(library):
    own, count, fast = bpe.load(PATH), token_counts.counter(PATH), bpe.library_encoder(PATH)
    texts = cases(6000)
    for t, e in zip(texts, library.encode_batch(texts, add_special_tokens=False)):
        ids = np.frombuffer(own.encode(t), dtype="<u4")
        assert ids.tolist() == e.ids == fast(t).tolist() and count(t) == len(e.ids)
        assert own.decode(ids) == t.encode()


def test_random_letters_and_bytes_match_plain_merging():
    own, rng = bpe.load(PATH), random.Random(3)
    for _ in range(3000):
        t = "".join(chr(rng.choice([rng.randrange(256), rng.randrange(97, 123)])) for _ in range(rng.randint(1, 14)))
        assert [own.token_of[i] for i in own.encode_bytes(t)] == own.merge(t)


def test_every_whole_token_is_proven_by_merging():
    own, rng = bpe.load(PATH), random.Random(5)
    for t in rng.sample(sorted(own.ids), 3000):
        assert (t in own.single) == (own.merge(t) == [t])


def docs(spark):
    rows = [(i, t) for i, t in enumerate(cases(300, 7))] + [(None, "null id"), (5, None), (5, ""), (5, "a b"), (9000, "word " * 9000), (9001, "<|endoftext|>" * 10)]
    return rows, spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, n_tokens int")


def test_encode_decode_frames(spark):
    rows, table = docs(spark)
    back = bpe.decode(bpe.encode(table, PATH), PATH)
    assert sorted(map(str, ((r.doc_id, r.text) for r in back.collect()))) == sorted(map(str, ((d, t or "") for d, t in rows)))
    assert bpe.round_trip(table.limit(0), PATH).count() == 0


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"])
def test_counts_of_all_kinds(spark, name):
    import sentencepiece

    rows, table = docs(spark)
    path = P.path(name)
    ids = sentencepiece.SentencePieceProcessor(model_file=path).encode if name.endswith(".model") else lambda t: Tokenizer.from_file(path).encode(t, add_special_tokens=False).ids
    if not name.endswith(".model"):
        tk = Tokenizer.from_file(path)
        ids = lambda t: tk.encode(t, add_special_tokens=False).ids
    got = token_counts.token_counts(table, path, limit=20)
    want = [(d, len((t or "").encode()), n := len(ids(t or "")), n > 20) for d, t in rows]
    assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want))


def test_packing_covers_every_id_once(spark, library):
    rows, table = docs(spark)
    rows, table = [r for r in rows if r[0] != 5], table.where("doc_id is null or doc_id != 5")
    pieces = packing.pack(table.repartition(3), PATH, size=256, round_tokens=5000, with_ids=True).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for p in pieces:
        by_doc[p.doc_id].append(p)
        by_seq[p.sequence_id].append(p)
        assert p.ids_crc32 == zlib.crc32(np.array(p.ids, dtype="<u4").tobytes()) and len(p.ids) == p.length
    for d, t in rows:
        got = [i for p in sorted(by_doc[d], key=lambda p: p.start) for i in p.ids]
        assert got == [*library.encode(t or "", add_special_tokens=False).ids, 1]
        assert all(p.doc_tokens == len(got) for p in by_doc[d])
    for s in by_seq.values():
        at = 0
        for p in sorted(s, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= 256 and at & (at - 1) == 0  # full, or a power of two


def test_packing_balances_cost():
    rng = np.random.default_rng(0)
    lengths = rng.integers(1, 500, 4000).tolist()
    out = packing.assign(lengths, 2048, 1.0, 1 / 1024)
    cost = defaultdict(float)
    for _, _, n, s, _ in out:
        cost[s] += n + n * n / 1024
    full = [c for c in cost.values() if c > 2048]
    assert np.std(full) / np.mean(full) < 0.05
    assert packing.assign([], 2048, 1.0, 0.0) == []


def test_null_and_repeated_rows(spark):
    table = spark.createDataFrame([(5, None), (5, ""), (5, "a b"), (5, "a b")], "doc_id long, text string")
    got = packing.pack(table, PATH, size=4).agg(F.sum("length")).first()[0]
    assert got == 1 + 1 + 3 + 3


LONG = [" " * 1_000_000, "\n" * 1_000_000, " \n" * 300_000, "a" * 100_000, "7" * 200_000, "\u3000" * 50_000, "x" + " " * 150_000 + "y", "!" * 100_000]


def test_very_long_runs_match_the_library(spark, library):
    """Operators 1, 2 and 4 on texts that are one run of a kind."""
    own, fast, count = bpe.load(PATH), bpe.library_encoder(PATH), token_counts.counter(PATH)
    for t in LONG:
        want = library.encode(t, add_special_tokens=False).ids
        assert np.frombuffer(own.encode(t), dtype="<u4").tolist() == want == fast(t).tolist() and count(t) == len(want)
    table = spark.createDataFrame(list(enumerate(LONG[:3])), "doc_id long, text string")
    assert packing.pack(table, PATH).agg({"length": "sum"}).first()[0] == sum(len(fast(t)) + 1 for t in LONG[:3])


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert packing.pack(none, PATH).count() == 0 and token_counts.token_counts(none, PATH).count() == 0
    assert bpe.encode(none, PATH).count() == 0 and bpe.decode(bpe.encode(none, PATH), PATH).count() == 0


def test_round_trip_matches_the_library(spark, library):
    rows, table = docs(spark)
    want = []
    for d, t in rows:
        ids = library.encode(t or "", add_special_tokens=False).ids
        sha = lambda x: hashlib.sha256(x).hexdigest()
        want.append((d, len(ids), sha(np.array(ids, dtype="<u4").tobytes()), sha(library.decode(ids, skip_special_tokens=False).encode())))
    assert sorted(map(tuple, bpe.round_trip(table, PATH).collect()), key=str) == sorted(want, key=str)
