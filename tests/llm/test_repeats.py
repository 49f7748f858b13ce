"""Substring and suffix-array dedup against brute force."""

import hashlib
import random
import re
from collections import defaultdict

import pytest

from edgegraph.llm.substring import repeated_passages
from edgegraph.llm.suffix import repeated_spans


def sha(x: bytes) -> str:
    return hashlib.sha256(x).hexdigest()


def brute_words(rows, width):
    words = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for _, t in rows]
    where = defaultdict(list)
    key = lambda d: -(2**63) if d is None else d
    for (d, _), w in zip(rows, words):
        for i in range(len(w) - width + 1):
            where[tuple(w[i : i + width])].append(key(d))
    out = []
    for (d, _), w in zip(rows, words):
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            if min(where[tuple(w[i : i + width])]) < key(d):
                gone[i : i + width] = [True] * width
        kept = " ".join(x for x, g in zip(w, gone) if not g)
        out.append((d, len(w), sum(gone), sha(kept.encode())))
    return out


def brute_bytes(rows, width):
    texts = [(t or "").encode() for _, t in rows]
    count = defaultdict(int)
    for t in texts:
        for i in range(len(t) - width + 1):
            count[t[i : i + width]] += 1
    out = []
    for (d, _), t in zip(rows, texts):
        gone = [False] * len(t)
        for i in range(len(t) - width + 1):
            if count[t[i : i + width]] > 1:
                gone[i : i + width] = [True] * width
        spans = sum(g and not p for g, p in zip(gone, [False, *gone]))
        out.append((d, len(t), sum(gone), spans, sha(bytes(b for b, g in zip(t, gone) if not g))))
    return out


def corpus(seed, n=60):
    rng = random.Random(seed)
    vocab = ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(1, 9))) for _ in range(400)]
    text = lambda k: " ".join(rng.choice(vocab) for _ in range(k))
    passages = [text(rng.randint(20, 90)) for _ in range(6)]
    rows = []
    for i in range(n):
        parts = [text(rng.randint(0, 60))]
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            a, b = sorted(rng.sample(range(len(p)), 2)) if rng.random() < 0.5 else (0, len(p))
            parts += [p[a:b], text(rng.randint(0, 20))]
        rows.append((i * 3 % 71, rng.choice([" ", "\n", " \t "]).join(parts)))
    rows += [(200, rows[5][1]), (201, rows[5][1]), (7, rows[5][1]), (300, None), (301, ""), (None, rows[3][1]), (None, rows[8][1]), (302, "x" * 900), (303, "ab" * 300), (304, " \n\t ")]
    return rows


@pytest.mark.parametrize("seed", [1, 2])
def test_passages_match_brute_force(spark, seed):
    rows = corpus(seed)
    docs = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, n_words string")
    for width, chunk in ((50, 4000), (12, 1500)):
        got = [tuple(r) for r in repeated_passages(docs, width=width, chunk_bytes=chunk, board_keys=500, digest=True).collect()]
        assert sorted(got, key=str) == sorted(brute_words(rows, width), key=str)
        assert sum(x[2] for x in got) > 0


@pytest.mark.parametrize("seed", [1, 2])
def test_spans_match_brute_force(spark, seed):
    rows = corpus(seed)
    docs = spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, chunk int")
    for width, chunk, spacing in ((200, 4000, 32), (100, 2000, 16), (60, 1 << 20, 8)):
        got = [tuple(r) for r in repeated_spans(docs, width=width, chunk_bytes=chunk, board_keys=500, spacing=spacing, digest=True).collect()]
        assert sorted(got, key=str) == sorted(brute_bytes(rows, width), key=str)


def test_empty_table_and_texts(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert repeated_passages(none).count() == 0 and repeated_spans(none).count() == 0
    one = spark.createDataFrame([(1, "a b  c")], "doc_id long, text string")
    # a text that loses nothing comes back as it was; its digest is over its words joined by one space
    assert repeated_passages(one).first().kept_text == "a b  c"
    assert repeated_passages(one, digest=True).first().kept_sha256 == sha(b"a b c")
    assert bytes(repeated_spans(one).first().kept) == b"a b  c"


def test_order_is_that_of_the_bytes():
    """Windows in the order of dictionary and parse suffixes against windows sorted as bytes."""
    import numpy as np

    from edgegraph.llm.rolling import spread
    from edgegraph.llm.suffix import repeated_windows, suffix_order

    rng = random.Random(0)
    for _ in range(40):
        width, base = rng.choice([20, 40, 60]), bytes(rng.choice(b"abcd") for _ in range(300))
        regions = []
        for _ in range(rng.randint(1, 12)):
            a = rng.randint(0, 200)
            r = bytearray(base[a : a + rng.randint(width, 100)])
            if rng.random() < 0.5:
                r[rng.randrange(len(r))] = rng.choice(b"abcd")
            regions.append(bytes(r))
        text = np.frombuffer(b"".join(regions), dtype=np.uint8)
        off = np.concatenate(([0], np.cumsum([len(r) for r in regions])))
        starts = spread(off[:-1], off[1:] - width + 1)
        own = [text[i : i + width].tobytes() for i in starts]
        for spacing in (1, 4, 64):
            order = suffix_order(text, off, starts, spacing, width)
            assert [own[i] for i in order] == sorted(own)
            assert repeated_windows(text, off, starts, spacing, width).tolist() == [own.count(w) > 1 for w in own]


def test_spans_rest_on_the_order(spark, monkeypatch):
    """Without the order of the suffixes, repeats at the borders are missed; crowded phrases go another way."""
    rows = corpus(3)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = sorted(brute_bytes(rows, 60), key=str)
    run = lambda **o: sorted((tuple(r) for r in repeated_spans(docs, width=60, chunk_bytes=4000, board_keys=5000, spacing=8, digest=True, **o).collect()), key=str)
    assert run() == want == run(crowd=1)


def test_long_texts_and_empty_tables(spark):
    rng = random.Random(8)
    line = " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(40))
    rows = [(1, "x" * 300_000), (2, line + " " + "y" * 200_000 + " " + line), (3, "ab" * 100_000 + line), (4, "\n".join(f"{i}" for i in range(40_000)))]
    docs = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, kept string")
    got = {r.doc_id: r for r in repeated_spans(docs, digest=True).collect()}
    assert got[1].n_removed == 300_000 and got[1].n_spans == 1 and got[4].n_removed == 0
    assert got[2].n_removed == 200_000 + 2 * len(line) and got[3].n_removed == 200_000 + len(line)
    words = {r.doc_id: r.n_removed for r in repeated_passages(docs, width=20, digest=True).collect()}
    assert words[1] == 0 and words[2] == 0 and words[3] >= 39


class Shuffled:
    """As much of a DataFrame as the passes of repeated_spans use; a group's rows arrive in another order each time."""

    def __init__(self, table, rng, keys=()):
        self.table, self.rng, self.keys = table, rng, keys

    def groupBy(self, key):
        return Shuffled(self.table, self.rng, [*self.keys, (key, self.table)])

    def cogroup(self, other):
        return Shuffled(None, self.rng, [*self.keys, *other.keys])

    def unionByName(self, other):
        import pyarrow as pa

        return Shuffled(pa.concat_tables([self.table, other.table]), self.rng)

    def applyInArrow(self, f, schema):
        import pyarrow as pa

        found = {}
        for i, (key, table) in enumerate(self.keys):
            for at, x in enumerate(table[key].to_pylist()):
                found.setdefault(x, [[] for _ in self.keys])[i].append(at)
        out = []
        for x, places in found.items():
            for p in places:
                self.rng.shuffle(p)
            groups = [t.take(pa.array(p, pa.int64())) for (_, t), p in zip(self.keys, places)]
            out.append(f(*groups) if len(groups) == 1 else f((pa.scalar(x),), *groups))
        return Shuffled(pa.concat_tables(out), self.rng)


@pytest.mark.parametrize("seed", range(4))
def test_spans_do_not_rest_on_the_order_of_rows(monkeypatch, seed):
    """The rows of a chunk come in any order from a shuffle, and in another one in each pass."""
    import pyarrow as pa

    from edgegraph.llm import suffix

    rng = random.Random(seed)
    base = "".join(rng.choice("abcd") for _ in range(900))
    rows = []
    for i in range(40):
        parts = [base[a : a + rng.randint(80, 400)] for a in (rng.randrange(700) for _ in range(3))]
        rows.append((i, "".join(rng.choice("efgh") for _ in range(30)).join(parts)))
    table = pa.table({"doc_id": [d for d, _ in rows], "text": [t for _, t in rows], "chunk": pa.array([d % 3 for d, _ in rows], pa.int32())})
    monkeypatch.setattr(suffix.B, "deal", lambda docs, size: (Shuffled(table, rng), sum(len(t) for _, t in rows)))
    out = suffix._chunks(None, 60, 1, 500, 8, suffix._digest, suffix.RESULT, 4096).table
    assert sorted(tuple(r.values()) for r in out.to_pylist()) == sorted(brute_bytes(rows, 60))
