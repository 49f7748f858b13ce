"""Quality classifier: votes of the nearest labelled documents in a latent-semantic space.

Terms are frequent words as they are, and all other words by their *shape* (letters by case, digits and
runs folded), besides a few facts about a text: how much of its words and lines repeat, and how long words
and lines are. The terms of a bounded sample of labelled documents are weighted (log counts, inverse
document frequency) and a truncated singular value decomposition of that matrix gives the latent space.
The sample's vectors are broadcast with their labels; every document is then compared with all of them
by exact cosine products, block by block, and the nearest vote with their similarity as weight.

The bounds: ``sample`` labelled documents, ``terms`` terms and ``dims`` dimensions, so the broadcast model
is a few MB for any corpus.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import _Bounded, texts_of
from .exact import shared_folder
from .links import store

_FOLD = re.compile(r"(.)\1+")
_LINE_FACTS = 5
_BINS = 12


def _kind(c: str) -> str:
    return "A" if c.isupper() else "a" if c.isalpha() else "9" if c.isdigit() else c


def shape(word: str) -> str:
    """A word with its letters by case, digits as 9 and runs of one sign folded."""
    return _FOLD.sub(r"\1", "".join(map(_kind, word)))


def _facts(text: str, words: list[str]) -> list[str]:
    """Terms for what a text is like as a whole, each a number in steps."""
    if not words:
        return ["empty"]
    lines = text.split("\n")
    step = lambda x: int(min(1.0, x) * _BINS)
    return [
        f"\nrepeated words {step(1 - len(set(words)) / len(words))}",
        f"\nrepeated lines {step(1 - len(set(lines)) / len(lines))}",
        f"\nword length {step(len(text) / len(words) / 24)}",
        f"\nline length {min(_BINS, int(np.log2(1 + len(words) / len(lines))))}",
        f"\nwords {min(_BINS, int(np.log2(1 + len(words))))}",
    ]


@dataclass
class Model:
    """A fitted classifier; score() gives the chance-like score of label 1 for each text."""

    vocabulary: dict[str, int]  # terms; a word that is none counts by its shape
    idf: np.ndarray
    axes: np.ndarray  # terms x dims
    vectors: np.ndarray  # labelled documents x dims, of length 1
    labels: np.ndarray
    neighbours: int
    sharpness: float
    prior: float

    def _term(self, word: str) -> int:
        at = self.vocabulary.get(word)
        return self.vocabulary.get("\t" + shape(word), 0) if at is None else at

    def counts(self, texts: list[str]) -> np.ndarray:
        if not hasattr(self, "_terms"):
            self._terms = _Bounded(self._term, 400_000)
        n = len(self.vocabulary) + 1
        out = np.zeros((len(texts), n), dtype=np.float32)
        for row, text in zip(out, texts, strict=True):
            words = text.split()
            row += np.bincount(np.fromiter(map(self._terms.__getitem__, words), dtype=np.int64, count=len(words)), minlength=n)
            for f in _facts(text, words):
                row[self.vocabulary.get(f, 0)] += 1 + len(words) / 20  # facts weigh as many words would
        return out

    def embed(self, texts: list[str]) -> np.ndarray:
        x = np.log1p(self.counts(texts)) * self.idf
        x /= np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-12)
        v = x @ self.axes
        return v / np.maximum(np.sqrt((v * v).sum(axis=1, keepdims=True)), 1e-12)

    def score(self, texts: list[str]) -> np.ndarray:
        cos = self.embed(texts) @ self.vectors.T
        k = min(self.neighbours, cos.shape[1])
        if not k:
            return np.full(len(texts), self.prior)
        near = np.argpartition(cos, cos.shape[1] - k, axis=1)[:, -k:]
        weight = np.maximum(np.take_along_axis(cos, near, axis=1).astype(np.float64), 0.0) ** self.sharpness
        total = weight.sum(axis=1)
        vote = (weight * self.labels[near]).sum(axis=1)
        return np.clip((vote + 1e-3 * self.prior) / (total + 1e-3), 0.0, 1.0)


def terms_of(text: str) -> set[str]:
    words = text.split()
    return {*words, *("\t" + shape(w) for w in set(words)), *_facts(text, words)}


def _untrained(often: list[tuple[str, int]], labels: list[float], neighbours: int, sharpness: float) -> Model:
    prior = float(np.mean(labels)) if len(labels) else 0.5
    model = Model({t: i + 1 for i, (t, _) in enumerate(often)}, np.zeros(0), np.zeros(0), np.zeros(0), np.asarray(labels, dtype=np.float64), neighbours, sharpness, prior)
    model.idf = np.log((1 + len(labels)) / (1 + np.array([0, *(n for _, n in often)]))).astype(np.float32) + 0.1
    return model


def _least(n: int) -> int:
    """In how many of n texts a term must stand."""
    return max(2, n // 200)


def _train(model: Model, counts: np.ndarray, dims: int, seed: int) -> Model:
    """The latent space, from the term counts of the labelled texts, and their vectors in it."""
    x = np.log1p(counts) * model.idf
    x /= np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-12)
    # randomised truncated singular value decomposition
    n = x.shape[1]
    k = max(1, min(dims, n, max(1, len(x))))
    basis = np.linalg.qr(np.random.default_rng(seed).standard_normal((n, k + 8)).astype(np.float32))[0]
    for _ in range(4):
        basis = np.linalg.qr(x.T @ (x @ basis))[0]
    _, _, vt = np.linalg.svd(x @ basis, full_matrices=False)
    model.axes = (basis @ vt[:k].T).astype(np.float32)
    v = x @ model.axes
    model.vectors = v / np.maximum(np.sqrt((v * v).sum(axis=1, keepdims=True)), 1e-12)
    model.__dict__.pop("_terms", None)  # the table of words met stays behind
    return model


def fit(texts: list[str], labels: list[float], terms: int = 3000, dims: int = 48, neighbours: int = 15, sharpness: float = 8.0, seed: int = 5) -> Model:
    """The model of labelled texts, all on one machine."""
    frequency: dict[str, int] = {}
    for text in texts:
        for t in terms_of(text):
            frequency[t] = frequency.get(t, 0) + 1
    often = sorted(((t, n) for t, n in frequency.items() if n >= _least(len(texts))), key=lambda t: (-t[1], t[0].encode()))[:terms]
    model = _untrained(often, labels, neighbours, sharpness)
    return _train(model, model.counts(texts) if texts else np.zeros((0, len(often) + 1), dtype=np.float32), dims, seed)


def held_out(doc_id) -> F.Column:
    """Rows that no labels are learned from: crc32 of the doc_id as text, modulo 4, is 2. Null: not held out."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def fit_on(docs: DataFrame, labels: DataFrame, sample: int = 2500, terms: int = 3000, dims: int = 48, neighbours: int = 15, sharpness: float = 8.0, seed: int = 5) -> Model:
    """fit() on at most ``sample`` labelled documents that are not held out, chosen by a hash of their id.

    Rows of labels without id or quality are left out; labels given twice count by their mean, and texts
    of one id given twice all count. Texts stay with the executors: the driver gets the ``terms`` most
    frequent terms and, for each document of the sample, the counts of these.
    """
    known = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.avg("quality").alias("label")).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(sample)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).join(F.broadcast(known), "doc_id")
    chosen = store(rows.orderBy(F.md5("text"), "doc_id").limit(sample).repartition(min(sample, 32)), f"{shared_folder(docs.sparkSession, 'quality')}/sample")

    def met(batches):
        for batch in batches:
            for _, texts in texts_of(batch):
                yield pa.RecordBatch.from_arrays([pa.array([t for text in texts for t in terms_of(text)], pa.string())], ["term"])

    n = chosen.count()
    often = chosen.select("text").mapInArrow(met, "term string").groupBy("term").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= _least(n)).orderBy(F.desc("n"), "term").limit(terms).collect()
    bare = _untrained([(r["term"], r["n"]) for r in often], [], neighbours, sharpness)

    def counted(batches):
        for batch in batches:
            for part, texts in texts_of(batch):
                x = bare.counts(texts)
                at = [np.flatnonzero(row) for row in x]
                yield pa.RecordBatch.from_arrays([part["doc_id"], part["label"], pa.array(at, pa.list_(pa.int32())), pa.array([row[i] for row, i in zip(x, at, strict=True)], pa.list_(pa.float32()))], ["doc_id", "label", "places", "counts"])

    found = sorted(tuple(r) for r in chosen.mapInArrow(counted, "doc_id long, label double, places array<int>, counts array<float>").collect())
    counts = np.zeros((len(found), len(often) + 1), dtype=np.float32)
    for row, (_, _, places, values) in zip(counts, found, strict=True):
        row[places] = values
    return _train(_untrained([(r["term"], r["n"]) for r in often], [r[1] for r in found], neighbours, sharpness), counts, dims, seed)


def quality_scores(docs: DataFrame, model: Model, threshold: float = 0.7, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every whole text, one row per input row.

    docs: doc_id, text; carry: columns of docs to return as well. A null text is empty; an empty text is
    scored like any other, by its facts. An empty table gives no rows.
    """
    spread = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = spread.value
        for batch in batches:
            for part, texts in texts_of(batch):
                yield pa.RecordBatch.from_arrays([*(part[c] for c in ("doc_id", *own)), pa.array(m.score(texts), pa.float64())], ["doc_id", *own, "score"])

    own = [f"__{c}" for c in carry]
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), *(F.col(c).alias(f"__{c}") for c in carry))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name != "text") + ", score double"
    scored = rows.mapInArrow(run, schema)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), *(F.col(f"__{c}").alias(c) for c in carry))
