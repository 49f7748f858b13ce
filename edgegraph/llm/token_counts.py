"""Token counts by the whole-token shortcut.

Offline, every vocabulary string is merged by itself: those that stay one token are proven (together
with their pre-token boundaries) to count one wherever they are a pre-token. At run time a pre-token
in that table counts one without any merging; only the others are encoded, and their counts are kept
in a bounded table. Files of other kinds are counted by their own library.
"""

from __future__ import annotations

import functools
import json

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import _JOINED, ByteBPE, _Bounded, load, texts_of, unsupported


class _Counter:
    def __init__(self, bpe: ByteBPE, cache: int = 300_000) -> None:
        self.bpe = bpe
        self.whole = frozenset(bpe.single)  # strings of one character a byte
        self.rest = _Bounded(lambda t: len(bpe.encode_bytes(t)), cache)
        self.pieces = _Bounded(lambda t: self._count(" " + t), cache)

    def _count(self, text: str) -> int:
        n = 0
        for t in self.bpe._cut(text):
            t = t if t.isascii() else t.encode().decode("latin-1")
            n += 1 if t in self.whole else self.rest[t]
        return n

    def _ordinary(self, text: str) -> int:
        if _JOINED.search(text) or not text:
            return self._count(text)
        first, *rest = text.split(" ")
        return self._count(first) + sum(map(self.pieces.__getitem__, rest))

    def count(self, text: str) -> int:
        split = self.bpe._split
        if split is None or not split.search(text):
            return self._ordinary(text)
        parts = split.split(text)
        return len(parts) - 1 + sum(map(self._ordinary, parts))


@functools.lru_cache(maxsize=2)
def counter(path: str):
    """text -> number of tokens, for each worker process and file."""
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda text: len(model.encode(text))
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    if unsupported(spec):
        import tokenizers

        library = tokenizers.Tokenizer.from_file(path)
        library.no_truncation()
        library.no_padding()
        return lambda text: len(library.encode(text, add_special_tokens=False).ids)
    return _Counter(load(path)).count


def token_counts(docs: DataFrame, path: str, limit: int = 512) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every whole text, one row per input row.

    docs: doc_id, text (other columns are ignored). path: a tokenizer file (.json or .model). No begin,
    end or added special tokens, no truncation or padding. A null text is empty.
    """

    def run(batches):
        count = counter(path)
        for batch in batches:
            for part, texts in texts_of(batch):
                yield pa.RecordBatch.from_arrays([part["doc_id"], part["n_bytes"], pa.array(map(count, texts), pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.octet_length(text).cast("long").alias("n_bytes"))
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
