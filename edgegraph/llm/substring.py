"""Substring dedup by fixed-block anchors.

1. *index*: the non-overlapping blocks of ``block`` words of every document, by hash. A window of
   ``width >= 2 * block - 1`` words holds at least one whole block of whichever document it stands in.
2. *probe*: every rolling window of ``block`` words of every document asks the index. A block is a
   *hit* when some other place of the corpus has its words. A probe travels as four bytes (the rest of
   its hash is the board it is sent to), so that probing all places costs less than the text itself.
3. *extend*: hits are extended to all windows of ``width`` words that hold one; runs of such windows
   are the maximal repeats. Hashes only find the hits; each window over one is compared with those of
   all documents by 128 bits of the SHA-256 of its words, and a word goes if a window over it also starts
   in a document of smaller id. The smallest document is found by the window and not by pairs of
   documents, so a passage in n documents costs n entries and never n * n.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import board as B
from .rolling import Prefix, covered, digest, joined, text_bytes, words

_BLOCK, _WINDOW = 0, 1
_NO_ID = np.iinfo(np.int64).min
RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string"
TEXTS = "doc_id long, n_words long, n_removed long, kept_text string"


class _Words:
    """Words of a chunk, the hashes of their blocks, and which documents they belong to."""

    def __init__(self, table: pa.Table, block: int, width: int) -> None:
        self.data, self.off = text_bytes(table["text"])
        self.starts, self.ends, self.first = words(self.data, self.off)
        self.block, self.width = block, width
        sums = Prefix.of_bytes(self.data)
        self.sums = Prefix(sums.at(self.starts, self.ends))
        n = len(self.starts)
        self.doc = np.repeat(np.arange(len(self.off) - 1), np.diff(self.first))
        self.rank = np.arange(n) - self.first[:-1][self.doc]  # of the word in its document
        self.left = self.first[1:][self.doc] - np.arange(n)  # words from here to the end
        self.probes = np.flatnonzero(self.left >= block)
        self.keys = self.sums.every(block)[self.probes]
        self.aligned = self.rank[self.probes] % block == 0

    def questions(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Distinct probes, their places, whether one is an indexed block, whether it occurs twice here."""
        uniq, place, count = B.repeats(self.keys)
        return uniq, place, np.bincount(place, weights=self.aligned, minlength=len(uniq)) > 0, count >= 2

    def windows(self, table: pa.Table, boards: int) -> tuple[np.ndarray, np.ndarray]:
        """Starts of the windows that hold a hit, and the digests of their words."""
        uniq, place, _, _ = self.questions()
        (hot,) = B.answers(table, _BLOCK, uniq, boards, 1)
        hits = np.zeros(len(self.starts) + 1, dtype=np.int64)
        hits[self.probes[hot[place]] + 1] = 1
        np.cumsum(hits, out=hits)
        at = np.flatnonzero(self.left >= self.width)
        at = at[hits[at + self.width - self.block + 1] > hits[at]]
        self.spaced, self.into = joined(self.data, self.starts, self.ends)
        return at, digest(memoryview(self.spaced), self.into[at], self.into[at + self.width] - 1)


def _blocks_answer(_: int, parts: list) -> list[list[np.ndarray]]:
    keys, indexed, twice = (np.concatenate(x) for x in zip(*(B.unpack(n, body, [np.uint32], 2) for _, n, body in parts), strict=True))
    uniq, place, count = B.repeats(keys)
    hot = (np.bincount(place, weights=indexed, minlength=len(uniq)) > 0) & ((count >= 2) | (np.bincount(place, weights=twice, minlength=len(uniq)) > 0))
    return [[x] for x in np.split(hot[place], np.cumsum([n for _, n, _ in parts])[:-1])]


def _window_body(keys: np.ndarray, ids: np.ndarray, boards: int, chunk: int):
    """Sorted distinct windows with the smallest id of this chunk: the ids once, each key with its place among them."""
    at = B.cuts(keys[:, 0], boards)
    for b in np.flatnonzero(np.diff(at)):
        lo, hi = at[b], at[b + 1]
        used, place = np.unique(ids[lo:hi], return_inverse=True)
        yield int(b), chunk, _WINDOW, int(hi - lo), b"".join((np.uint32(len(used)).tobytes(), used.tobytes(), keys[lo:hi].tobytes(), place.astype(np.uint16 if len(used) <= 65535 else np.uint32).tobytes()))


def _windows_answer(_: int, parts: list) -> list[list[np.ndarray]]:
    keys, ids = [], []
    for _, n, body in parts:
        m = int(np.frombuffer(body, dtype=np.uint32, count=1)[0])
        used = np.frombuffer(body, dtype=np.int64, count=m, offset=4)
        keys.append(np.frombuffer(body, dtype=np.uint64, count=2 * n, offset=4 + 8 * m).reshape(-1, 2))
        ids.append(used[np.frombuffer(body, dtype=np.uint16 if m <= 65535 else np.uint32, count=n, offset=4 + 8 * m + 16 * n)])
    uniq, place, _ = B.repeats_wide(np.concatenate(keys))
    own = np.concatenate(ids)
    least = np.full(len(uniq), np.iinfo(np.int64).max)
    np.minimum.at(least, place, own)
    # told apart from the chunk's own smallest id: the chunk knows that one
    return [[x] for x in np.split(least[place] < own, np.cumsum([len(k) for k in keys])[:-1])]


def repeated_passages(docs: DataFrame, width: int = 50, block: int | None = None, chunk_bytes: int = 1_500_000, board_keys: int = 400_000, digest: bool = False, carry: tuple[str, ...] = ()) -> DataFrame:
    """Words covered by a window of ``width`` words that also starts in a document of smaller id.

    docs: doc_id, text (other columns are ignored). Words are the runs without white space (space and
    the five ASCII controls from tab to carriage return). One row per input row: counts and the kept
    words joined by one space, or their SHA-256. The document of the smallest id keeps a passage whole.
    Null text: no words. Rows of the same id do not count as smaller than each other, and a null id
    counts as the smallest. An empty table gives no rows. A text that loses nothing is returned as it was;
    carry: columns of docs to return as well.
    """
    block = (width + 1) // 2 if block is None else block
    if 2 * block - 1 > width:
        raise ValueError("a window must hold a whole block: 2 * block - 1 <= width")
    dealt, size = B.deal(docs, chunk_bytes, carry)
    probe_boards, window_boards = max(1, math.ceil(size / 6 / board_keys)), max(1, math.ceil(size / 20 / board_keys))

    schema = (RESULT if digest else TEXTS) + "".join(f", `__{c}` {dict(docs.dtypes)[c]}" for c in carry)

    def probe(table: pa.Table) -> pa.Table:
        uniq, _, indexed, twice = _Words(table, block, width).questions()
        low = (uniq & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        return B.asked_table(B.ask(table["chunk"][0].as_py(), _BLOCK, uniq, [low], [indexed, twice], probe_boards))

    def smallest(w: _Words, at: np.ndarray, keys: np.ndarray, column) -> tuple:
        ids = np.asarray(column.fill_null(_NO_ID), dtype=np.int64)[w.doc[at]]
        uniq, place, _ = B.repeats_wide(keys)
        least = np.full(len(uniq), np.iinfo(np.int64).max)
        np.minimum.at(least, place, ids)
        return uniq, place, least, ids

    def extend(key, left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return B.asked_table([])
        w = _Words(left, block, width)
        at, keys = w.windows(right, probe_boards)
        uniq, _, least, _ = smallest(w, at, keys, left["doc_id"])
        return B.asked_table(_window_body(uniq, least, window_boards, key[0].as_py()))

    def remove(_, left: pa.Table, right: pa.Table) -> pa.Table:
        w = _Words(left, block, width)
        at, keys = w.windows(right, probe_boards)
        uniq, place, least, ids = smallest(w, at, keys, left["doc_id"])
        (elsewhere,) = B.answers(right, _WINDOW, uniq[:, 0], window_boards, 1)
        gone = covered(at[elsewhere[place] | (least[place] < ids)], width, len(w.starts))
        out = _finish(left["doc_id"], w, gone, digest)
        for c in carry:
            out = out.append_column(f"__{c}", left[f"__{c}"])
        return out

    by_chunk = dealt.groupBy("chunk")
    first = by_chunk.applyInArrow(probe, B.ASKED).groupBy("board").applyInArrow(B.owner(_blocks_answer), B.ANSWERED)
    second = by_chunk.cogroup(first.groupBy("chunk")).applyInArrow(extend, B.ASKED).groupBy("board").applyInArrow(B.owner(_windows_answer), B.ANSWERED)
    out = dealt.groupBy("chunk").cogroup(first.unionByName(second).groupBy("chunk")).applyInArrow(remove, schema)
    return out.withColumnsRenamed({f"__{c}": c for c in carry})


def _finish(ids, w: _Words, gone: np.ndarray, digest: bool) -> pa.Table:
    """The kept words of each row joined by one space, written into one buffer for the whole chunk."""
    keep = np.flatnonzero(~gone)
    out, into = joined(w.data, w.starts[keep], w.ends[keep])
    kept = np.concatenate(([0], np.cumsum(~gone)))[w.first]
    n = np.diff(w.first)
    bounds = into[kept]
    lost = n - np.diff(kept)
    whole = np.zeros(len(n), dtype=bool) if digest else lost == 0
    texts = [w.data[c:d].tobytes() if same else out[a : max(a, b - 1)].tobytes() for a, b, c, d, same in zip(bounds[:-1], bounds[1:], w.off[:-1], w.off[1:], whole, strict=True)]
    cols = {"doc_id": ids, "n_words": n.astype(np.int64), "n_removed": lost.astype(np.int64)}
    if digest:
        return pa.table(cols | {"kept_sha256": [hashlib.sha256(x).hexdigest() for x in texts]})
    return pa.table(cols | {"kept_text": pa.array([x.decode() for x in texts], pa.string())})
