"""Byte-level BPE by backtracking over Aho-Corasick matches, and decoding by an offset table.

A token sequence is the exact result of the merges when each token is the result of merging its own
bytes and each pair of neighbours is *compatible*: merging the bytes of both together gives back the
two. So an encoder needs no merge loop over the text. It takes the longest token at a place, checks it
against the token before it in the table of pairs, falls back to the next shorter match where the pair
is not compatible, and gives up a place for good when nothing fits there. Each place is left at most
once, which makes it linear. An entry of the table of pairs is made when the pair is first met, from the
edges of both tokens: the parts that stand at the right edge of the left one and at the left edge of the
right one while they are put together, and whether any merge joins two of these before they are taken up.

Encoded pieces are kept in bounded tables. A piece is what stands between two single spaces; such
spaces always begin a pre-token, so pieces are independent of their neighbours.
"""

from __future__ import annotations

import functools
import hashlib
import json
import re
import struct
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The pattern of this kind of tokenizer, with the white space that its library knows.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
# The same for texts of printable ASCII, ASCII white space and Latin-1 letters only.
_LATIN = "À-ÖØ-öø-ÿ"
_PLAIN = re.compile(rf"[\t-\r -~{_LATIN}]*")
_PLAIN_PATTERN = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-z{_LATIN}]+| ?[0-9]+| ?[^\t-\r A-Za-z{_LATIN}0-9]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+")
_WIDE_PATTERN = regex.compile(PATTERN)
#: A space beside white space, or white space at an end: there the pieces between spaces hang together.
_JOINED = re.compile(r" [\t-\r \x85\xa0  -     　]|[\t-\r \x85\xa0  -     　] |\s\Z|\A\s")

_LONG_RUN = re.compile(r"\s{5000}")


def printable_bytes() -> dict[str, int]:
    """The characters that stand for the 256 bytes in such vocabularies: visible Latin-1 characters
    for themselves, the others by number from 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class _Bounded(dict):
    """A table that fills itself by make() and starts anew when it is full."""

    def __init__(self, make, most: int) -> None:
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, key):
        value = self.make(key)
        if len(self) >= self.most:
            self.clear()
        self[key] = value
        return value


class ByteBPE:
    """Exact encoder and decoder of a byte-level BPE file of the tokenizers library."""

    def __init__(self, path: str, cache: int = 300_000) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        why = unsupported(spec)
        if why:
            raise ValueError(f"{path}: {why}")
        byte_of = printable_bytes()
        latin = lambda s: "".join(chr(byte_of[c]) for c in s)  # noqa: E731  a string of one character a byte
        model = spec["model"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.ids = {latin(t): i for t, i in model["vocab"].items() if t not in self.special}
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.ranks = {(latin(a), latin(b)): i for i, (a, b) in enumerate(merges)}
        self.made_by: dict[str, tuple[str, str, int]] = {}
        for (a, b), r in self.ranks.items():
            self.made_by.setdefault(a + b, (a, b, r))
        self.token_of = {i: t for t, i in self.ids.items()}
        self.right_edges = _Bounded(lambda i: self._spine(self.token_of[i], True), 1 << 20)
        self.left_edges = _Bounded(lambda i: self._spine(self.token_of[i], False), 1 << 20)
        self.single = self._whole_tokens()
        self.matcher = ahocorasick.Automaton()
        for t, i in self.single.items():
            self.matcher.add_word(t, i)
        self.matcher.make_automaton()
        self.token_length = {i: len(t) for i, t in self.token_of.items()}
        self.most = max(map(len, self.single))  # no match is longer
        self.shorter = _Bounded(self._next_shorter, 1 << 20)
        self.pairs = _Bounded(self._compatible, 1_000_000)
        self.pretokens = _Bounded(self._pretoken, cache)
        self.pieces = _Bounded(self._piece, cache)
        self.first_pieces = _Bounded(self._first_piece, 20_000)
        self._split = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        size = max([-1, *self.ids.values(), *self.special.values()]) + 1
        spelled = [b""] * size
        for t, i in self.ids.items():
            spelled[i] = t.encode("latin-1")
        for t, i in self.special.items():
            spelled[i] = t.encode()
        self.length = np.fromiter(map(len, spelled), dtype=np.int64, count=size)
        self.offset = np.concatenate(([0], np.cumsum(self.length)))[:-1]
        self.blob = np.frombuffer(b"".join(spelled), dtype=np.uint8)

    def merge(self, text: str) -> list[str]:
        """Plain merging: the pair of the best rank first, from the left."""
        parts = list(text)
        while len(parts) > 1:
            rank, at = min((self.ranks.get(p, 1 << 30), i) for i, p in enumerate(zip(parts, parts[1:], strict=False)))
            if rank == 1 << 30:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _whole_tokens(self) -> dict[str, int]:
        """Vocabulary strings that the merges leave as the one token they are: a single byte, or two such
        strings that are compatible up to the merge that makes the token."""
        out: dict[str, int] = {}
        for t in sorted(self.ids, key=len):
            if len(t) == 1:
                out[t] = self.ids[t]
            elif t in self.made_by:
                a, b, rank = self.made_by[t]
                if a in out and b in out and self._stay_apart_until(a, b, rank):
                    out[t] = self.ids[t]
        return out

    def _stay_apart_until(self, a: str, b: str, rank: int) -> bool:
        for left, until_left in self._spine(a, True):
            for right, until_right in self._spine(b, False):
                r = self.ranks.get((left, right))
                if r is not None and r < rank and r < until_left and r <= until_right:
                    return False
        return True

    def _spine(self, token: str, right: bool) -> list[tuple[str, int]]:
        """What stands at the right (left) edge of a token while it is put together: each part, and
        the rank of the merge that takes it up."""
        out, until = [], 1 << 30
        while True:
            out.append((token, until))
            if token not in self.made_by:
                return out
            left_part, right_part, until = self.made_by[token]
            token = right_part if right else left_part

    def _compatible(self, pair: tuple[int, int]) -> bool:
        """Whether no merge joins an edge part of the left token with one of the right token while both
        are there. Merges run in the order of ranks, equal ones from the left."""
        ranks = self.ranks
        for left, until_left in self.right_edges[pair[0]]:
            for right, until_right in self.left_edges[pair[1]]:
                rank = ranks.get((left, right))
                if rank is not None and rank < until_left and rank <= until_right:
                    return False
        return True

    def encode_bytes(self, text: str) -> list[int]:
        """Ids of one pre-token, given with one character a byte."""
        if text in self.single:
            return [self.single[text]]
        n, pairs, shorter, length, matches, most = len(text), self.pairs, self.shorter, self.token_length, self.matcher.iter_long, self.most
        given_up = None
        tokens: list[int] = []
        before, here = -1, 0
        longest = matches(text)  # the longest match at each place, one after the other
        token = next(longest)[1]
        while True:
            if (before < 0 or pairs[before, token]) and (given_up is None or not given_up[here + length[token]]):
                tokens.append(token)
                here += length[token]
                if here == n:
                    return tokens
                before = token
                token = next(longest)[1] if longest is not None else next(matches(text[here : here + most]))[1]
                continue
            longest = None
            token = shorter[token]
            while token < 0:  # nothing fits here: the token before was too long
                if given_up is None:
                    given_up = bytearray(n + 1)
                given_up[here] = 1
                last = tokens.pop()
                here -= length[last]
                before = tokens[-1] if tokens else -1
                token = shorter[last]

    def _next_shorter(self, token: int) -> int:
        """The longest whole token that begins this one; -1 if it is a single byte."""
        text = self.token_of[token]
        return next((self.single[text[:k]] for k in range(len(text) - 1, 0, -1) if text[:k] in self.single), -1)

    def _pretoken(self, text: str) -> bytes:
        ids = self.encode_bytes(text if text.isascii() else text.encode().decode("latin-1"))
        return struct.pack(f"<{len(ids)}I", *ids)

    def _cut(self, text: str) -> list[str]:
        return (_PLAIN_PATTERN if _PLAIN.fullmatch(text) else _WIDE_PATTERN).findall(text)

    def _first_piece(self, text: str) -> bytes:
        return b"".join(map(self.pretokens.__getitem__, self._cut(text)))

    def _piece(self, text: str) -> bytes:
        return self._first_piece(" " + text)

    def _ordinary(self, text: str) -> bytes:
        if _JOINED.search(text) or not text:
            return self._first_piece(text)
        first, *rest = text.split(" ")
        return self.first_pieces[first] + b"".join(map(self.pieces.__getitem__, rest))

    def encode(self, text: str) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers."""
        if self._split is None or not self._split.search(text):
            return self._ordinary(text)
        out, at = [], 0
        for m in self._split.finditer(text):
            out += [self._ordinary(text[at : m.start()]), np.array([self.special[m[0]]], dtype="<u4").tobytes()]
            at = m.end()
        return b"".join([*out, self._ordinary(text[at:])])

    def decode(self, ids: np.ndarray) -> bytes:
        """The bytes of a token sequence, gathered from the table of all tokens' bytes."""
        size = self.length[ids]
        ends = np.cumsum(size)
        if not len(ids) or not ends[-1]:
            return b""
        return self.blob[np.repeat(self.offset[ids] - ends + size, size) + np.arange(ends[-1])].tobytes()


def unsupported(spec: dict) -> str:
    """Why a tokenizer file is none of this kind; empty if it is one."""
    model, pre = spec["model"], spec.get("pre_tokenizer") or {}
    if model.get("type", "BPE") != "BPE" or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or not pre.get("use_regex", True):
        return "not byte-level BPE with the usual pattern"
    if spec.get("normalizer") or any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges")):
        return "a normaliser or model option is set"
    if any(t.get(k) for t in spec["added_tokens"] for k in ("single_word", "lstrip", "rstrip", "normalized")):
        return "an added token has options"
    return ""


@functools.lru_cache(maxsize=2)
def load(path: str) -> ByteBPE:
    """One encoder for each worker process and file."""
    return ByteBPE(path)


@functools.lru_cache(maxsize=2)
def library_encoder(path: str):
    """text -> ids as numpy, by a compiled library where the file's ids follow its merges, else by ByteBPE.

    For operators that need ids but are not about making them.
    """
    bpe = load(path)
    ranks = {t.encode("latin-1"): i for t, i in bpe.ids.items()}
    order = [bpe.ids.get(a + b, -1) for a, b in bpe.ranks]
    if len(bpe.single) != len(bpe.ids) or order != sorted(order) or min([0, *order]) < 0 or max(bpe.ids[chr(b)] for b in range(256)) > min([256, *order]):
        return lambda text: np.frombuffer(bpe.encode(text), dtype="<u4")
    import tiktoken

    compiled = tiktoken.Encoding("file", pat_str=PATTERN.replace(r"\p{White_Space}", r"\s").replace(r"\P{White_Space}", r"\S"), mergeable_ranks=ranks, special_tokens=bpe.special)
    # that library refuses runs of white space from some 10**5 signs on: they go to the other encoder
    return lambda text: np.frombuffer(bpe.encode(text), dtype="<u4") if _LONG_RUN.search(text) else compiled.encode_to_numpy(text, allowed_special="all")


def texts_of(batch: pa.RecordBatch, size: int = 256) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Slices of a batch with their texts; null is empty."""
    for at in range(0, batch.num_rows, size):
        part = batch.slice(at, size)
        yield part, [x or "" for x in part["text"].to_pylist()]


def _select(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def encode(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids array<int>) of every whole text, one row per input row; a null text is empty.

    docs: doc_id, text (other columns are ignored). Nothing is added, truncated or padded; strings of
    special tokens inside a text become those tokens, as the tokenizers library does by default.
    """

    def run(batches):
        bpe = load(path)
        for batch in batches:
            for part, texts in texts_of(batch):
                ids = [np.frombuffer(bpe.encode(t), dtype="<u4").astype(np.int32) for t in texts]
                yield pa.RecordBatch.from_arrays([part["doc_id"], pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return _select(docs).mapInArrow(run, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids); bytes that are no UTF-8 become U+FFFD. Null ids give an empty text."""

    def run(batches):
        bpe = load(path)
        for batch in batches:
            texts = [bpe.decode(np.asarray(x or [], dtype=np.int64)).decode("utf-8", "replace") for x in batch["ids"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """Digests of encode() and of decode() after it: n_tokens, ids_sha256, decoded_sha256 per row."""

    def run(batches):
        bpe = load(path)
        for batch in batches:
            for part, texts in texts_of(batch):
                ids = [bpe.encode(t) for t in texts]
                back = [bpe.decode(np.frombuffer(x, dtype="<u4")).decode("utf-8", "replace").encode() for x in ids]
                yield pa.RecordBatch.from_arrays(
                    [part["doc_id"], pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in ids]), pa.array([hashlib.sha256(x).hexdigest() for x in back])],
                    ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
                )

    return _select(docs).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
