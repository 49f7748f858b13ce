"""Suffix-array dedup by prefix-free parsing.

Every text is cut into phrases at *triggers*: places where the rolling hash of the next
``TRIGGER`` bytes falls into a fixed class. Whether a place is a trigger depends on these bytes
alone, so a repeated passage is parsed alike wherever it stands, and a long repeat costs a few
phrases and not a suffix for each byte.

1. *parse*: each phrase occurrence asks with the phrase that follows it and with its *context* (its
   own bytes and the ``width`` bytes after it, by SHA-256). Contexts that occur twice settle all their
   windows. A following phrase that occurs in one context only cannot lie in a window that another
   context shares, nor can any phrase that occurs once.
2. *order*: what is left, at the borders of repeats, goes to the owner of the following phrase with its
   bytes; of equal contexts one stands for all. The owner parses these regions again, sorts the suffixes of
   its dictionary of phrases, and the suffixes of its parse by the ranks of their phrases; a place of the text
   is ordered by its dictionary suffix and then by the parse suffix that follows, which gives the order of all
   windows. Neighbours in that order are compared byte by byte over the width: equal ones are repeats.

Phrases followed by more than ``crowd`` contexts, and windows too long for a whole phrase (between two far
triggers), would put any number of regions into one task. Their windows are told apart by 128 bits of their
SHA-256 instead, each at an owner of its own.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import board as B
from .rolling import Prefix, covered, digest, mix, spread, text_bytes

TRIGGER, SPACING = 8, 32
_NEXT, _CONTEXT, _WINDOW, _REGION = 0, 1, 2, 3
RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
SPANS = "doc_id long, n_bytes long, starts array<long>, ends array<long>, kept binary"


def _triggers(data: np.ndarray, spacing: int) -> np.ndarray:
    """Places where the hash of TRIGGER bytes falls into a class of about one in spacing."""
    n = max(0, len(data) - TRIGGER + 1)
    every = np.ndarray((n,), dtype="<u8", buffer=np.ascontiguousarray(data), strides=(1,)) if n else np.zeros(0, dtype=np.uint64)
    limit, step = np.uint64((1 << 24) // spacing), 1 << 15
    found = [np.flatnonzero(mix(mix(every[i : i + step]) + np.uint64(1)) >> np.uint64(40) < limit) + i for i in range(0, n, step)]
    return np.concatenate(found) if found else np.zeros(0, dtype=np.int64)


class _Classes:
    """Strings data[lo:hi] of a chunk by equality: the class of each, in the order of a hash. Strings that
    share their hash with another one of the chunk are told apart by SHA-256."""

    def __init__(self, data: np.ndarray, sums: Prefix, lo: np.ndarray, hi: np.ndarray) -> None:
        self.data, self.lo, self.hi = memoryview(data), lo, hi
        key = sums.at(lo, hi)
        order = np.argsort(key, kind="stable")
        ranked = key[order]
        new = np.ones(len(key), dtype=bool)
        new[1:] = ranked[1:] != ranked[:-1]
        twins = ~new
        twins[:-1] |= ~new[1:]
        if twins.any():
            at = order[twins]
            sha = digest(self.data, lo[at], hi[at])
            within = np.lexsort((sha[:, 1], sha[:, 0], ranked[twins]))
            order[twins], sha = at[within], sha[within]
            new[np.flatnonzero(twins)[1:]] |= (sha[1:] != sha[:-1]).any(axis=1)
        self.place = np.empty(len(key), dtype=np.int64)
        self.place[order] = np.cumsum(new) - 1
        self.first = order[new]  # one of each class
        self.key, self.count = ranked[new], np.diff(np.append(np.flatnonzero(new), len(key)))

    def digests(self, which: np.ndarray | slice = slice(None)) -> np.ndarray:
        """128 bits of the SHA-256 of classes."""
        at = self.first[which]
        return digest(self.data, self.lo[at], self.hi[at])


class _Groups:
    """The windows of a chunk, grouped by the first trigger at or after their start."""

    def __init__(self, data: np.ndarray, off: np.ndarray, width: int, spacing: int) -> None:
        self.data, self.off, self.width = data, off, width
        self.sums = Prefix.of_bytes(data)
        at = _triggers(data, spacing)
        doc = np.searchsorted(off, at, side="right") - 1
        fits = at + TRIGGER <= off[doc + 1]
        at, doc = at[fits], doc[fits]
        last = off[1:] - width  # of the starts of windows
        n_docs = len(off) - 1
        # a group after the last trigger of each document, without a phrase that follows
        at = np.concatenate((at, last))
        doc = np.concatenate((doc, np.arange(n_docs)))
        tail = np.zeros(len(at), dtype=bool)
        tail[len(at) - n_docs :] = True
        order = np.lexsort((at, tail, doc))
        at, doc, tail = at[order], doc[order], tail[order]
        lo = off[doc].copy()
        same = doc[1:] == doc[:-1]
        lo[1:][same] = at[:-1][same] + 1
        follow = np.full(len(at), -1, dtype=np.int64)
        has = np.flatnonzero(same & ~tail[1:])
        follow[has] = at[has + 1]
        hi = np.minimum(at, last[doc])  # the last start, included
        keep = (lo <= hi) | (follow >= 0)  # phrases count wherever they stand
        hi = np.maximum(hi, lo - 1)
        self.lo, self.hi, at, follow, doc = lo[keep], hi[keep], at[keep], follow[keep], doc[keep]
        # starts from which the following phrase lies whole in the window
        whole = np.where(follow < 0, self.hi + 1, follow + TRIGGER - width)
        self.whole = np.minimum(np.maximum(self.lo, whole), self.hi + 1)
        self.asks = np.flatnonzero(follow >= 0)
        a = self.asks
        self.phrase_end, self.doc = follow[a] + TRIGGER, doc[a]
        self.next_key = self.sums.at(at[a], follow[a] + TRIGGER)
        self.context = _Classes(data, self.sums, self.lo[a], np.minimum(at[a] + width, off[doc[a] + 1]))

    def questions(self) -> tuple:
        """Distinct following phrases, the context of each if there is one only in this chunk, and their number;
        and the contexts of the others."""
        phrase, place, _ = B.repeats(self.next_key)
        first = np.zeros(len(phrase), dtype=np.int64)
        first[place] = self.context.place
        many = np.zeros(len(phrase), dtype=bool)
        many[place[self.context.place != first[place]]] = True
        alone = ~many[place]
        twice = np.bincount(place, minlength=len(phrase)) >= 2
        n = np.bincount(place[self.context.first], minlength=len(phrase)).astype(np.uint64)
        context, at, count = np.unique(self.context.place[~alone], return_inverse=True, return_counts=True)
        return phrase, place, first, n, many, twice & ~many, alone, context, at.reshape(-1), count >= 2

    def hard(self, table: pa.Table, boards: int) -> tuple[np.ndarray, tuple, np.ndarray]:
        """From the answers: groups whose windows all repeat; regions (phrase key, first window, windows) sorted by
        key; and starts to be compared one by one."""
        phrase, place, _, _, _, _, alone, context, at, _ = self.questions()
        settled, emits = np.zeros(len(self.asks), dtype=bool), np.zeros(len(self.asks), dtype=bool)
        several, repeated, leads, crowded = B.answers(table, _NEXT, phrase, boards, 4)
        settled[alone] = repeated[place[alone]]
        emits[alone] = leads[place[alone]]
        repeated, leads = B.answers(table, _CONTEXT, self.context.key[context], boards, 2)
        settled[~alone] = repeated[at]
        emits[~alone] = leads[at]
        emits &= several[place]
        # a window that holds a phrase which occurs once cannot repeat: it must end before the first such
        once = ~(several[place] | settled)
        n = len(once)
        after = np.minimum.accumulate(np.where(once, np.arange(n), n)[::-1])[::-1]
        bound = np.full(n, np.iinfo(np.int64).max)
        has = after < n
        has[has] = self.doc[after[has]] == self.doc[has]
        bound[has] = self.phrase_end[after[has]] - self.width
        # of equal contexts in this chunk, one compares its windows
        one = np.zeros(len(self.asks), dtype=bool)
        one[self.context.first] = True
        go = np.flatnonzero(emits & one)
        at = self.asks[go]
        low, high = self.whole[at], np.minimum(self.hi[at] + 1, bound[go])
        some = high > low
        near = some & ~crowded[place[go]]
        order = np.argsort(self.next_key[go[near]], kind="stable")
        regions = tuple(x[near][order] for x in (self.next_key[go], low, high - low))
        far = some & crowded[place[go]]
        starts = np.concatenate((spread(self.lo, self.whole), spread(low[far], high[far])))
        return self.asks[settled], regions, starts


def _first_answer(kind: int, parts: list, crowd: int) -> list[list[np.ndarray]]:
    sizes = [n for _, n, _ in parts]
    ends = np.cumsum(sizes)[:-1]
    if kind == _NEXT:
        cols = [np.concatenate(x) for x in zip(*(B.unpack(n, body, [np.uint32, np.uint64, np.uint32], 2) for _, n, body in parts), strict=True)]
        phrase, context, rest, many, twice = cols
        order = np.lexsort((rest, context, many, phrase))
        p, c, e, m = phrase[order], context[order], rest[order], many[order]
        new_phrase = np.ones(len(p), dtype=bool)
        new_phrase[1:] = p[1:] != p[:-1]
        new_pair = new_phrase.copy()
        new_pair[1:] |= (c[1:] != c[:-1]) | (e[1:] != e[:-1]) | m[1:] | m[:-1]
        group = np.cumsum(new_phrase) - 1
        pairs = np.bincount(group, weights=new_pair) + np.bincount(group, weights=m)
        several_s = pairs[group] >= 2
        load = np.bincount(group, weights=np.where(m, c, new_pair).astype(np.float64))
        pair = np.cumsum(new_pair) - 1
        repeated_s = ((np.bincount(pair)[pair] >= 2) | (np.bincount(pair, weights=twice[order])[pair] > 0)) & ~m
        leads_s = ~repeated_s | new_pair
        back = np.empty(len(p), dtype=np.int64)
        back[order] = np.arange(len(p))
        bits = [x[back] for x in (several_s, repeated_s, leads_s, load[group] > crowd)]
    else:
        context, rest, twice = (np.concatenate(x) for x in zip(*(B.unpack(n, body, [np.uint64, np.uint32], 1) for _, n, body in parts), strict=True))
        _, place, count = B.repeats_wide(np.stack((context, rest.astype(np.uint64)), axis=1))
        repeated = (count[place] >= 2) | (np.bincount(place, weights=twice)[place] > 0)
        lead = np.zeros(len(context), dtype=bool)
        lead[np.unique(place, return_index=True)[1]] = True
        bits = [repeated, ~repeated | lead]
    return [list(x) for x in zip(*(np.split(b, ends) for b in bits), strict=True)]


def _ranks(keys: np.ndarray, end: np.ndarray, depth: int, most: int) -> np.ndarray:
    """Ranks of suffixes, equal ones for equal suffixes, from keys that order their first depth items.

    A suffix ends before its place in end, and what lies behind an end is smaller than all else. A rank is the
    number of smaller suffixes, so only those that still share one are looked at again, by the rank of what
    follows at twice the depth; until most items, or until nothing changes.
    """
    order = np.argsort(keys, kind="stable")
    open_, rank, before = order, np.zeros(len(keys), dtype=np.int64), np.zeros(len(keys), dtype=np.int64)
    key, depth = keys[order], depth / 2
    while len(open_):
        here = np.arange(len(open_))
        old, new = np.ones(len(open_), dtype=bool), np.ones(len(open_), dtype=bool)
        old[1:] = before[1:] != before[:-1]
        new[1:] = old[1:] | (key[1:] != key[:-1])
        start = np.maximum.accumulate(np.where(new, here, 0))
        after = before + start - np.maximum.accumulate(np.where(old, here, 0))
        rank[open_] = after
        depth = int(2 * depth)
        if depth >= most or len(open_) < len(keys) and (after == before).all():
            break
        twins = ~new
        twins[:-1] |= ~new[1:]
        open_, before = open_[twins], after[twins]
        to = open_ + depth
        key = np.where(to < end[open_], rank[np.minimum(to, len(keys) - 1)] + 1, 0)
        order = np.lexsort((key, before))
        open_, before, key = open_[order], before[order], key[order]
    return rank


def suffix_order(text: np.ndarray, off: np.ndarray, starts: np.ndarray, spacing: int, width: int) -> np.ndarray:
    """The starts (places in text, with width bytes before the end of their region) in the order of the text
    that begins there, as far as width bytes go; off: the offsets of the regions of text."""
    at = _triggers(text, spacing)
    at = at[at + TRIGGER <= off[np.searchsorted(off, at, side="right")]]
    # phrases: from a region's start or a trigger to the end of the next trigger, or of the region
    lo = np.union1d(off[:-1], at)
    region = np.searchsorted(off, lo, side="right") - 1
    last = np.ones(len(lo), dtype=bool)
    last[:-1] = region[1:] != region[:-1]
    hi = np.where(last, off[region + 1], np.append(lo[1:], 0) + TRIGGER)
    # the dictionary
    known: dict[tuple[bytes, bool], int] = {}
    data = text.tobytes()
    phrase = np.fromiter((known.setdefault((data[a:b], z), len(known)) for a, b, z in zip(lo.tolist(), hi.tolist(), last.tolist(), strict=True)), dtype=np.int64, count=len(lo))
    words = [w for w, _ in known]
    size = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    begin = np.concatenate(([0], np.cumsum(size)))
    letters = np.frombuffer(b"".join(words), dtype=np.uint8)
    end = np.repeat(begin[1:], size)
    # its suffix array, from seven letters on
    here = np.arange(len(letters))
    first = np.zeros(len(letters), dtype=np.int64)
    for j in range(7):
        first = first << 9 | np.where(here + j < end, letters[np.minimum(here + j, len(letters) - 1)].astype(np.int64) + 1, 0)
    rank = _ranks(first, end, 7, int(size.max(initial=0)))
    # the suffix array of the parse, whose letters are the ranks of the phrases
    of_region = np.append(np.flatnonzero(last) + 1, 0)[np.cumsum(last) - last]
    follow = _ranks(rank[begin[phrase]], of_region, 1, width)
    # both together
    t = np.searchsorted(lo, starts, side="right") - 1
    after = np.where(last[t], 0, follow[np.minimum(t + 1, len(lo) - 1)] + 1)
    return np.lexsort((after, rank[begin[phrase[t]] + starts - lo[t]]))


def repeated_windows(text: np.ndarray, off: np.ndarray, starts: np.ndarray, spacing: int, width: int) -> np.ndarray:
    """Which of the starts have width bytes in common with another one."""
    order = suffix_order(text, off, starts, spacing, width)
    a, b = starts[order[:-1]], starts[order[1:]]
    same = np.arange(len(a))
    step = 8 if width >= 8 else 1
    letters = np.ndarray((max(0, len(text) - step + 1),), dtype=f"<u{step}", buffer=text.tobytes(), strides=(1,))  # step bytes from each place on
    for j in [*range(0, width - step, step), width - step]:
        same = same[letters[a[same] + j] == letters[b[same] + j]]
    out = np.zeros(len(starts), dtype=bool)
    out[order[same]] = True
    out[order[same + 1]] = True
    return out


def _second_answer(kind: int, parts: list, spacing: int, width: int) -> list[list[np.ndarray]]:
    if kind == _REGION:
        counts = [np.frombuffer(body, dtype=np.uint32, count=n).astype(np.int64) for _, n, body in parts]
        text = np.frombuffer(b"".join(body[4 * n :] for _, n, body in parts), dtype=np.uint8)
        n = np.concatenate(counts)
        off = np.concatenate(([0], np.cumsum(n + width - 1)))
        hot = repeated_windows(text, off, spread(off[:-1], off[:-1] + n), spacing, width)
        return [[x] for x in np.split(hot, np.cumsum([c.sum() for c in counts])[:-1])]
    keys, twice = [], []
    for _, n, body in parts:
        keys.append(np.frombuffer(body, dtype=np.uint64, count=2 * n).reshape(-1, 2))
        twice += B.unpack(n, body[16 * n :], [], 1)
    _, place, count = B.repeats_wide(np.concatenate(keys))
    hot = (count >= 2) | (np.bincount(place, weights=np.concatenate(twice), minlength=len(count)) > 0)
    return [[x] for x in np.split(hot[place], np.cumsum([n for _, n, _ in parts])[:-1])]


def _in_order(table: pa.Table) -> pa.Table:
    """The rows of a chunk by id and text. Regions of one phrase are told apart by their place in the chunk, and its
    rows may arrive in another order in each pass."""
    return table.sort_by([("doc_id", "ascending"), ("text", "ascending")])


def _chunks(docs: DataFrame, width: int, chunk_bytes: int, board_keys: int, spacing: int, finish, schema: str, crowd: int) -> DataFrame:
    dealt, size = B.deal(docs, chunk_bytes)
    phrase_boards = max(1, math.ceil(size / spacing / board_keys))
    window_boards = max(1, math.ceil(size / 24 / board_keys))
    region_boards = max(1, math.ceil(size / (4 * board_keys)))

    def parse(table: pa.Table) -> pa.Table:
        chunk = table["chunk"][0].as_py()
        g = _Groups(*text_bytes(_in_order(table)["text"]), width, spacing)
        phrase, _, first, n, many, twice, _, context, _, again = g.questions()
        low = lambda x: (x & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        sha = g.context.digests()  # of these, 96 bits travel
        told = np.where(many, n, sha[first, 0]) if len(first) else n
        return B.asked_table([*B.ask(chunk, _NEXT, phrase, [low(phrase), told, low(sha[first, 1])], [many, twice], phrase_boards), *B.ask(chunk, _CONTEXT, g.context.key[context], [sha[context, 0], low(sha[context, 1])], [again], phrase_boards)])

    def windows(g: _Groups, starts: np.ndarray) -> _Classes:
        return _Classes(g.data, g.sums, starts, starts + width)

    def compare(key, left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return B.asked_table([])
        chunk = key[0].as_py()
        g = _Groups(*text_bytes(_in_order(left)["text"]), width, spacing)
        _, (phrase, low, n), starts = g.hard(right, phrase_boards)
        rows, at = [], B.cuts(phrase, region_boards)
        for b in np.flatnonzero(np.diff(at)):
            part = slice(at[b], at[b + 1])
            rows.append((int(b), chunk, _REGION, int(at[b + 1] - at[b]), n[part].astype(np.uint32).tobytes() + g.data[spread(low[part], low[part] + n[part] + width - 1)].tobytes()))
        w = windows(g, starts)
        return B.asked_table([*rows, *B.ask(chunk, _WINDOW, w.key, [w.digests()], [w.count >= 2], window_boards)])

    def remove(_, left: pa.Table, right: pa.Table) -> pa.Table:
        left = _in_order(left)
        data, off = text_bytes(left["text"])
        gone = np.zeros(len(data), dtype=bool)
        if len(data):
            g = _Groups(data, off, width, spacing)
            settled, (phrase, low, n), starts = g.hard(right, phrase_boards)
            w = windows(g, starts)
            (hot,) = B.answers(right, _WINDOW, w.key, window_boards, 1)
            (also,) = B.answers(right, _REGION, np.repeat(phrase, n), region_boards, 1)
            gone = covered(np.concatenate((spread(g.lo[settled], g.hi[settled] + 1), starts[hot[w.place]], spread(low, low + n)[also])), width, len(data))
        return finish(left["doc_id"], data, off, gone)

    by_chunk = dealt.groupBy("chunk")
    first = by_chunk.applyInArrow(parse, B.ASKED).groupBy("board").applyInArrow(B.owner(lambda kind, parts: _first_answer(kind, parts, crowd)), B.ANSWERED)
    second = by_chunk.cogroup(first.groupBy("chunk")).applyInArrow(compare, B.ASKED).groupBy("board").applyInArrow(B.owner(lambda kind, parts: _second_answer(kind, parts, spacing, width)), B.ANSWERED)
    return dealt.groupBy("chunk").cogroup(first.unionByName(second).groupBy("chunk")).applyInArrow(remove, schema)


def _runs(gone: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of removed runs; a run ends with its row."""
    n = len(gone)
    edge = np.zeros(n + 1, dtype=bool)
    edge[off] = True
    before, after = np.zeros(n, dtype=bool), np.zeros(n, dtype=bool)
    before[1:], after[:-1] = gone[:-1], gone[1:]
    return np.flatnonzero(gone & (edge[:n] | ~before)), np.flatnonzero(gone & (edge[1:] | ~after)) + 1


def _digest(ids, data, off, gone) -> pa.Table:
    starts, _ = _runs(gone, off)
    sums = np.concatenate(([0], np.cumsum(gone)))
    removed = sums[off[1:]] - sums[off[:-1]]
    spans = np.searchsorted(starts, off[1:]) - np.searchsorted(starts, off[:-1])
    sha = [hashlib.sha256((data[a:b][~gone[a:b]] if r else data[a:b]).tobytes()).hexdigest() for a, b, r in zip(off[:-1], off[1:], removed, strict=True)]
    return pa.table({"doc_id": ids, "n_bytes": np.diff(off), "n_removed": removed.astype(np.int64), "n_spans": spans.astype(np.int64), "kept_sha256": sha})


def _whole(ids, data, off, gone) -> pa.Table:
    starts, ends = _runs(gone, off)
    a, b = np.searchsorted(starts, off[:-1]), np.searchsorted(starts, off[1:])
    return pa.table({
        "doc_id": ids, "n_bytes": np.diff(off),
        "starts": pa.array([(starts[i:j] - o).tolist() for i, j, o in zip(a, b, off[:-1], strict=True)], pa.list_(pa.int64())),
        "ends": pa.array([(ends[i:j] - o).tolist() for i, j, o in zip(a, b, off[:-1], strict=True)], pa.list_(pa.int64())),
        "kept": pa.array([data[i:j][~gone[i:j]].tobytes() for i, j in zip(off[:-1], off[1:], strict=True)], pa.binary()),
    })


def repeated_spans(docs: DataFrame, width: int = 200, chunk_bytes: int = 1_500_000, board_keys: int = 400_000, spacing: int = SPACING, digest: bool = False, crowd: int = 4096) -> DataFrame:
    """Bytes covered by a string of ``width`` bytes that also starts anywhere else in the corpus.

    docs: doc_id, text (other columns are ignored). One row per input row, repeated rows included:
    removed runs as ``starts``/``ends`` and the bytes kept, or their counts and digest. A null text is
    empty; texts shorter than the width lose nothing; all copies of a repeated string go, the first
    one too. A null doc_id is kept as such. An empty table gives no rows.
    """
    if digest:
        return _chunks(docs, width, chunk_bytes, board_keys, spacing, _digest, RESULT, crowd)
    return _chunks(docs, width, chunk_bytes, board_keys, spacing, _whole, SPANS, crowd)
