"""Repeated byte strings across documents, by suffix arrays of shards.

A string of ``size`` bytes has one anchor, the string of ``GRAM`` bytes in it with the least hash (the leftmost
of equals), whatever document it stands in. So equal strings share the anchor, and:

1. each chunk of documents sends its distinct anchors, and learns which stand in two documents at least;
2. around those, each run of strings with one anchor is one snippet; a chunk sends its distinct snippets with
   their first document to the shard of the anchor. An anchor with many different snippets (a common line among ever
   other texts) is split: each of its strings goes alone, once a chunk, to the shard of its own hash;
3. a shard sorts all suffixes of its snippets by external induced sorting (``suffix_array``); suffixes whose
   common prefix is ``size`` or more are one string; each chunk gets a bit for each string of its snippets:
   a document before its own first one has it;
4. each chunk removes every byte that such a string covers.

Order is that of doc_id (nulls last); rows that share a doc_id are one document: none is before the other.
Null and empty texts have no bytes; texts of any length are whole; matches don't cross documents.
Shards hold snippets that are distinct in their chunk, so a group of copies is one entry of each chunk; an anchor that
stands in ``crowd`` chunks with ``DIVERSE`` different snippets in one of them, and with so many in all that they would be a
good part of a shard, is split, so common lines don't fill a shard. Split strings have ``size`` bytes each instead of one and
a share of the rest, so rarer anchors stay whole.
"""

from __future__ import annotations

import hashlib
from copy import copy

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import common as C
from .chunks import MESSAGE, Plan, Reader, Writer, doc_order, merge, messages, ordered, parts, received, released
from .suffix_array import induce

#: Bytes of an anchor. Shorter ones repeat by chance in ever more texts as a table grows; longer ones are more.
GRAM = 24
#: When an anchor is split: different snippets in a chunk, chunks that hold it (so many bytes of text in all), and snippets in
#: all chunks together (one for so many bytes of a chunk; a snippet has about 70 bytes, so they'd be a sixth of a chunk).
DIVERSE, CROWD_BYTES, CROWD_SHARE = 8, 384 << 20, 384
_OUT = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("spans", pa.list_(pa.int64()))])
SCHEMA = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<long>"
#: UTF-8 has no byte above 0xF7, so all bytes can go up by one and 0 is free to end a snippet.
_UP = (np.arange(256) + 1).astype(np.uint8)


def anchors(data: np.ndarray, offsets: np.ndarray, size: int):
    """Snippets of the rows: first string, number of strings, hash of the anchor; a snippet has size - 1 more bytes."""
    n = len(data)
    none = np.zeros(0, np.int64)
    if n < size:
        return none, none, np.zeros(0, np.uint64)
    words = np.ndarray((n - 7,), "<u8", buffer=np.ascontiguousarray(data), strides=(1,)).astype(np.uint64)
    gram = min(GRAM, size // 8 * 8)
    m = n - gram + 1
    grams = np.zeros(m, np.uint64)
    for j, c in enumerate(C.draws(gram // 8, 31)):
        grams += words[8 * j : 8 * j + m] * c
    grams = C.mix(grams)
    low = np.uint64((1 << 24) - 1)
    if n > 1 << 24:  # one very long text: in stretches that overlap by a string
        return _long_anchors(data, offsets, size)
    least = (grams & ~low) | np.arange(m, dtype=np.uint64)
    width, have = size - gram + 1, 1
    while 2 * have <= width:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    if have < width:
        least = np.minimum(least[: len(least) - (width - have)], least[width - have :])
    anchor = (least & low).astype(np.int64)
    lengths = np.diff(offsets)
    rows = np.repeat(np.arange(len(lengths)), lengths)[: len(anchor)]
    inside = np.arange(len(anchor)) + size <= offsets[rows + 1]
    new = inside.copy()
    new[1:] &= ~(inside[:-1] & (anchor[1:] == anchor[:-1]) & (rows[1:] == rows[:-1]))
    first = np.flatnonzero(new)
    after = np.flatnonzero(new | ~inside)
    ends = np.append(after, len(anchor))[np.searchsorted(after, first, "right")]
    return first, ends - first, C.mix(grams[anchor[first]] + np.uint64(1))  # hashes of anchors are low: spread them again


def _long_anchors(data: np.ndarray, offsets: np.ndarray, size: int, step: int = 1 << 23):
    out = []
    for row in range(len(offsets) - 1):
        for at in range(int(offsets[row]), int(offsets[row + 1]), step):
            to = min(int(offsets[row + 1]), at + step + size - 1)
            first, count, gram = anchors(data[at:to], np.array([0, to - at]), size)
            out.append((first + at, count, gram))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


class Snippets:
    """Snippets of a chunk, row by row: bytes of the chunk, first string, strings, anchor, row."""

    def __init__(self, table: pa.Table, size: int, hold: bool = True):
        first, count, gram, row, body, base = [], [], [], [], [], 0
        for at, data, offsets in parts(table):
            f, c, g = anchors(data, offsets, size)
            first.append(f + base)
            count.append(c)
            gram.append(g)
            row.append((np.searchsorted(offsets, f, "right") - 1 + at).astype(np.int64))
            body.append(data)
            base += len(data)
        join = lambda xs, kind: np.concatenate([*xs, np.zeros(0, kind)])
        self.first, self.count, self.row, self.gram = join(first, np.int64), join(count, np.int64), join(row, np.int64), join(gram, np.uint64)
        self.data = join(body, np.uint8) if hold else None

    def sorted_hashes(self, docs: np.ndarray, bits: int, size: int = 0):
        """Distinct anchors, whether each stands in two documents of the chunk, and its snippets: below DIVERSE all, else
        (given ``size``) the different ones, but one less than DIVERSE at least."""
        key = self.gram >> np.uint64(64 - bits)
        order = np.argsort(key, kind="stable")  # rows, and so documents, rise within an anchor
        key, doc = key[order], docs[self.row[order]]
        starts = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
        ends = np.append(starts[1:], len(key)) - 1
        found = np.minimum(ends - starts + 1, DIVERSE - 1)
        for i in np.flatnonzero(ends - starts + 1 >= DIVERSE) if size else ():
            own = order[starts[i] : ends[i] + 1]
            found[i] = max(found[i], len(np.unique(C.span_hashes(self.data, self.first[own], self.first[own] + self.count[own] + size - 1))))
        return key[starts], doc[starts] != doc[ends] if len(key) else np.zeros(0, bool), found

    def pick(self, mask: np.ndarray, crowded: np.ndarray, size: int) -> Snippets:
        """The snippets of the mask; crowded ones as a snippet for each string, by the string's own hash."""
        at = np.flatnonzero(mask)
        alone = crowded[at]
        n = np.where(alone, self.count[at], 1)
        of, alone = np.repeat(at, n), np.repeat(alone, n)
        out = copy(self)
        out.first = self.first[of] + np.where(alone, np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n), 0)
        out.count, out.row, out.gram = np.where(alone, 1, self.count[of]), self.row[of], self.gram[of].copy()
        out.gram[alone] = C.mix(C.span_hashes(self.data, out.first[alone], out.first[alone] + size) + np.uint64(1))
        return out


def _distinct(snippets: Snippets, docs: np.ndarray, size: int):
    """Distinct snippets: which each is, the first that has it, the distinct ones by anchor."""
    start, end = snippets.first, snippets.first + snippets.count + size - 1
    a, b = (C.span_hashes(snippets.data, start, end, s) for s in (1, 2))
    order = np.lexsort((np.arange(len(a)), b, a, snippets.gram))
    new = np.ones(len(order), bool)
    new[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    which = np.empty(len(order), np.int64)
    which[order] = np.cumsum(new) - 1
    return which, order[new], docs[snippets.row[order[new]]]


def merged_crowds(readers: list[Reader], crowd: int, most: int = 0) -> list[bytes]:
    """Each body: sorted anchors, flags ``many`` (in two documents there) and numbers of snippets. The answer has two bits for
    each: whether the anchor stands in two documents, and whether it is to be split (``most``: only with more snippets in all)."""
    own = [(r.numbers(True), r.bits(), r.numbers().astype(np.int64)) for r in readers]
    keys, many, found = (np.concatenate([o[k] for o in own]) for k in range(3))
    order = np.argsort(keys, kind="stable")
    starts = np.flatnonzero(np.append(True, np.diff(keys[order]) > 0)) if len(keys) else np.zeros(0, np.int64)
    sizes = np.diff(np.append(starts, len(keys)))
    hot, split = np.zeros(len(keys), bool), np.zeros(len(keys), bool)
    if len(keys):
        hot[order] = np.repeat(np.logical_or.reduceat(many[order], starts) | (sizes > 1), sizes)
        split[order] = np.repeat((np.maximum.reduceat(found[order], starts) >= DIVERSE) & (sizes >= crowd) & (np.add.reduceat(found[order], starts) > most), sizes)
    cuts = np.cumsum([0] + [len(o[0]) for o in own])
    return [Writer().bits(hot[x:y]).bits(split[x:y]).done() for x, y in zip(cuts, cuts[1:], strict=False)]


def _holds(found: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Which of ``own`` are in the sorted ``found``."""
    return found[np.minimum(np.searchsorted(found, own), len(found) - 1)] == own if len(found) else np.zeros(len(own), bool)


def _spread(data: np.ndarray, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """data[start : start + length] of all spans, end to end."""
    out, total = np.empty(int(length.sum()), data.dtype), np.cumsum(length)
    for a in range(0, len(start), C.PIECE // 64):
        own = length[a : a + C.PIECE // 64]
        lo, hi = int(total[a] - length[a]), int(total[a + len(own) - 1])
        out[lo:hi] = data[np.arange(hi - lo) - np.repeat(np.cumsum(own) - own - start[a : a + len(own)], own)]
    return out


def shard_answers(readers: list[Reader], size: int) -> list[bytes]:
    """Each body: strings and first document of each snippet, and their bytes end to end; the answer has a bit for each string."""
    own = [(r.numbers().astype(np.int64), r.numbers().astype(np.int64), r.raw(np.uint8)) for r in readers]
    count, doc = np.concatenate([o[0] for o in own]), np.concatenate([o[1] for o in own])
    body = np.concatenate([o[2] for o in own])
    length = count + size - 1
    start = np.cumsum(length) - length
    a, b = (C.span_hashes(body, start, start + length, s) for s in (1, 2))
    order = np.lexsort((doc, b, a))
    new = np.ones(len(order), bool)
    new[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    which = np.empty(len(order), np.int64)
    which[order] = np.cumsum(new) - 1
    keep = order[new]  # one of each text, the one of the first document
    t_len, t_doc = length[keep] + 1, doc[keep]
    t_start = np.cumsum(t_len) - t_len
    text = np.zeros(int(t_len.sum()), np.uint8)
    inside = np.ones(len(text), bool)
    inside[t_start + t_len - 1] = False
    text[inside] = _UP[_spread(body, start[keep], length[keep])]
    del body, a, b, order, new, inside
    first_doc = np.zeros(len(text), np.int64)
    owner = np.repeat(np.arange(len(keep), dtype=np.int32), t_len)
    t_last = t_start + t_len - size  # whole strings start before
    most = np.iinfo(np.int64).max
    held_at, held_doc = [], []  # the open group goes over block borders

    def close(at: np.ndarray, docs: np.ndarray, starts: np.ndarray) -> None:
        if len(at):
            first_doc[at] = np.repeat(np.minimum.reduceat(docs, starts), np.diff(np.append(starts, len(at))))

    for at, lcp in induce(text, size):
        at = np.concatenate([*held_at, at])
        cut = np.concatenate([*held_doc, lcp >= size]) if held_doc else lcp >= size
        starts = np.flatnonzero(~cut)
        starts = starts if len(starts) and starts[0] == 0 else np.append(0, starts)
        end = int(starts[-1])
        of = owner[at]
        docs = np.where(at < t_last[of], t_doc[of], most)
        close(at[:end], docs[:end], starts[:-1])
        held_at, held_doc = [at[end:]], [np.append(False, cut[end + 1 :])]
    if held_at:
        of = owner[held_at[0]]
        close(held_at[0], np.where(held_at[0] < t_last[of], t_doc[of], most), np.zeros(1, np.int64))
    out, at = [], 0
    for counts, docs, _ in own:
        mine = which[at : at + len(counts)]
        at += len(counts)
        seen = _spread(first_doc, t_start[mine], counts)
        out.append(Writer().bits(seen < np.repeat(docs, counts)).done())
    return out


def without_repeats(docs: DataFrame, size: int = 50, plan: Plan | None = None, crowd: int | None = None) -> DataFrame:
    """One row per document: bytes, removed bytes, maximal removed runs, digest of what is left, and the runs [start, end, ...).
    crowd: chunks that hold an anchor that is split, however few its snippets are (else as said above)."""
    plan = plan or Plan(docs, bytes_per_key=9)
    dealt, bits = plan.deal(docs), plan.bits
    most = 0 if crowd else plan.chunk_bytes // CROWD_SHARE
    crowd = crowd or max(4, CROWD_BYTES // plan.chunk_bytes)
    shards = copy(plan)
    shards.buckets = max(plan.buckets, 2 * plan.chunks)  # so that a shard has some MB

    def report(key, table):
        table = ordered(table)
        keys, many, found = Snippets(table, size).sorted_hashes(doc_order(table), bits, size)
        return messages([(k, key[0].as_py(), Writer().numbers(keys[x:y], True).bits(many[x:y]).numbers(found[x:y]).done()) for k, x, y in plan.by_bucket(keys, bits)])

    def send(key, left, right):
        chunk, table = key[0].as_py(), ordered(left)
        snippets, order = Snippets(table, size), doc_order(table)
        keys, _, _ = snippets.sorted_hashes(order, bits)
        answers = [(r.bits(), r.bits()) for r in (Reader(b) for _, _, b in received(right))]
        own = snippets.gram >> np.uint64(64 - bits)
        mask, crowded = (_holds(keys[np.concatenate([*(a[k] for a in answers), np.zeros(0, bool)])], own) for k in (0, 1))
        sent = [(-1, chunk, Writer().bits(mask).bits(crowded).done())]
        picked = snippets.pick(mask, crowded, size)
        _, first, doc = _distinct(picked, order, size)
        for k, x, y in shards.by_bucket(picked.gram[first], 64):
            mine = first[x:y]
            sent.append((k, chunk, Writer().numbers(picked.count[mine]).numbers(doc[x:y]).raw(_spread(picked.data, picked.first[mine], picked.count[mine] + size - 1)).done()))
        return messages(sent)

    def remove(key, left, right):
        table, rows = ordered(left), received(right)
        snippets, order = Snippets(table, size), doc_order(table)
        none = np.zeros(len(snippets.row), bool)
        mask, crowded = next(((r.bits(), r.bits()) for r in (Reader(b) for k, _, b in rows if k < 0)), (none, none))
        picked = snippets.pick(mask, crowded, size)
        which, first, doc = _distinct(picked, order, size)
        bit = np.concatenate([*(Reader(b).bits() for k, _, b in rows if k >= 0), np.zeros(0, bool)])
        count = picked.count[first]
        own = np.repeat(order[picked.row] > doc[which], picked.count) if len(which) else np.zeros(0, bool)
        repeated = own | _spread(bit, (np.cumsum(count) - count)[which], picked.count)
        at = _spread(np.arange(len(picked.data)), picked.first, picked.count)[repeated]
        cover = np.zeros(len(snippets.data) + 1, np.int32)
        cover[:-1] += np.bincount(at, minlength=len(snippets.data)).astype(np.int32)
        cover -= np.bincount(at + size, minlength=len(snippets.data) + 1).astype(np.int32)
        return _result(table, snippets.data, np.cumsum(cover[:-1]) > 0)

    hot = merge(dealt.groupBy("chunk").applyInArrow(released(report), MESSAGE), lambda readers: merged_crowds(readers, crowd, most))
    sent = dealt.groupBy("chunk").cogroup(hot.groupBy("chunk")).applyInArrow(released(send), MESSAGE)
    return dealt.groupBy("chunk").cogroup(merge(sent, lambda readers: shard_answers(readers, size)).groupBy("chunk")).applyInArrow(released(remove), SCHEMA)


def _result(table: pa.Table, data: np.ndarray, gone: np.ndarray) -> pa.Table:
    _, offsets = C.flat(table["text"])
    n = len(table)
    before = np.zeros(len(gone), bool)
    before[1:] = gone[:-1]
    after = np.zeros(len(gone), bool)
    after[:-1] = gone[1:]
    edges = offsets[(offsets > 0) & (offsets < len(data))]
    before[edges] = False
    after[edges - 1] = False
    starts, ends = np.flatnonzero(gone & ~before), np.flatnonzero(gone & ~after) + 1
    row = np.searchsorted(offsets, starts, "right") - 1
    spans = np.bincount(row, minlength=n).astype(np.int64)
    removed = np.bincount(row, weights=ends - starts, minlength=n).astype(np.int64)
    kept = data[~gone].tobytes()
    cut = np.concatenate([[0], np.cumsum(~gone)])[offsets]
    sha = [hashlib.sha256(kept[a:b]).hexdigest() for a, b in zip(cut, cut[1:], strict=False)]
    runs = np.stack([starts - offsets[row], ends - offsets[row]], 1).ravel()
    lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(2 * spans)]).astype(np.int32)), pa.array(runs.astype(np.int64)))
    return pa.Table.from_arrays([table["doc_id"].combine_chunks(), pa.array(np.diff(offsets)), pa.array(removed), pa.array(spans), pa.array(sha, pa.string()), lists], schema=_OUT)
