"""Repeated passages of words, by fixed-block anchors.

Every document is cut into reference blocks of ``size // 2`` words that don't overlap; they are the
index. Every rolling window of a block's length probes it. Two equal passages of ``size`` words both
hold a whole block of their own, which the other's rolling windows meet, so each passage has a hit.
Hits are extended: around them, the windows of ``size`` words are compared by fingerprints; runs of consecutive
repeated windows are the maximal exact repeats. A window that also starts earlier (smaller doc_id, or
the same document further ahead) is removed, that is, all words it covers.

Three passes over chunks (see ``chunks``): blocks and probes to hash ranges and a bit back; windows around
hits to hash ranges with their first document and a bit back; then removal. Nothing is sent but distinct
hashes of a chunk, so hot passages and huge groups of copies stay small.

Null and empty texts have no words. Documents are ordered by doc_id; rows that share a doc_id are taken as one after
the other, ordered by text; rows without doc_id come last, in a fixed order of no meaning. Texts of any length are
whole. Windows are compared by 64 bits from each of two hashes of their words, not word by word.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common as C
from .chunks import MESSAGE, Plan, Reader, Writer, doc_order, merge, merged_hot, messages, ordered, parts, received, released

_OUT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("text", pa.string())])
SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string, text string"


class Words:
    """Words of a chunk: hashes (``second``: of another hash function too), row of each, place in its row."""

    def __init__(self, table: pa.Table, second: bool = False):
        hashes, others, rows = [], [], []
        for first, data, offsets in parts(table):
            starts, ends, row = C.word_spans(data, offsets, C.IS_DARK)
            hashes.append(C.span_hashes(data, starts, ends))
            if second:
                others.append(C.span_hashes(data, starts, ends, 2))
            rows.append((row + first).astype(np.int32))
        self.hash, self.other = (np.concatenate([*h, np.zeros(0, np.uint64)]) for h in (hashes, others))
        self.row = np.concatenate([*rows, np.zeros(0, np.int32)])
        self.n = np.bincount(self.row, minlength=len(table)).astype(np.int64)

    def place(self) -> np.ndarray:
        return np.arange(len(self.row)) - np.repeat(np.cumsum(self.n) - self.n, self.n)

    def whole(self, size: int) -> np.ndarray:
        """Whether the window of ``size`` words from each word ends in the same row."""
        m = max(0, len(self.row) - size + 1)
        return self.row[:m] == self.row[size - 1 : size - 1 + m]


def _probes(words: Words, block: int, bits: int):
    """Sorted distinct hashes of the rolling windows; whether each stands twice here, whether it is a block; all hashes by place."""
    grams = C.gram_hashes(words.hash, block) >> np.uint64(64 - bits)
    ok = words.whole(block)
    keys = (grams << np.uint64(1)) | (words.place()[: len(grams)] % block == 0)
    keys = np.sort(keys[ok])
    plain = keys >> np.uint64(1)
    last = np.append(plain[1:] != plain[:-1], True) if len(plain) else np.zeros(0, bool)
    ends = np.flatnonzero(last)
    sizes = np.diff(ends, prepend=-1)
    return plain[ends], sizes > 1, (keys[ends] & np.uint64(1)).astype(bool), grams, ok


def _windows(words: Words, candidates: np.ndarray, size: int):
    """Fingerprints of candidate windows, by two hashes of their words: the distinct ones, and which of them each is."""
    a = C.gram_hashes(words.hash, size, 1)[candidates] if len(candidates) else np.zeros(0, np.uint64)
    b = C.gram_hashes(words.other, size, 2)[candidates] if len(candidates) else np.zeros(0, np.uint64)
    order = np.lexsort((b, a))
    new = np.ones(len(order), bool)
    new[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    which = np.empty(len(order), np.int64)
    which[order] = np.cumsum(new) - 1
    first = np.full(int(new.sum()), len(words.row), np.int64)
    np.minimum.at(first, which, np.arange(len(order))) if len(order) else None
    return a[order][new], b[order][new], first, which


def _merged_first(readers: list[Reader]) -> list[bytes]:
    """Each body: fingerprints and the first document with each; a bit for each: no chunk has an earlier document."""
    own = [(r.numbers(True), r.raw(np.uint64), r.numbers()) for r in readers]
    a, b, doc = (np.concatenate([o[k] for o in own]) for k in range(3))
    order = np.lexsort((doc, b, a))
    new = np.ones(len(order), bool)
    new[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    first = np.zeros(len(order), bool)
    first[order] = new
    cuts = np.cumsum([0] + [len(o[0]) for o in own])
    return [Writer().bits(first[x:y]).done() for x, y in zip(cuts, cuts[1:], strict=False)]


def _joined(rows) -> np.ndarray:
    found = [Reader(body).bits() for bucket, _, body in rows if bucket >= 0]
    return np.concatenate([*found, np.zeros(0, bool)])


def without_repeats(docs: DataFrame, size: int = 20, plan: Plan | None = None, carry: bool = False) -> DataFrame:
    """One row per document: words, removed words, digest of the kept words and the text without the removed
    ones (with the white space after each). ``carry``: also ``rest``, the row's other columns."""
    plan, block = plan or Plan(docs), size // 2
    dealt = plan.deal(docs, carry)
    schema = T._parse_datatype_string(SCHEMA)
    schema = T.StructType([*schema, *(f for f in dealt.schema if f.name == "rest")])
    bits = min(60, plan.bits)

    def anchors(key, table):
        keys, many, anchor, _, _ = _probes(Words(ordered(table)), block, bits)
        return messages([(k, key[0].as_py(), Writer().numbers(keys[x:y], True).bits(many[x:y]).bits(anchor[x:y]).done()) for k, x, y in plan.by_bucket(keys, bits)])

    def extend(key, left, right):
        chunk, table = key[0].as_py(), ordered(left)
        words = Words(table, True)
        keys, _, _, grams, ok = _probes(words, block, bits)
        hot = keys[_joined(received(right))]
        near = np.minimum(np.searchsorted(hot, grams), max(0, len(hot) - 1))
        at = (hot[near] == grams) & ok if len(hot) else np.zeros(len(grams), bool)
        seen = np.concatenate([[0], np.cumsum(at)])
        whole = words.whole(size)
        candidates = np.flatnonzero(whole & (seen[size - block + 1 :][: len(whole)] > seen[: len(whole)])) if len(whole) else np.zeros(0, np.int64)
        a, b, first, _ = _windows(words, candidates, size)
        doc = doc_order(table)[words.row[candidates[first]]] if len(first) else np.zeros(0, np.int64)
        mask = np.zeros(len(words.row), bool)
        mask[candidates] = True
        sent = [(-1, chunk, Writer().bits(mask).done())]
        sent += [(k, chunk, Writer().numbers(a[x:y], True).raw(b[x:y]).numbers(doc[x:y]).done()) for k, x, y in plan.by_bucket(a, 64)]
        return messages(sent)

    def remove(key, left, right):
        table, rows = ordered(left), received(right)
        words = Words(table, True)
        mask = next((Reader(body).bits() for bucket, _, body in rows if bucket < 0), np.zeros(len(words.row), bool))
        candidates = np.flatnonzero(mask)
        a, _, first, which = _windows(words, candidates, size)
        repeated = np.ones(len(candidates), bool)
        repeated[first] = False
        repeated[first] |= ~_joined(rows)
        cover = np.zeros(len(words.row) + 1, np.int32)
        np.add.at(cover, candidates[repeated], 1)
        np.add.at(cover, candidates[repeated] + size, -1)
        return _result(table, words, np.cumsum(cover[:-1]) > 0)

    hot = merge(dealt.groupBy("chunk").applyInArrow(released(anchors), MESSAGE), merged_hot)
    first = merge(dealt.groupBy("chunk").cogroup(hot.groupBy("chunk")).applyInArrow(released(extend), MESSAGE), _merged_first)
    return dealt.groupBy("chunk").cogroup(first.groupBy("chunk")).applyInArrow(released(remove), schema)


def _result(table: pa.Table, words: Words, gone: np.ndarray) -> pa.Table:
    removed = np.bincount(words.row[gone], minlength=len(table)).astype(np.int64)
    digests, texts, word = [], [], 0
    for _, data, offsets in parts(table):
        starts, ends, row = C.word_spans(data, offsets, C.IS_DARK)
        out = gone[word : word + len(starts)]
        word += len(starts)
        keep = ~out
        size = (ends - starts)[keep] + 1
        at = np.cumsum(size) - size
        body = np.full(int(size.sum()), 32, np.uint8)
        source = np.arange(len(body)) - np.repeat(at - starts[keep], size)
        inside = np.ones(len(body), bool)
        inside[at + size - 1] = False
        body[inside] = data[source[inside]]
        edges = np.searchsorted(row[keep], np.arange(len(offsets)))
        cut = np.append(at, len(body))[edges]
        joined = body.tobytes()
        digests += [hashlib.sha256(joined[x : y - 1] if y > x else b"").hexdigest() for x, y in zip(cut, cut[1:], strict=False)]
        # the text: a removed word goes with the white space up to the next word
        nexts = np.minimum(np.append(starts[1:], len(data)), offsets[row + 1]) if len(starts) else starts
        drop = np.zeros(len(data) + 1, np.int32)
        np.add.at(drop, starts[out], 1)
        np.add.at(drop, nexts[out], -1)
        left = np.cumsum(drop[:-1]) == 0
        kept = data[left].tobytes()
        cut = np.concatenate([[0], np.cumsum(left)])[offsets]
        texts += [kept[x:y].decode() for x, y in zip(cut, cut[1:], strict=False)]
    nulls = table["text"].is_null().to_pylist()
    out = pa.Table.from_arrays([table["doc_id"].combine_chunks(), pa.array(words.n), pa.array(removed), pa.array(digests, pa.string()), pa.array([None if z else x for z, x in zip(nulls, texts, strict=True)], pa.string())], schema=_OUT)
    return out.append_column("rest", table["rest"]) if "rest" in table.column_names else out


def deduplicated(docs: DataFrame, size: int = 20) -> DataFrame:
    """The table with repeated passages cut out of ``text``; each row carries its other columns (of any name) through the
    passes, n_chars follows the text."""
    new = without_repeats(docs, size, carry=True)

    def column(c: str):
        if c == "text":
            return F.col("text").cast(docs.schema[c].dataType)
        return F.char_length("text").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col("rest")[c].alias(c)

    return new.select(*[column(c) for c in docs.columns])
