"""Repeats of bytes and of words against brute force, over several chunks and awkward rows."""

import hashlib
import random
import re

import numpy as np
import pytest

from approxdq.llm import block_dedup, suffix_dedup
from approxdq.llm.chunks import Plan, Reader, Writer
from approxdq.llm.suffix_array import suffix_array

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def corpus(seed, n=60):
    r = random.Random(seed)
    vocab = ["the", "of", "a", "é", "über", "lorem", "ipsum", "x" * 30, "…"]
    words = lambda k: [r.choice(vocab) for _ in range(k)]
    shared = [words(k) for k in (19, 20, 21, 60)]
    out = []
    for i in range(n):
        body = words(r.randint(0, 120))
        for s in r.sample(shared, r.randint(0, 2)):
            at = r.randint(0, len(body))
            body[at:at] = s
        out.append((i * 7 % n, r.choice([" ", "\n", "  "]).join(body)))
    out += [(n, None), (n + 1, ""), (n + 2, out[0][1]), (n + 3, out[0][1]), (n + 4, "\x00" * 70 + "z" * 200), (n + 5, "z" * 90 + "\x00" * 51), (n + 6, "ab " * 400)]
    return out


def test_arrays_are_packed_and_read_back():
    x = np.sort(np.random.default_rng(0).integers(0, 1 << 50, 1000)).astype(np.uint64)
    body = Writer().numbers(x, True).numbers(np.array([5, 0], np.int64)).bits(x % 2 == 0).raw(x).numbers(np.zeros(0)).done()
    r = Reader(body)
    assert (r.numbers(True) == x).all() and list(r.numbers()) == [5, 0] and (r.bits() == (x % 2 == 0)).all() and (r.raw(np.uint64) == x).all() and len(r.numbers()) == 0


@pytest.mark.parametrize("limit,block", [(3, 2), (50, 7), (1 << 20, 1 << 16)])
def test_suffix_array_and_common_prefixes(limit, block):
    r = random.Random(limit)
    for k in range(60):
        t = bytes(r.choice(b"ab" if k % 2 else b"abcdz") for _ in range(r.randint(1, 50)))
        sa = sorted(range(len(t)), key=lambda i: t[i:])
        lcp = [0] + [next((k for k in range(len(t)) if t[a + k : a + k + 1] != t[b + k : b + k + 1] or b + k >= len(t) or a + k >= len(t)), 0) for a, b in zip(sa, sa[1:])]
        got = suffix_array(t, limit=limit, block=block)
        assert list(got[0]) == sa and list(got[1]) == lcp


def brute_bytes(rows, size):
    first = {}
    for doc, text in rows:
        b = (text or "").encode()
        for i in range(len(b) - size + 1):
            g = b[i : i + size]
            first[g] = min(first.get(g, 1 << 62), doc)
    out = {}
    for doc, text in rows:
        b = (text or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - size + 1):
            if first[b[i : i + size]] < doc:
                gone[i : i + size] = b"\x01" * size
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out[doc] = (len(b), sum(gone), len(re.findall(b"\x01+", bytes(gone))), hashlib.sha256(kept).hexdigest())
    return out


def brute_words(rows, size):
    seen, out = set(), {}
    for doc, text in sorted(rows):
        w = WORD.findall(text or "")
        gone = [False] * len(w)
        for i in range(len(w) - size + 1):
            g = tuple(w[i : i + size])
            if g in seen:
                gone[i : i + size] = [True] * size
            seen.add(g)
        out[doc] = (len(w), sum(gone), hashlib.sha256(" ".join(x for x, g in zip(w, gone) if not g).encode()).hexdigest())
    return out


@pytest.mark.parametrize("chunk_bytes", [700, 1 << 20])
def test_against_brute_force(spark, tmp_path, chunk_bytes):
    rows = corpus(4)
    spark.createDataFrame([(d, t, "clash", 1) for d, t in rows], "doc_id long, text string, chunk string, bucket int").write.parquet(str(tmp_path / "d"))
    docs = spark.read.parquet(str(tmp_path / "d"))
    got = {r[0]: tuple(r)[1:5] for r in suffix_dedup.without_repeats(docs, 50, Plan(docs, chunk_bytes)).collect()}
    assert got == brute_bytes(rows, 50)
    got = {r[0]: tuple(r)[1:4] for r in block_dedup.without_repeats(docs, 20, Plan(docs, chunk_bytes)).collect()}
    assert got == brute_words([(d, t or "") for d, t in rows], 20)


def test_empty_and_null_tables(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert suffix_dedup.without_repeats(docs).count() == 0 and block_dedup.without_repeats(docs).count() == 0
    docs = spark.createDataFrame([(None, "a b " * 30), (None, "a b " * 30), (1, None)], "doc_id long, text string")
    assert suffix_dedup.without_repeats(docs).count() == 3 and sorted(r.n_removed for r in block_dedup.without_repeats(docs).collect()) == [0, 58, 60]


@pytest.mark.parametrize("crowd", [1, 2, 1000])
def test_common_line_among_other_texts(spark, crowd):
    """One line in many documents gives its anchor ever other snippets; split or not, the answer is that of brute force."""
    r = random.Random(crowd)
    line = "this line of fifty and some more bytes stands in all texts"
    words = lambda: " ".join(str(r.randint(0, 10**6)) for _ in range(12))
    rows = [(i, f"{words()} {line} {words()}") for i in range(60)] + [(60, line), (61, line[:50]), (62, "x" + line[3:] + "y")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    plan = Plan(docs, chunk_bytes=1200, bytes_per_key=9)
    assert plan.chunks > 2
    want = brute_bytes(rows, 50)
    got = {x.doc_id: (x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in suffix_dedup.without_repeats(docs, 50, plan, crowd).collect()}
    assert got == want


def test_only_an_anchor_that_fills_a_shard_is_split():
    """Anchors 1 and 2 are in all chunks, with nine snippets in each and with a thousand."""
    own = np.array([1, 2], np.uint64)
    body = Writer().numbers(own, True).bits(np.array([False, True])).numbers(np.array([9, 1000])).done()
    for most, split in ((0, [True, True]), (16384, [False, True]), (1 << 20, [False, False])):
        for b in suffix_dedup.merged_crowds([Reader(body) for _ in range(70)], 64, most):
            r = Reader(b)
            assert r.bits().all() and list(r.bits()) == split


def test_anchors_of_short_and_long_strings():
    """Equal strings have equal anchors, also where strings are shorter than an anchor."""
    data = np.frombuffer(b"a common passage of some sixty bytes that stands in two texts, " * 2, np.uint8)
    for size in (16, 20, 50):
        first, count, gram = suffix_dedup.anchors(data, np.array([0, len(data)]), size)
        of = np.repeat(gram, count)
        assert len(of) == len(data) - size + 1 and (of[: len(of) - 63] == of[63:]).all()
