"""Order MinHash: alignment against the full table, classes against brute force, large buckets, awkward rows."""

import random

import numpy as np
import pytest

from approxdq.llm import order_minhash as om


def table(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_banded_distance_is_exact_within_the_band():
    r = random.Random(5)
    for _ in range(400):
        a = [r.randint(0, 3) for _ in range(r.randint(0, 14))]
        b = [x for x in a if r.random() < 0.8] + [r.randint(0, 3) for _ in range(r.randint(0, 3))]
        d = table(a, b)
        for most in (0, 1, 3, 20):
            assert om.edit_distance(np.array(a, np.uint32), np.array(b, np.uint32), most) == (d if d <= most else None)


def brute_classes(rows, similarity):
    words = {d: tuple(w for w in "".join(c if c.isalnum() else " " for c in t.lower()).split()) for d, t in rows if t is not None}
    up = {d: d for d, _ in rows}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(words)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            n = max(len(words[a]), len(words[b]))
            if words[a] == words[b] and n or n and table(words[a], words[b]) <= (1 - similarity) * n + 1e-9:
                x, y = sorted((top(a), top(b)))
                up[y] = x
    return {d: top(d) for d, _ in rows}


def corpus():
    r = random.Random(1)
    vocab = [f"w{i}" for i in range(400)]
    rows, n = [], 0
    for _ in range(12):
        base = [r.choice(vocab) for _ in range(60)]
        for _ in range(r.randint(1, 5)):
            own = [w if r.random() > 0.03 else r.choice(vocab) for w in base]
            rows.append((n, " ".join(own).capitalize() + "."))
            n += 1
    rows += [(n, rows[0][1]), (n + 1, rows[0][1].upper()), (n + 2, None), (n + 3, ""), (n + 4, "one two"), (n + 5, "One, two!"), (n + 6, None)]
    return rows


@pytest.mark.parametrize("small", [64, 2])
def test_classes_against_brute_force(spark, monkeypatch, small):
    monkeypatch.setattr(om, "SMALL", small)
    rows = corpus()
    docs = spark.createDataFrame([(d, t, 1, "x") for d, t in rows], "doc_id long, text string, n int, copy string")
    got = {r.doc_id: r for r in om.near_duplicates(docs).collect()}
    assert {d: r.class_id for d, r in got.items()} == brute_classes(rows, 0.8)
    kept = {r.doc_id for r in om.one_of_each(docs).collect()}
    assert kept == {d for d, r in got.items() if r.class_id == d} and docs.columns == om.one_of_each(docs).columns


def test_common_passage_makes_large_buckets_but_no_class(spark, monkeypatch):
    monkeypatch.setattr(om, "SMALL", 4)
    r = random.Random(3)
    shared = [f"s{i}" for i in range(40)]
    rows = [(i, " ".join(shared + [f"w{r.randint(0, 10**6)}" for _ in range(40)])) for i in range(25)]
    got = om.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(x.class_id == x.doc_id for x in got)


def test_empty_table(spark):
    assert om.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_bound_of_blocks_loses_no_similar_pair():
    r = random.Random(9)
    texts = []
    for _ in range(30):
        base = [r.randint(0, 50) for _ in range(r.randint(1, 60))]
        texts += [base, [w if r.random() > 0.12 else r.randint(0, 50) for w in base], base[: int(len(base) * 0.85)]]
    words = np.array([w for t in texts for w in t], np.uint64)
    rows = np.repeat(np.arange(len(texts)), [len(t) for t in texts])
    counts, n, label = om.pair_counts(words, rows, len(texts)), np.array([len(t) for t in texts]), np.arange(len(texts))
    ok = om.possible(n, label, counts, n, label, counts, 0.8)
    for i, a in enumerate(texts):
        for j, b in enumerate(texts):
            if i != j and len(a) and len(b) and table(a, b) <= 0.2 * max(len(a), len(b)) + 1e-9:
                assert ok[i, j]
    assert not ok.diagonal().any()


def edited(r, n, edits):
    """A text of n words and a copy with so many scattered edits, each a new word, a word less or a word more."""
    a = [f"w{r.randint(0, 10**9)}" for _ in range(n)]
    b = list(a)
    for at in sorted(r.sample(range(n), edits), reverse=True):
        b[at : at + 1] = r.choice(([f"x{r.randint(0, 10**9)}"], [f"x{r.randint(0, 10**9)}"], [], [b[at], f"x{r.randint(0, 10**9)}"]))
    return a, b


def test_pairs_at_the_threshold_are_found(spark):
    r = random.Random(17)
    rows, same = [], 0
    for n in (5, 6, 9, 10, 14, 15, 20, 25, 35, 50, 60, 100, 200, 400):
        for _ in range(20):
            for a, b in (edited(r, n, int(0.2 * n + 1e-9)), edited(r, n, int(0.1 * n + 0.5) if n > 5 else 1)):
                if table(a, b) <= 0.2 * max(len(a), len(b)) + 1e-9:
                    rows += [(len(rows), " ".join(a)), (len(rows) + 1, " ".join(b))]
                    same += 1
    rows.append((len(rows), "a b c d e f g h i j"))
    rows.append((len(rows), "a b c d X f g h i j"))
    got = {x.doc_id: x.class_id for x in om.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    missed = [len(t.split()) for d, t in rows if d % 2 and got[d] != d - 1]
    assert same > 400 and not [n for n in missed if n <= 45] and len(missed) <= 1


def test_exact_keys_of_short_texts_lose_no_similar_pair():
    r = random.Random(23)
    for similarity in (0.7, 0.8, 0.9):
        texts = []
        for n in range(1, om.SHORT + 1):
            for _ in range(8):
                base = [r.randint(0, 60) for _ in range(n)]
                texts.append((base, [w for w in base for w in r.choices(([w], [99], [], [w, 98]), (8, 1, 0.5, 0.5))[0]] or [97]))
        flat = [t for p in texts for t in p]
        rows = np.repeat(np.arange(len(flat)), [len(t) for t in flat])
        own, keys = om.seeds(np.array([w for t in flat for w in t], np.uint64), rows, len(flat), similarity)
        of = [set(keys[own == i].tolist()) for i in range(len(flat))]
        near = [i for i, (a, b) in enumerate(texts) if a != b and max(len(a), len(b)) <= om.SHORT and table(a, b) <= int((1 - similarity) * max(len(a), len(b)) + 1e-9)]
        assert len(near) > 15 and all(of[2 * i] & of[2 * i + 1] for i in near)
