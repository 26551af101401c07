"""Inverted multi-index against brute force: recall, ties, repeated and invalid rows, few rows, split cells."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from approxdq.llm import multi_index as mi

SCHEMA = "vec_id long, embedding array<float>, label int, id string, v int"


def frame(spark, rows):
    return spark.createDataFrame([(i, v, 0, "clash", 1) for i, v in rows], SCHEMA)


def brute(rows, query_ids, k):
    ok = {}
    for i, v in rows:
        if v is not None and all(x is not None and np.isfinite(x) for x in v) and any(v):
            ok[i] = np.array(v, np.float32).astype(float)
    out = {}
    for q in query_ids:
        if q in ok:
            own = sorted(((-float((ok[q] * x).sum()), i) for i, x in ok.items() if i != q))[:k]
            out[q] = [(i, -s) for s, i in own]
    return out


def test_heap_walks_cells_by_summed_distance():
    x = np.random.default_rng(0).normal(size=(200, 8))
    index = mi.MultiIndex(x, 6)
    sizes = np.bincount(index.cells(x), minlength=36)
    got = index.visit(x[3], sizes, 1e9)
    a, b = index.distances(x[3])
    d = (a[:, None] + b).ravel()
    assert sorted(got) == sorted(np.flatnonzero(sizes)) and all(d[p] <= d[q] + 1e-12 for p, q in zip(got, got[1:]))
    some = index.visit(x[3], sizes, 50)
    assert some == got[: len(some)] and sizes[some].sum() >= 50 > sizes[some[:-1]].sum()


def test_recall_order_and_scores(spark):
    r = np.random.default_rng(1)
    centres = r.normal(size=(12, 16))
    rows = [(i, (centres[i % 12] + 0.4 * r.normal(size=16)).astype(np.float32).tolist()) for i in range(900)]
    got = mi.search(frame(spark, rows), F.col("id") % 20 == 0, k=10, centroids=8).collect()
    want = brute(rows, range(0, 900, 20), 10)
    assert len(got) == 450
    hits = 0
    for q in want:
        own = sorted((x for x in got if x.query_id == q), key=lambda x: x.rank)
        assert [x.rank for x in own] == list(range(1, 11)) and all((-a.score, a.vec_id) < (-b.score, b.vec_id) for a, b in zip(own, own[1:]))
        true = dict(want[q])
        hits += sum(x.vec_id in true for x in own)
        assert all(abs(true[x.vec_id] - x.score) < 1e-12 for x in own if x.vec_id in true)
    assert hits / 450 >= 0.9


@pytest.mark.parametrize("unit", [4096, 8])
def test_repeated_invalid_and_hot_vectors(spark, monkeypatch, unit):
    monkeypatch.setattr(mi, "UNIT", unit)
    hot = [1.0, 2.0, 0.0, 1.0]
    rows = [(i, hot) for i in range(60)] + [(100, None), (101, [0.0] * 4), (102, [1.0, None, 0.0, 1.0]), (103, [float("nan"), 1.0, 1.0, 1.0]), (104, [float("inf"), 1.0, 1.0, 1.0]), (40, hot), (200, [0.5, 0.5, 0.5, 0.5])]
    got = mi.search(frame(spark, rows), F.col("id") % 20 == 0, k=5, recall=1.0).collect()
    want = brute(rows, [0, 20, 40, 200], 5)
    assert {q: [x.vec_id for x in sorted((x for x in got if x.query_id == q), key=lambda x: x.rank)] for q in want} == {q: [i for i, _ in w] for q, w in want.items()}


def test_few_and_no_rows(spark):
    got = mi.search(frame(spark, [(0, [1.0, 0.0]), (1, [0.5, 1.0])]), F.col("id") % 20 == 0).collect()
    assert [(x.query_id, x.rank, x.vec_id, x.score) for x in got] == [(0, 1, 1, 0.5)]
    assert mi.search(frame(spark, []), F.col("id") % 20 == 0).count() == 0


def test_brute_force_twin(spark, sf_dir):
    table = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    got = {(r.query_id, r.vec_id) for r in mi.search(table, F.col("id") % 20 == 0).collect()}
    want = {(r.query_id, r.vec_id) for r in mi.exact_search(table, list(range(0, 500, 20))).collect()}
    assert len(got & want) / len(want) >= 0.9
