"""Rows without doc_id, rows that share one, and columns whose names operators use themselves."""

from collections import Counter

import pytest

import corpus_pipeline
from approxdq.llm import block_dedup, langid, order_minhash

BASE = "the quick brown fox jumps over the lazy dog while seven small birds sing in the old green garden by the long river bank every single day"
OTHER = "completely different words stand in this second text about ships and storms on a cold northern sea where nobody had sailed before that winter"


@pytest.fixture(scope="module")
def docs(spark):
    texts = [(1, BASE), (1, OTHER), (2, BASE + " more"), (3, OTHER + " too"), (None, BASE), (None, OTHER + " again"), (None, None), (4, ""), (4, None), (5, BASE), (5, BASE)]
    rows = [(d, t, "en", "s", len(t or ""), i, "n", {"a": i}, 7, i) for i, (d, t) in enumerate(texts)]
    rows[-1] = rows[-2]  # equal in every column
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, _id int, _new string, chunk map<string,int>, r1 int, copy int")


def test_each_stage_returns_a_part_of_its_rows(spark, docs, sf_dir):
    given = Counter(r["_id"] for r in docs.collect())
    for name, f in corpus_pipeline.STAGES[:-1]:
        out = f(spark, docs, sf_dir)
        rows = out.collect()
        assert out.columns == docs.columns and Counter(r["_id"] for r in rows) <= given, name
        if name in ("passages", "benchmark"):
            assert Counter(r["_id"] for r in rows) == given


def test_one_row_of_each_group_stays(docs):
    kept = {r["_id"]: r for r in order_minhash.one_of_each(docs).collect()}
    assert set(kept) == {0, 1, 6, 7, 8} and kept[0].text == BASE and kept[1].text == OTHER
    classes = {(r.doc_id, r.class_id) for r in order_minhash.near_duplicates(docs).collect()}
    assert {(2, 1), (3, 1), (5, 1), (None, 1)} <= classes


def test_a_class_without_any_doc_id(spark):
    docs = spark.createDataFrame([(None, BASE, 1), (None, BASE + " more", 2), (None, OTHER, 3)], "doc_id long, text string, key int")
    kept = order_minhash.one_of_each(docs).collect()
    assert len(kept) == 2 and sorted(r.key for r in kept)[-1] == 3


def test_texts_of_one_doc_id_are_not_crossed(docs):
    out = {r["_id"]: r for r in block_dedup.deduplicated(docs).collect()}
    assert out[1].text.startswith("completely") and out[0].text.startswith("the quick")
    assert out[2].text == "more" and out[3].text == "too" and out[5].text == "again" and out[6].text is None and out[8].text is None
    assert all(r.n_chars is None if r.text is None else r.n_chars == len(r.text) for r in out.values())


def test_each_text_is_judged_by_itself(docs):
    kept = Counter(r["_id"] for r in langid.accepted(docs, per_lang=5, steps=2, least=0.0).collect())
    assert set(kept) == {0, 1, 2, 3, 4, 5, 9} and kept[9] == 2


def test_sample_is_that_of_the_least_hashes_in_each_language(spark):
    rows = [(i, f"text {i}", "en" if i % 10 else "fr") for i in range(3000)] + [(i, f"text {i}", "de") for i in range(3000, 3004)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    seen = {}
    real = langid.ByteGRU.train
    langid.ByteGRU.train = lambda self, texts, labels, **kw: seen.update(texts=texts, labels=labels, langs=self.langs) or self
    try:
        langid.fit(docs, per_lang=50)
    finally:
        langid.ByteGRU.train = real
    from pyspark.sql import functions as F

    able = docs.where(~langid.held_out()).withColumn("key", F.xxhash64(F.col("doc_id").cast("string")))
    want = {k: sorted((r.key, r.text) for r in able.where(F.col("lang") == k).collect())[:50] for k in ("de", "en", "fr")}
    got = Counter((seen["langs"][y], t.decode()) for t, y in zip(seen["texts"], seen["labels"], strict=True))
    assert got == Counter((k, t) for k, own in want.items() for _, t in own)
