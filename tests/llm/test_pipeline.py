"""The pipeline's stages against brute force on a fixture, and its run over the small tables."""

import hashlib

import pytest
import tiktoken

import corpus_pipeline
from approxdq.llm import bpe


def stage(name):
    return dict(corpus_pipeline.STAGES)[name]


@pytest.fixture(scope="module")
def docs(spark):
    base = "the quick brown fox jumps over the lazy dog while seven small birds sing in the old green garden by the long river bank every single day"
    rows = [(1, base, "en", "s", len(base)), (2, base, "en", "s", len(base)), (3, base.replace("seven", "eight"), "en", "s", len(base)), (4, "Ein ganz anderer Text " + base + " mit eigenem Ende und noch viel mehr Worten damit er kein Duplikat ist und bleibt sowie weitere zwanzig Worte die sonst nirgends stehen in diesem kleinen Bestand von Texten", "de", "s", 1), (5, "1234 !!", "en", "s", 7), (6, None, "en", "s", 0), (7, "", "en", "s", 0)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")


def test_stage_order_and_names():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "passages", "benchmark", "tokens"] and corpus_pipeline.ORACLE_SQL is None


def test_language_rejects_what_has_no_letters(spark, docs, sf_dir):
    assert {r.doc_id for r in stage("language")(spark, docs, sf_dir).collect()} == {1, 2, 3, 4}


def test_one_of_each_group_stays(spark, docs, sf_dir):
    assert {r.doc_id for r in stage("near_duplicates")(spark, docs.where("doc_id < 5"), sf_dir).collect()} == {1, 4}


def test_repeated_passage_is_cut(spark, docs, sf_dir):
    got = {r.doc_id: r for r in stage("passages")(spark, docs.where("doc_id in (1, 4)"), sf_dir).collect()}
    assert got[1].text.startswith("the quick") and got[4].text.startswith("Ein ganz anderer Text mit eigenem") and got[4].n_chars == len(got[4].text)


def test_run_over_the_small_tables(spark, sf_dir):
    import public_tokenizers as p

    rows = corpus_pipeline.run(spark, sf_dir).collect()
    all_docs = {r.doc_id: r for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    assert 0 < len(rows) < len(all_docs) and len({r.doc_id for r in rows}) == len(rows)
    enc = bpe.encoder(p.path("byte_bpe_multi_50k.tiktoken"), p.PATTERN)
    ref = tiktoken.Encoding("own", pat_str=p.PATTERN, mergeable_ranks=enc.rank, special_tokens={})
    for r in rows:
        assert r.same_bytes and r.n_tokens == len(r.ids)
        text = enc.decode(r.ids).decode()
        assert ref.encode_ordinary(text) == list(r.ids) and hashlib.sha256(text.encode()).hexdigest() == r.decoded_sha256


def test_stages_take_empty_tables_and_extra_columns(spark, docs, sf_dir):
    from pyspark.sql import functions as F

    none = docs.where("false").withColumn("key", F.lit(1)).withColumn("chunk", F.lit("x"))
    for _, f in corpus_pipeline.STAGES:
        assert f(spark, none, sf_dir).count() == 0
    some = docs.where("doc_id < 5").withColumn("key", F.lit(1)).withColumn("copy", F.lit("x")).withColumn("runs", F.lit(2))
    for _, f in corpus_pipeline.STAGES[:-1]:
        assert f(spark, some, sf_dir).columns == some.columns
