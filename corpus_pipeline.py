"""The training-data pipeline over ``documents``: five stages, each one of the operators of approxdq.llm.

Each stage takes what the stage before wrote, works on all of it, and its decisions take effect: rows that are
rejected go, passages that repeat or leak are cut out of the text. All stages but the last keep the columns of
documents; the last returns one row per document with its token ids.

Rows with a null text go at the first stage (their language is ``und``); an empty table stays empty; extra columns
are carried along; a document whose text becomes empty stays, with an empty text.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from approxdq.checkpoints import checkpoint_folder
from approxdq.llm import block_dedup, bpe, decontaminate, langid, order_minhash
from approxdq.llm.common import read


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language go."""
    return langid.accepted(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of copies and near copies stays, that of the smallest doc_id."""
    return order_minhash.one_of_each(docs)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 20 words and more that came before are cut out."""
    return block_dedup.deduplicated(docs)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of benchmark items are cut out."""
    return decontaminate.clean_documents(docs, read(spark, sf_dir, "benchmark"), remove="spans")


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, with digests of the ids and of what they decode to."""
    return bpe.encode_documents(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, ids=True)


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("passages", passages), ("benchmark", benchmark), ("tokens", tokens)]

#: A trained network decides in the first stage, which SQL can't express; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; what each but the last keeps is written to the checkpoint folder and read again."""
    docs = read(spark, sf_dir, "documents")
    folder = f"{checkpoint_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
