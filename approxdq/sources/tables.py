"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..deploy import ship

FORMATS = ("parquet", "orc", "json", "csv")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, form: str, schema) -> DataFrame:
    """A file set with a given schema; nothing is inferred."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def write(df: DataFrame, path: str, form: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    writer = df.write.mode(mode).format(form)
    if form == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def run(df: DataFrame) -> None:
    """Does all the work and keeps nothing, for timing."""
    df.write.format("noop").mode("overwrite").save()
