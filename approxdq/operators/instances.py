"""Instances: the set of (predicate, object) pairs of a subject, and its signature."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def canonical(*parts: Column) -> Column:
    """Text of several terms from which they can be told apart again: each with its length."""
    return F.concat(*[F.concat(F.char_length(p).cast("string"), F.lit(":"), p) for p in parts])


def from_any(triples: DataFrame) -> DataFrame:
    """s, sig, n_pairs of each subject, whatever the order of triples: one shuffle by subject."""
    pairs = triples.select("s", canonical(F.col("p"), F.col("o")).alias("c")).distinct()
    return pairs.groupBy("s").agg(F.md5(F.array_join(F.array_sort(F.collect_list("c")), "")).alias("sig"), F.count(F.lit(1)).cast("int").alias("n_pairs"))


def from_sorted(triples: DataFrame, seq: str = "seq") -> DataFrame:
    """The same from triples sorted by subject: a change of subject closes an instance. Ranges of subjects stay
    together, so each task closes its own; a subject in two runs gives two instances, as in one pass."""
    ranged = triples.repartitionByRange("s").sortWithinPartitions("s", seq)
    before = F.lag("s").over(Window.partitionBy(F.spark_partition_id()).orderBy("s", seq))
    runs = ranged.withColumn("opens", (before.isNull() | (before != F.col("s"))).cast("long"))
    numbered = runs.withColumn("run", F.sum("opens").over(Window.partitionBy(F.spark_partition_id()).orderBy("s", seq)))
    grouped = numbered.groupBy("s", "run").agg(F.collect_set(canonical(F.col("p"), F.col("o"))).alias("cs"))
    return grouped.select("s", F.md5(F.array_join(F.array_sort("cs"), "")).alias("sig"), F.size("cs").alias("n_pairs"))


def from_columns(df: DataFrame, seq: str, columns: list[str]) -> DataFrame:
    """seq, sig where a row is an instance and these columns are its objects: narrow."""
    each = [canonical(F.lit(c), F.coalesce(F.expr(c).cast("string"), F.lit(""))) for c in columns]
    return df.select(F.expr(seq).cast("long").alias("seq"), F.md5(F.concat(*each)).alias("sig"))


def from_columns_sql(frm: str, seq: str, columns: list[str]) -> str:
    each = " || ".join(f"'{len(c)}:' || {_quoted(c)} || length(coalesce(({c})::VARCHAR, ''))::VARCHAR || ':' || coalesce(({c})::VARCHAR, '')" for c in columns)
    return f"SELECT ({seq})::BIGINT AS seq, md5({each}) AS sig FROM {frm}"


def _quoted(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"
