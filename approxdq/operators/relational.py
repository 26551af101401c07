"""Joins and frames around the metrics: as-of, range, interval, cubes, quality rules."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def as_of(left: DataFrame, right: DataFrame, by: str, time: str, value: str) -> DataFrame:
    """left with the value of the last right row of the same key at or before it: one union, one ordered window."""
    a = left.select(by, time, F.lit(1).alias("is_left"), F.lit(None).cast(right.schema[value].dataType).alias("v"), F.struct(*left.columns).alias("row"))
    b = right.select(by, time, F.lit(0).alias("is_left"), F.col(value).alias("v"), F.lit(None).cast(a.schema["row"].dataType).alias("row"))
    w = Window.partitionBy(by).orderBy(time, "is_left").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = a.unionByName(b).withColumn("last", F.last("v", ignorenulls=True).over(w)).where("is_left = 1")
    return out.select("row.*", F.col("last").alias(f"last_{value}"))


def bands(df: DataFrame, column: str, ranges: DataFrame) -> DataFrame:
    """Rows with the band (lo <= x < hi) they fall in; ranges are few and broadcast."""
    return df.join(F.broadcast(ranges), (F.col(column) >= F.col("lo")) & (F.col(column) < F.col("hi")))


def range_join(left: DataFrame, right: DataFrame, point: str, lo: str, hi: str, width: float) -> DataFrame:
    """Points within intervals of any number: both sides are dealt to bins of ``width``, then joined on the bin."""
    a = left.withColumn("_bin", F.floor(F.col(point) / width))
    b = right.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return a.join(b, "_bin").where((F.col(point) >= F.col(lo)) & (F.col(point) < F.col(hi))).drop("_bin")


def quality_rules(df: DataFrame, key: list[str], ranges: dict[str, tuple[float, float]]) -> DataFrame:
    """Rows, distinct keys, null cells and out-of-range cells in one pass."""
    nulls = [F.count_if(F.col(c).isNull()).alias(f"null_{c}") for c in df.columns]
    out = [F.count_if((F.col(c) < lo) | (F.col(c) > hi)).alias(f"out_{c}") for c, (lo, hi) in ranges.items()]
    return df.agg(F.count(F.lit(1)).alias("n_rows"), F.count_distinct(*key).alias("n_keys"), *nulls, *out)


def orphans(child: DataFrame, column: str, parent: DataFrame, key: str) -> DataFrame:
    return child.join(parent.select(F.col(key).alias("_k")).distinct(), F.col(column) == F.col("_k"), "left_anti").agg(F.count(F.lit(1)).alias("orphans"))
