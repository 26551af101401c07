"""Reservoir samples: the sequential forms as kernels, and mergeable bottom-k samples for Spark.

The k rows of least random key are a uniform k-subset, as a sequential reservoir gives, but partitions can
be sampled apart and merged: k rows of each partition cross the shuffle.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterable
from itertools import islice

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.keys import fast_key, random_key


def sequential(items: Iterable, k: int, seed: int = 0) -> list:
    """One pass; each item beyond the first k replaces a uniform place of those seen so far, if that is in the sample."""
    rng, kept = random.Random(seed), []
    for n, item in enumerate(items):
        if n < k:
            kept.append(item)
        elif (at := rng.randrange(n + 1)) < k:
            kept[at] = item
    return kept


def skipping(items: Iterable, k: int, seed: int = 0) -> list:
    """The same law with about k(1 + ln(n/k)) draws: how many items to pass over is drawn at once."""
    rng, it = random.Random(seed), iter(items)
    kept = list(islice(it, k))
    if len(kept) < k or not k:
        return kept
    w = math.exp(math.log(1 - rng.random()) / k)
    while True:
        skip = int(math.log(1 - rng.random()) / math.log1p(-w)) if w < 1 else 0
        for _ in range(skip):
            if next(it, kept) is kept:
                return kept
        item = next(it, kept)
        if item is kept:
            return kept
        kept[rng.randrange(k)] = item
        w *= math.exp(math.log(1 - rng.random()) / k)


def sequential_df(df: DataFrame, column: str, k: int, order: str, seed: int = 0, kernel=sequential) -> DataFrame:
    """The paper's baseline as it stands: one pass in order in one task. Use ``bottom_k`` for large inputs."""

    def run(batches):
        values = (v for b in batches for v in b.column(0).to_pylist() if v is not None)
        yield pa.RecordBatch.from_arrays([pa.array(kernel(values, k, seed), pa.string())], names=["item"])

    return df.select(F.col(column).cast("string").alias("v"), order).repartition(1).sortWithinPartitions(order).select("v").mapInArrow(run, "item string")


def _key(ids: list[str | Column], seed: int, form: str) -> Column:
    return random_key(seed, *ids) if form == "md5" else fast_key(seed, *ids)


def bottom_k(df: DataFrame, ids: list[str], k: int, seed: int = 0, form: str = "md5", unit: str = "occurrence") -> DataFrame:
    """k rows of least key (ties by the ids). unit ``distinct``: the ids' values are the items, whatever their number
    of occurrences; ``occurrence``: each row is an item, so ids must tell rows apart. Null items are dropped."""
    items = df.dropna(subset=ids)
    if unit == "distinct":
        items = items.select(*ids).distinct()
    return items.withColumn("key", _key(ids, seed, form)).orderBy("key", *ids).limit(k)


def bottom_k_by(df: DataFrame, group: str, ids: list[str], k: int, seed: int = 0, form: str = "md5") -> DataFrame:
    """k rows of each group: partial limits before the shuffle, so a hot group costs k rows of each partition."""
    place = F.row_number().over(Window.partitionBy(group).orderBy("key", *ids))
    return df.dropna(subset=[group, *ids]).withColumn("key", _key(ids, seed, form)).withColumn("place", place).where(F.col("place") <= k).drop("place")


def two_level(df: DataFrame, group: str, ids: list[str], groups: int, per_group: int, seed: int = 0, group_unit: str = "distinct") -> DataFrame:
    """A sample of groups, then of items in each; rows of other groups are dropped. ``distinct``: every group has the
    same chance; ``occurrence``: groups come in by their rows. The chosen groups (``groups`` rows) are broadcast."""
    if group_unit == "distinct":
        chosen = bottom_k(df, [group], groups, seed, unit="distinct").select(group)
    else:
        first = df.dropna(subset=[group]).groupBy(group).agg(F.min(_key([group, *ids], seed, "md5")).alias("key"))
        chosen = first.orderBy("key", group).limit(groups).select(group)
    return bottom_k_by(df.join(F.broadcast(chosen), group, "left_semi"), group, ids, per_group, seed)


def merge(a: DataFrame, b: DataFrame, ids: list[str], k: int) -> DataFrame:
    """The sample of a union from the samples of its parts (same seed)."""
    return a.unionByName(b).orderBy("key", *ids).limit(k)


def bernoulli(df: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    return df.sample(withReplacement=False, fraction=fraction, seed=seed)


def stratified(df: DataFrame, group: str, fractions: dict, seed: int = 0) -> DataFrame:
    return df.sampleBy(group, fractions, seed)


def capacity(expected: int, bytes_per_item: int, budget: int, eps: float = 0.02, delta: float = 0.05) -> int:
    """Places for a half-width ``eps`` with confidence 1 - delta, within memory and the expected number of items."""
    wanted = math.ceil(math.log(2 / delta) / (2 * eps * eps))
    return max(0, min(expected, budget // max(1, bytes_per_item), wanted))
