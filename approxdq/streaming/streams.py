"""Streams: samples and filters with state, windows with watermarks, joins, batch twins' sources."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.keys import random_key
from ..operators.bloom import ResettingFilter, draws


def file_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_stream(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def reservoir(stream: DataFrame, group: str, item: str, k: int, seed: int = 0) -> DataFrame:
    """grp, item, key, n_seen: the k items of least key of each group so far (update mode). State: k keys a group."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        kept, seen = (list(state.get[0]), state.get[1]) if state.exists else ([], 0)
        best = dict(x.split("|", 1) for x in kept)
        for f in frames:
            seen += len(f)
            best.update(zip(f["key"], f["item"], strict=True))
            best = dict(sorted(best.items())[:k])
        state.update(([f"{a}|{b}" for a, b in best.items()], seen))
        yield pd.DataFrame({"grp": key[0], "item": list(best.values()), "key": list(best), "n_seen": seen})

    keyed = stream.select(F.col(group).cast("string").alias("grp"), F.col(item).cast("string").alias("item")).dropna().withColumn("key", random_key(seed, "item"))
    return keyed.groupBy("grp").applyInPandasWithState(step, "grp string, item string, key string, n_seen long", "kept array<string>, seen long", "update", GroupStateTimeout.NoTimeout)


def flag_balanced(stream: DataFrame, sig: str, seq: str, bits: int, k: int, shards: int = 4, seed: int = 0, policy: str = "balanced") -> DataFrame:
    """seq, sig, is_dup as they arrive (append mode). State: the bit vectors of a shard."""
    own = bits // shards

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        made = ResettingFilter(k, own, policy, bytes(state.get[0]) if state.exists else None)
        rows = pd.concat(list(frames)).sort_values("seq")
        at, where, chance = draws(rows["sig"].tolist(), rows["seq"].tolist(), k, max(1, own // k), seed)
        out = [made.add(at[i], where[i], chance[i]) for i in range(len(rows))]
        state.update((made.state(),))
        yield pd.DataFrame({"seq": rows["seq"].to_numpy(), "sig": rows["sig"].to_numpy(), "is_dup": out})

    dealt = stream.select(F.col(seq).cast("long").alias("seq"), F.col(sig).cast("string").alias("sig")).withColumn("shard", F.pmod(F.xxhash64("sig"), F.lit(shards)).cast("int"))
    return dealt.groupBy("shard").applyInPandasWithState(step, "seq long, sig string, is_dup boolean", "state binary", "append", GroupStateTimeout.NoTimeout)


def drop_repeats(stream: DataFrame, sig: str, time: str, delay: str = "2 hours") -> DataFrame:
    """The exact baseline: a signature that came within the watermark is dropped."""
    return stream.withWatermark(time, delay).dropDuplicatesWithinWatermark([sig])


def tumbling(df: DataFrame, time: str = "ts", size: str = "1 hour", delay: str | None = None) -> DataFrame:
    """Count and sum of value in windows by event_type; batch or stream (then with a watermark, late rows go)."""
    own = df.withWatermark(time, delay) if delay else df
    return own.groupBy(F.window(time, size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(df: DataFrame, time: str = "ts", size: str = "2 hours", slide: str = "1 hour", delay: str | None = None) -> DataFrame:
    own = df.withWatermark(time, delay) if delay else df
    return own.groupBy(F.window(time, size, slide).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(df: DataFrame, user: str = "user_id", time: str = "ts", gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    own = df.withWatermark(time, delay) if delay else df
    return own.groupBy(F.session_window(time, gap).alias("w"), user).agg(F.count(F.lit(1)).alias("n")).select(user, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def late(df: DataFrame, every: int = 50, hours: int = 2) -> DataFrame:
    """A test set: one event in so many comes later in arrival order (column arrival)."""
    return df.withColumn("arrival", F.when(F.pmod("event_id", F.lit(every)) == 0, F.col("ts") + F.expr(f"INTERVAL {hours} HOURS")).otherwise(F.col("ts")))


def within(left: DataFrame, right: DataFrame, user: str, minutes: int) -> DataFrame:
    """Interval join of two streams (or tables): rows of a user at most so many minutes after. Inputs: user, ts, id."""
    a, b = left.toDF("user", "ts", "id").alias("a"), right.toDF("user2", "ts2", "id2").alias("b")
    near = (F.col("user") == F.col("user2")) & (F.col("ts2") > F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr(f"INTERVAL {minutes} MINUTES"))
    return a.join(b, near).select("id", "id2")


def start(df: DataFrame, sink: Callable[[DataFrame, int], None] | str, checkpoint: str, mode: str = "append", name: str | None = None):
    """A query that works off what is there: to ``foreachBatch``, or to a table in memory."""
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    return writer.format("memory").queryName(name or sink).start() if isinstance(sink, str) else writer.foreachBatch(sink).start()
