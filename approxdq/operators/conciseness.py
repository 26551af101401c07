"""Extensional conciseness: instances that no other instance repeats, over all instances."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bloom

#: Two readings: ``first`` counts the first of each group of equal instances, ``strict`` only those that nobody shares.
MODES = ("first", "strict")


def _ratio(numer, denom) -> list:
    return [numer.cast("long").alias("numer"), denom.cast("long").alias("denom"), F.when(denom > 0, numer / denom).otherwise(1.0).alias("value")]


def exact(instances: DataFrame, mode: str = "first") -> DataFrame:
    """By signature: one shuffle, partial counts."""
    groups = instances.groupBy("sig").agg(F.count(F.lit(1)).alias("n"))
    kept = F.count(F.lit(1)) if mode == "first" else F.count_if(F.col("n") == 1)
    return groups.agg(*_ratio(kept, F.coalesce(F.sum("n"), F.lit(0))))


def pairwise(instances: DataFrame, block: int = 65_536) -> DataFrame:
    """The literal baseline, quadratic in the instances: each is compared with every other one. Instances are dealt to
    blocks, which are packed once, and each two blocks are compared in a task of their own, signature against signature;
    an instance repeats one of an earlier block, or one before it in its own."""
    n = instances.count()
    blocks = max(1, -(-n // block))
    dealt = instances.select("seq", "sig", F.pmod(F.xxhash64("seq", "sig"), F.lit(blocks)).cast("int").alias("block"))

    def pack(key, table):
        table = table.sort_by([("seq", "ascending")])
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "body": pa.array([bytes.fromhex("".join(table["sig"].to_pylist()))], pa.binary())})

    def compare(key, table):
        lo, hi = (k.as_py() for k in key)
        body = dict(zip(table["block"].to_pylist(), table["body"].to_pylist(), strict=True))
        x, y = (np.frombuffer(body[b], "<u4").reshape(-1, 4) for b in (lo, hi))
        return pa.table({"block": pa.array([hi], pa.int32()), "repeated": pa.array([np.packbits(repeats(y, x, lo == hi)).tobytes()], pa.binary())})

    def either(key, table):
        found = [np.frombuffer(b, np.uint8) for b in table["repeated"].to_pylist()]
        return pa.table({"d": pa.array([int(np.unpackbits(np.bitwise_or.reduce(found)).sum())], pa.int64())})

    packed = dealt.groupBy("block").applyInArrow(pack, "block int, body binary")
    both = packed.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    # a block that no instance was dealt to sends nothing, and is compared with nothing
    tasks = both.select("block", "body", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi")).repartition(max(1, blocks * (blocks + 1) // 2), "lo", "hi")
    found = tasks.groupBy("lo", "hi").applyInArrow(lambda key, table: compare(key, table) if len(table) == 1 + (key[0] != key[1]) else pa.table({"block": pa.array([], pa.int32()), "repeated": pa.array([], pa.binary())}), "block int, repeated binary")
    return found.groupBy("block").applyInArrow(either, "d long").agg(F.coalesce(F.sum("d"), F.lit(0)).alias("d")).select(*_ratio(F.lit(n) - F.col("d"), F.lit(n)))


def repeats(y: np.ndarray, x: np.ndarray, before: bool, stretch: int = 16_384) -> np.ndarray:
    """Which rows of y are in x (``before``: in x above their own place). Each is compared with all by its first word, and by
    the others where that is equal."""
    out = np.zeros(len(y), bool)
    first = np.ascontiguousarray(x[:, 0])
    for at in range(0, len(x), stretch):
        own = first[at : at + stretch]
        for i, word in enumerate(y[:, 0]):
            if not out[i]:
                equal = (own[: max(0, i - at)] if before else own) == word
                out[i] = equal.any() and (x[at + np.flatnonzero(equal)] == y[i]).all(1).any()
    return out


def of_flags(flags: DataFrame) -> DataFrame:
    return flags.agg(*_ratio(F.count_if(~F.col("is_dup")), F.count(F.lit(1))))


def estimate(instances: DataFrame, k: int | None = None, bits: int = 100_000, fpr: float | None = None, shards: int = 1, seed: int = 0, policy: str = "balanced", form: str = "murmur128") -> DataFrame:
    """By filters that reset; unflagged instances over all. A long single stream is read in ranges, with the same numbers."""
    if shards == 1:
        return estimates(instances, [(k or bloom.filters_for(fpr), bits)], seed, policy, form)[0]
    return of_flags(bloom.flag_balanced(instances, bits, fpr, k, seed, shards, policy, form))


def estimates(instances: DataFrame, settings: list[tuple[int, int]], seed: int = 0, policy: str = "balanced", form: str = "murmur128") -> list[DataFrame]:
    """``estimate`` of each (filters, bits): a long stream is dealt, sorted and hashed once for all."""
    return [instances.sparkSession.createDataFrame([found], "n long, m long").select(*_ratio(F.col("n"), F.col("m"))) if found else of_flags(bloom.flag_balanced(instances, bits, None, k, seed, 1, policy, form)) for (k, bits), found in zip(settings, bloom.count_settings(instances, settings, seed, policy, form), strict=True)]


def sampled(instances: DataFrame, theta: float, mode: str = "first", seed: int = 0) -> DataFrame:
    """By a sample of signatures: a kept signature keeps all its copies, so both readings stay unbiased."""
    from ..functions.keys import fraction, random_key

    return exact(instances.where(fraction(random_key(seed, "sig")) < theta), mode)


def sketch(instances: DataFrame, rsd: float = 0.02) -> DataFrame:
    """By an estimated number of distinct signatures."""
    return instances.agg(*_ratio(F.least(F.approx_count_distinct("sig", rsd), F.count(F.lit(1))), F.count(F.lit(1))))


def prefiltered(instances: DataFrame, k: int = 4, bits: int = 1 << 22) -> DataFrame:
    """Exact, but only candidates of the two-plane filter are grouped."""
    repeats = bloom.candidates(instances, k, bits).groupBy("sig").agg((F.count(F.lit(1)) - 1).alias("extra")).agg(F.coalesce(F.sum("extra"), F.lit(0)).alias("d"))
    return instances.agg(F.count(F.lit(1)).alias("n")).crossJoin(repeats).select(*_ratio(F.col("n") - F.col("d"), F.col("n")))
