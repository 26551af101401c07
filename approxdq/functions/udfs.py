"""What users call from SQL: hashing, a sample as an aggregate, table functions for N-Triples and walks."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..deploy import ship
from .murmur import murmur3

SAMPLE = 16


@F.pandas_udf(T.ArrayType(T.StringType()))
def reservoir_agg(values: pd.Series) -> list:
    """The SAMPLE values of least digest in a group: a uniform sample of its distinct values. For groups of
    bounded size; ``reservoir.bottom_k_by`` takes any."""
    import hashlib

    own = {str(v) for v in values.dropna()}
    return sorted(own, key=lambda v: (hashlib.md5(f"0|{v}".encode()).hexdigest(), v))[:SAMPLE]


_TRIPLE = re.compile(r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"\S*)\s*\.\s*$')


class _ParseLine:
    def eval(self, line: str):
        if line and (m := _TRIPLE.match(line)):
            yield m[1], m[2], m[3] if m[3] is not None else m[4], "uri" if m[3] is not None else "literal"


class _WalkSteps:
    """Steps of a walk over a small graph given as a table of links (src, dst), read both ways; from its least vertex."""

    def __init__(self):
        self.near: dict[str, set[str]] = {}
        self.steps = self.seed = 0

    def eval(self, row, steps: int, seed: int):
        self.steps, self.seed = steps, seed
        for a, b in ((row["src"], row["dst"]), (row["dst"], row["src"])):
            self.near.setdefault(a, set()).add(b)

    def terminate(self):
        import hashlib

        lists = {v: sorted(own) for v, own in self.near.items()}
        at = min(lists) if lists else None
        for t in range(1, self.steps + 1 if lists else 1):
            yield t, at
            at = lists[at][int(hashlib.md5(f"{self.seed}|0|{t}".encode()).hexdigest()[:8], 16) % len(lists[at])]


def register(spark: SparkSession) -> None:
    """murmur3_128, reservoir_agg, ntriples_parse and walk_steps for SQL."""
    ship(spark)
    spark.udf.register("murmur3_128", murmur3)
    spark.udf.register("reservoir_agg", reservoir_agg)
    spark.udtf.register("ntriples_parse", F.udtf(_ParseLine, returnType="s string, p string, o string, o_kind string"))
    spark.udtf.register("walk_steps", F.udtf(_WalkSteps, returnType="step int, v string"))
