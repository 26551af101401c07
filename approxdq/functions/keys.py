"""Random keys that are functions of the row, so that a retried task and another engine give the same sample."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def random_key(seed: int | str, *columns: Column | str) -> Column:
    """Uniform text key of a row: MD5 over the seed and the columns."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in columns]))


def number(key: Column) -> Column:
    """The first 32 bits of a hexadecimal digest."""
    return F.conv(F.substring(key, 1, 8), 16, 10).cast("long")


def fraction(key: Column) -> Column:
    return number(key) / F.lit(float(1 << 32))


def fast_key(seed: int, *columns: Column | str) -> Column:
    """64-bit key for runs that need no twin in another engine."""
    return F.xxhash64(F.lit(seed), *columns)


def positions(signature: Column, k: int, size: int, seed: int = 0) -> Column:
    """Array of k bit positions below ``size``, one for each filter."""
    return F.array(*[F.pmod(number(F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(i)), signature))), F.lit(size)) for i in range(k)])
