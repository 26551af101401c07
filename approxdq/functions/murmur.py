"""128-bit Murmur3 of strings, over whole Arrow batches (published algorithm, x64 form)."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql import types as T

# Fixed values of the published hash.
C1, C2 = np.uint64(0x87C37B91114253D5), np.uint64(0x4CF5AD432745937F)
F1, F2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)
N1, N2 = np.uint64(0x52DCE729), np.uint64(0x38495AB5)


def _turn(x, n):
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _finish(x):
    x = (x ^ (x >> np.uint64(33))) * F1
    x = (x ^ (x >> np.uint64(33))) * F2
    return x ^ (x >> np.uint64(33))


def murmur3_128(values: list[bytes], seed: int = 0) -> np.ndarray:
    """(n, 2) unsigned halves. All values advance together, 16 bytes a round, those that are done stand still."""
    n = len(values)
    lengths = np.array([len(v) for v in values], np.int64)
    width = (int(lengths.max()) // 16 + 1) * 16 if n else 16
    block = np.zeros((n, width), np.uint8)
    flat = np.frombuffer(b"".join(values), np.uint8)
    block[np.repeat(np.arange(n), lengths), np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)] = flat
    return _rounds(block.view("<u8"), lengths, seed)


def murmur3_strings(values: pa.Array, seed: int = 0) -> np.ndarray:
    """The same of an Arrow array of strings without nulls; rows of one length that follow each other are hashed as they stand."""
    n = len(values)
    values = values.cast(pa.string())
    ends = np.frombuffer(values.buffers()[1], np.int32)[values.offset : values.offset + n + 1].astype(np.int64) if n else np.zeros(1, np.int64)
    lengths = np.diff(ends)
    cuts = np.flatnonzero(lengths[1:] != lengths[:-1]) + 1
    if len(cuts) * 64 > n:
        return murmur3_128([v.encode() for v in values.to_pylist()], seed)
    flat = np.frombuffer(values.buffers()[2], np.uint8) if n and values.buffers()[2] else np.zeros(0, np.uint8)
    out = np.zeros((n, 2), np.uint64)
    for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), n], strict=True) if n else ():
        size = int(lengths[lo])
        block = np.zeros((hi - lo, (size // 16 + 1) * 16), np.uint8)
        block[:, :size] = flat[ends[lo] : ends[hi]].reshape(hi - lo, size)
        out[lo:hi] = _rounds(block.view("<u8"), lengths[lo:hi], seed)
    return out


def _rounds(words: np.ndarray, lengths: np.ndarray, seed: int) -> np.ndarray:
    n, width = len(words), words.shape[1] * 8
    a = np.full(n, seed, np.uint64)
    b = a.copy()
    with np.errstate(over="ignore"):
        for r in range(width // 16):
            x, y = words[:, 2 * r], words[:, 2 * r + 1]
            tail = lengths // 16 == r
            mx, my = _turn(x * C1, 31) * C2, _turn(y * C2, 33) * C1
            full = lengths // 16 > r
            na = (_turn(a ^ mx, 27) + b) * np.uint64(5) + N1
            nb = (_turn(b ^ my, 31) + na) * np.uint64(5) + N2
            a, b = np.where(full, na, np.where(tail, a ^ mx, a)), np.where(full, nb, np.where(tail, b ^ my, b))
        size = lengths.astype(np.uint64)
        a, b = a ^ size, b ^ size
        a = a + b
        b = b + a
        a, b = _finish(a), _finish(b)
        a = a + b
        b = b + a
    return np.stack([a, b], 1)


@F.pandas_udf(T.StructType([T.StructField("h1", T.LongType()), T.StructField("h2", T.LongType())]))
def murmur3(values: pd.Series) -> pd.DataFrame:
    """Both halves as signed longs; null as the empty string."""
    h = murmur3_128([(v or "").encode() for v in values]).view(np.int64)
    return pd.DataFrame({"h1": h[:, 0], "h2": h[:, 1]})
