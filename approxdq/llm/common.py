"""What the text operators share: Arrow columns as flat bytes, word spans and hashes in NumPy.

A task never holds more than one Arrow batch; work inside a batch is cut into pieces of about
``PIECE`` bytes (at least one whole text), so scratch memory follows the longest text, not the table.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import deploy

PIECE = 1 << 20
#: Rows of an Arrow batch, where the session has Spark's default: a batch of 10,000 whole texts costs an executor hundreds of MB.
BATCH_KEY, BATCH_DEFAULT, BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", "10000", "1000"

#: Bytes of words: 0-9, a-z (after lower-casing) and every byte of a non-ASCII character.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
IS_WORD = np.zeros(256, dtype=bool)
IS_WORD[48:58] = IS_WORD[97:123] = IS_WORD[128:] = True
#: Bytes of words that white space separates: everything but space and tab to carriage return.
IS_DARK = np.ones(256, dtype=bool)
IS_DARK[[32, 9, 10, 11, 12, 13]] = False


def ship(spark: SparkSession) -> SparkSession:
    """The session with this package on its executors and batches of whole texts that fit them."""
    if spark.conf.get(BATCH_KEY, BATCH_DEFAULT) == BATCH_DEFAULT:
        spark.conf.set(BATCH_KEY, BATCH_ROWS)
    return deploy.ship(spark)


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{table}.parquet")


def documents(df: DataFrame) -> DataFrame:
    """The two columns that text operators use, whatever else the table holds."""
    ship(df.sparkSession)
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def row_key(df: DataFrame) -> list[Column]:
    """Two 64-bit digests of a whole row (all columns), which name it where doc_id is null or repeated."""
    kinds = {f.name: f.dataType.typeName() for f in df.schema}
    own = [F.to_json(F.struct(df[c])) if kinds[c] in ("map", "variant") else df[c] for c in df.columns]
    return [F.xxhash64(F.lit(seed), *own).alias(f"r{seed}") for seed in (1, 2)]


#: Row keys that are broadcast at most (16 bytes each); beyond it tables are joined by a shuffle.
MOST_KEYS = 1 << 20


def without(df: DataFrame, rows: DataFrame, how: str = "left_anti", most: int = MOST_KEYS) -> DataFrame:
    """df less the rows (r1, r2) named by ``row_key`` (``left_semi``: only those); its columns may have any names. Narrow up to
    ``most`` keys, a checked number."""
    keyed = df.select(F.struct(*[df[c] for c in df.columns]).alias("row"), *row_key(df))
    side = F.broadcast(rows) if rows.count() <= most else rows
    return keyed.join(side.select("r1", "r2"), ["r1", "r2"], how).select("row.*")


def flat(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all strings (null: empty) end to end, and where each begins (one more than strings)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    if column.null_count:
        column = column.fill_null(b"" if "binary" in str(column.type) else "")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, where, body = column.buffers()
    offsets = np.frombuffer(where, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(body, np.uint8)[offsets[0] : offsets[-1]] if body is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def pieces(batch: pa.RecordBatch, text: str = "text", most: int = PIECE) -> Iterator[pa.RecordBatch]:
    """Slices of a batch, each of about ``most`` bytes of text and one row at least."""
    if not batch.num_rows:
        return
    _, offsets = flat(batch.column(text))
    at = 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1)
        yield batch.slice(at, to - at)
        at = to


try:
    _TRIM = ctypes.CDLL(None).malloc_trim
except AttributeError:  # a C library without it
    _TRIM = None


def release() -> None:
    """Gives freed memory back to the system, so that a worker between tasks is small."""
    pa.default_memory_pool().release_unused()
    if _TRIM:
        _TRIM(0)


def map_pieces(df: DataFrame, work: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str, text: str = "text", done: Callable[[], None] | None = None) -> DataFrame:
    """``work`` over each piece of each Arrow batch, ``done`` when a task ends; narrow, so a lost executor only repeats
    its own splits."""

    def run(batches):
        try:
            for batch in batches:
                for piece in pieces(batch, text):
                    yield work(piece)
        finally:
            if done:
                done()
            release()

    return df.mapInArrow(run, schema)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64 bits (the splitmix one), so that every bit depends on every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def draws(n: int, seed: int) -> np.ndarray:
    """n fixed odd 64-bit multipliers."""
    with np.errstate(over="ignore"):
        return mix((np.arange(1, n + 1, dtype=np.uint64) + np.uint64(seed) * np.uint64(1 << 32)) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


_MULT = {s: draws(256, s) for s in (1, 2)}


def word_spans(data: np.ndarray, offsets: np.ndarray, is_word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of word bytes, and the row of each; runs end where a text ends."""
    n = len(data)
    inside = is_word[data]
    before = np.zeros(n, bool)
    before[1:] = inside[:-1]
    cuts = offsets[1:-1]
    before[cuts[cuts < n]] = False
    after = np.zeros(n, bool)
    after[:-1] = inside[1:]
    after[cuts[cuts > 0] - 1] = False
    starts = np.flatnonzero(inside & ~before)
    ends = np.flatnonzero(inside & ~after) + 1
    return starts, ends, np.searchsorted(offsets, starts, "right") - 1


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 1) -> np.ndarray:
    """A 64-bit multilinear hash of each (non-empty) span; spans may overlap. Works through about PIECE bytes at once."""
    lengths = ends - starts
    if not len(starts):
        return np.zeros(0, np.uint64)
    longest, table = int(lengths.max()), _MULT[seed]
    if longest > len(table):
        table = _MULT[seed] = draws(1 << int(longest).bit_length(), seed)
    total = np.cumsum(lengths)
    cuts = np.unique(np.append(np.searchsorted(total, np.arange(0, int(total[-1]), PIECE), "right"), len(starts)))
    out = np.empty(len(starts), np.uint64)
    for a, b in zip(np.append(0, cuts), cuts, strict=False):
        if b > a:
            own = lengths[a:b]
            first = np.cumsum(own) - own
            at = np.arange(int(own.sum())) - np.repeat(first, own)
            values = (data[at + np.repeat(starts[a:b], own)].astype(np.uint64) + np.uint64(1)) * table[at]
            out[a:b] = mix(np.add.reduceat(values, first) + own.astype(np.uint64))
    return out


def gram_hashes(words: np.ndarray, n: int, seed: int = 1) -> np.ndarray:
    """Hash of each run of n consecutive words (rows aren't looked at); words: hashes of words."""
    m = max(0, len(words) - n + 1)
    out = np.zeros(m, np.uint64)
    if m:
        for j, c in enumerate(draws(n, 7 + seed)):
            out += words[j : j + m] * c
    return mix(out)


def counts_of(rows: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(rows, minlength=n).astype(np.int64)
