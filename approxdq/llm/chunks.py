"""Two-way exchange between chunks of documents and hash ranges, in packed form.

Documents are dealt to chunks by a hash of doc_id (many chunks, so a hot source or a long text stays
one of many). A chunk reports its *distinct* hashes, sorted and delta-packed, one row for each hash
range; a range merges what the chunks report and answers each chunk with a bit for each hash. So a
passage that stands in a third of all documents is one entry of each chunk, never a group of rows.
Everything goes through Spark's shuffle: a lost executor costs a recomputation, no state.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

MESSAGE = "bucket int, chunk int, body binary"
_MESSAGE = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("body", pa.binary())])
#: Place of a null doc_id in the order of documents: after all others.
LAST = (1 << 63) - 1
#: Text of a chunk, and how many times its size in Parquet a table's text is taken to have.
CHUNK_BYTES, SWELL, KEYS = 6 << 20, 2, 32


class Plan:
    """Chunks, hash ranges and hash bits for a table of this size (from the optimizer's statistics). A chunk grows with the
    square root of the table (from 6 MB to about 140 MB at 100 TB), so that a message holds about ``KEYS`` hashes at least and the number of
    messages, chunks times ranges, grows with the table and not with its square."""

    def __init__(self, docs: DataFrame, chunk_bytes: int = CHUNK_BYTES, bytes_per_key: int = 6):
        size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) * SWELL
        size = min(size, 1 << 60)
        partitions = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        chunk_bytes = max(chunk_bytes, math.isqrt(KEYS * bytes_per_key * size // 2)) if chunk_bytes >= CHUNK_BYTES else chunk_bytes
        self.chunk_bytes = chunk_bytes
        self.chunks = max(1, min(1 << 30, -(-size // chunk_bytes)))
        self.buckets = max(1, min(1 << 30, max(partitions if size > 1 << 20 else 1, self.chunks // 2)))
        self.bits = min(60, max(40, math.ceil(math.log2(size / bytes_per_key + 2)) + 14))

    def deal(self, docs: DataFrame, carry: bool = False) -> DataFrame:
        """doc_id, text, chunk; ``carry``: also the other columns as one struct ``rest``, and ``tie``, a digest of the row.
        Rows without doc_id are dealt by their text."""
        C.ship(docs.sparkSession)
        doc, text = F.col("doc_id").cast("long"), F.col("text").cast("string")
        chunk = F.pmod(F.xxhash64(F.coalesce(doc, F.xxhash64(text))), F.lit(self.chunks)).cast("int")
        more = [F.struct(*[docs[c] for c in docs.columns if c != "text"]).alias("rest"), C.row_key(docs)[0].alias("tie")] if carry else []
        return docs.select(doc.alias("doc_id"), text.alias("text"), chunk.alias("chunk"), *more)

    def bucket(self, hashes: np.ndarray, bits: int) -> np.ndarray:
        """Range of each hash; rises with the hash."""
        top = hashes >> np.uint64(bits - 32) if bits >= 32 else hashes << np.uint64(32 - bits)
        return ((top * np.uint64(self.buckets)) >> np.uint64(32)).astype(np.int64)

    def by_bucket(self, hashes: np.ndarray, bits: int) -> Iterator[tuple[int, int, int]]:
        """(range, from, to) of sorted hashes."""
        own = self.bucket(hashes, bits)
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(own)) + 1, [len(own)]]) if len(own) else [0]
        for a, b in zip(cuts, cuts[1:], strict=False):
            yield int(own[a]), int(a), int(b)


def ordered(table: pa.Table) -> pa.Table:
    """A chunk's documents in their order: doc_id (nulls last), then text, then the digest of the row."""
    table = table.combine_chunks()
    repeated = pc.count_distinct(table["doc_id"], "all").as_py() < len(table)
    return table.take(pc.sort_indices(table, [("doc_id", "ascending")] + ([("text", "ascending")] + [("tie", "ascending")] * ("tie" in table.column_names) if repeated else []), null_placement="at_end"))


def doc_order(table: pa.Table) -> np.ndarray:
    return table["doc_id"].fill_null(LAST).to_numpy() if len(table) else np.zeros(0, np.int64)


def parts(table: pa.Table, most: int = C.PIECE) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets) of pieces of a chunk."""
    at = 0
    for batch in table.select(["text"]).to_batches():
        for piece in C.pieces(batch, most=most):
            data, offsets = C.flat(piece.column(0))
            yield at, data, offsets
            at += piece.num_rows


# -- packed arrays ------------------------------------------------------------------------------------------


class Writer:
    def __init__(self):
        self.body = bytearray()

    def raw(self, x: np.ndarray) -> Writer:
        self.body += np.int64(x.nbytes).tobytes() + x.tobytes()
        return self

    def numbers(self, x: np.ndarray, sorted_: bool = False) -> Writer:
        """Unsigned numbers as planes of bytes, as many as the largest needs; sorted ones as differences."""
        x = np.ascontiguousarray(x).astype(np.uint64)
        first = x[0] if len(x) else np.uint64(0)
        x = np.diff(x, prepend=first) if sorted_ else x
        width = max(1, (int(x.max()).bit_length() + 7) // 8) if len(x) else 1
        self.body += np.array([len(x), width, first if sorted_ else 0], np.uint64).tobytes()
        self.body += x.view(np.uint8).reshape(-1, 8)[:, :width].T.tobytes()
        return self

    def bits(self, x: np.ndarray) -> Writer:
        self.body += np.int64(len(x)).tobytes() + np.packbits(x).tobytes()
        return self

    def done(self) -> bytes:
        return bytes(self.body)


class Reader:
    def __init__(self, body: bytes):
        self.body, self.at = body, 0

    def _take(self, n: int) -> bytes:
        self.at += n
        return self.body[self.at - n : self.at]

    def raw(self, kind) -> np.ndarray:
        return np.frombuffer(self._take(int(np.frombuffer(self._take(8), np.int64)[0])), kind)

    def numbers(self, sorted_: bool = False) -> np.ndarray:
        n, width, first = map(int, np.frombuffer(self._take(24), np.uint64))
        out = np.zeros((n, 8), np.uint8)
        out[:, :width] = np.frombuffer(self._take(n * width), np.uint8).reshape(width, n).T
        out = out.view(np.uint64).ravel()
        return np.cumsum(out, dtype=np.uint64) + np.uint64(first) if sorted_ else out

    def bits(self) -> np.ndarray:
        n = int(np.frombuffer(self._take(8), np.int64)[0])
        return np.unpackbits(np.frombuffer(self._take((n + 7) // 8), np.uint8), count=n).astype(bool)


def released(work):
    """A function of groups that gives its memory back when it is done with one."""

    def one(key, table):
        out = work(key, table)
        C.release()
        return out

    def two(key, left, right):
        out = work(key, left, right)
        C.release()
        return out

    return one if work.__code__.co_argcount == 2 else two


def messages(rows: list[tuple[int, int, bytes]]) -> pa.Table:
    return pa.Table.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.binary())], schema=_MESSAGE)


def received(table: pa.Table) -> list[tuple[int, int, bytes]]:
    return sorted(zip(table["bucket"].to_pylist(), table["chunk"].to_pylist(), table["body"].to_pylist(), strict=True))


def merge(sent: DataFrame, answer) -> DataFrame:
    """``answer(bodies) -> bodies`` in each range; what a chunk sends to itself (range -1) comes back unchanged."""

    def run(key, table):
        rows = received(table)
        if rows[0][0] < 0:
            return messages(rows)
        return messages([(b, c, body) for (b, c, _), body in zip(rows, answer([Reader(r[2]) for r in rows]), strict=True)])

    lane = F.when(F.col("bucket") < 0, -1 - F.col("chunk")).otherwise(F.col("bucket"))
    return sent.withColumn("lane", lane).groupBy("lane").applyInArrow(released(lambda key, table: run(key, table.drop_columns(["lane"]))), MESSAGE)


def merged_hot(readers: list[Reader]) -> list[bytes]:
    """Each body: sorted hashes, flags ``many`` (found at two places there) and ``anchor``. A hash is hot if it is an
    anchor somewhere and stands at two places at least; the answer has a bit for each hash of the chunk."""
    own = [(r.numbers(True), r.bits(), r.bits()) for r in readers]
    keys = np.concatenate([o[0] for o in own])
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    starts = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    sizes = np.diff(np.append(starts, len(keys)))
    if not len(keys):
        return [Writer().bits(np.zeros(0, bool)).done() for _ in own]
    many = np.logical_or.reduceat(np.concatenate([o[1] for o in own])[order], starts) | (sizes > 1)
    anchor = np.logical_or.reduceat(np.concatenate([o[2] for o in own])[order], starts)
    hot = np.zeros(len(keys), bool)
    hot[order] = np.repeat(many & anchor, sizes)
    cuts = np.cumsum([0] + [len(o[0]) for o in own])
    return [Writer().bits(hot[a:b]).done() for a, b in zip(cuts, cuts[1:], strict=False)]
