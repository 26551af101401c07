"""Benchmark decontamination: word windows of test items in a hash set, sent to every task.

Each item is cut into all its windows of ``n`` words (an item of fewer words is one window). Their
64-bit hashes go to the executors; every rolling window of every document is hashed in NumPy, looked
up, and each hit is verified word by word. Words of all occurrences are hit, and can be cut out, or
the document can be dropped.

The items are broadcast only up to ``most_bytes`` of text (a task holds about ten times that, in arrays). Beyond it they
go in slices of that size, one pass over the documents after the other, and the hits are united by row, so no bound
drops a case and no task holds more than a slice.
Null or empty texts (of either table) have no words. Repeated items all count; repeated documents are
judged each by itself. An empty benchmark hits nothing.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..checkpoints import cut
from . import common as C

_HIT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("runs", pa.list_(pa.int32())), ("items", pa.list_(pa.string()))])
HIT = "doc_id long, n_words long, runs array<int>, items array<string>"
SCHEMA = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, items array<string>, runs array<int>"
BITS, REMEMBER = 22, 10_000


class WindowSet:
    """All windows of the items, by their number of words: sorted hashes, and the word where each window starts."""

    def __init__(self, items: list[tuple[str, str]], n: int):
        self.items = [item for item, _ in items]
        texts = [text.encode() for _, text in items]
        self.data = C.LOWER[np.frombuffer(b"".join(texts), np.uint8)]
        offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts], dtype=np.int64)])
        self.starts, self.ends, self.rows = C.word_spans(self.data, offsets, C.IS_WORD)
        words = C.span_hashes(self.data, self.starts, self.ends)
        sizes = np.minimum(np.bincount(self.rows, minlength=len(texts)), n)[self.rows]  # of each word's windows
        self.hashes, self.known = {}, {}
        for size in np.unique(sizes).tolist():
            grams = C.gram_hashes(words, size)
            m = len(grams)
            place = np.flatnonzero((sizes[:m] == size) & (self.rows[:m] == self.rows[size - 1 : size - 1 + m]))
            place = place[np.argsort(grams[place], kind="stable")]
            first = np.zeros(1 << BITS, bool)
            first[(grams[place] >> np.uint64(64 - BITS)).astype(np.int64)] = True
            self.hashes[size] = (first, grams[place], place)

    def window(self, at: int, size: int) -> bytes:
        return b" ".join(self.data[a:b].tobytes() for a, b in zip(self.starts[at : at + size].tolist(), self.ends[at : at + size].tolist(), strict=True))

    def owners(self, size: int, gram: int, key: bytes) -> set[str]:
        """Items that hold this window of words; remembered, for frequent windows hit often."""
        if (size, gram) not in self.known:
            if len(self.known) > REMEMBER:
                self.known.clear()
            _, grams, place = self.hashes[size]
            own: dict[bytes, set[str]] = {}
            for at in place[np.searchsorted(grams, np.uint64(gram)) : np.searchsorted(grams, np.uint64(gram), "right")].tolist():
                own.setdefault(self.window(at, size), set()).add(self.items[self.rows[at]])
            self.known[size, gram] = own
        return self.known[size, gram].get(key, set())

    def find(self, data: np.ndarray, offsets: np.ndarray):
        """Words of each row, and for each row that is hit its covered runs [start, end, ...) and items."""
        low = C.LOWER[data]
        starts, ends, rows = C.word_spans(low, offsets, C.IS_WORD)
        words = C.span_hashes(low, starts, ends)
        first_word = np.searchsorted(rows, np.arange(len(offsets)))
        covers: dict[int, list[tuple[int, int]]] = {}
        items: dict[int, set[str]] = {}
        for size, (first, grams, _) in self.hashes.items():
            h = C.gram_hashes(words, size)
            at = np.flatnonzero(first[(h >> np.uint64(64 - BITS)).astype(np.int64)])
            at = at[grams[np.minimum(np.searchsorted(grams, h[at]), len(grams) - 1)] == h[at]]
            at = at[rows[at] == rows[at + size - 1]]
            for i in at.tolist():
                key = b" ".join(low[starts[j] : ends[j]].tobytes() for j in range(i, i + size))
                if owners := self.owners(size, int(h[i]), key):
                    row = int(rows[i])
                    covers.setdefault(row, []).append((i - int(first_word[row]), i + size - int(first_word[row])))
                    items.setdefault(row, set()).update(owners)
        return np.diff(first_word), covers, items


def united(spans: list[tuple[int, int]]) -> list[int]:
    out: list[int] = []
    for a, b in sorted(spans):
        if out and a <= out[-1]:
            out[-1] = max(out[-1], b)
        else:
            out += [a, b]
    return out


class Slices:
    """The items (id, text) in ``n`` parts, each of about ``most_bytes`` of text."""

    def __init__(self, benchmark: DataFrame, most_bytes: int):
        self.items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text")).where("text is not null and item_id is not null")
        size = self.items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        self.n = max(1, -(-size // most_bytes))

    def part(self, k: int):
        """A broadcast of one part."""
        own = self.items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(self.n)) == k)
        return self.items.sparkSession.sparkContext.broadcast([(r.item_id, r.text) for r in own.collect()])


def found(windows: WindowSet, column) -> tuple[np.ndarray, list[list[int]], list[list[str]]]:
    """Words, runs and items of each text of a column."""
    counts, covers, owners = windows.find(*C.flat(column))
    return counts, [united(covers.get(i, [])) for i in range(len(column))], [sorted(owners.get(i, ())) for i in range(len(column))]


def _hits(docs: DataFrame, slices: Slices, n: int) -> DataFrame:
    """r1, r2 (the row), spans, items of the rows that some slice hits: a pass for each slice, of which only hits are kept."""
    rows = docs.select(F.col("text").cast("string").alias("text"), *C.row_key(docs))
    whole = None
    for k in range(slices.n):
        made = slices.part(k)

        def run(batches, made=made):
            windows = WindowSet(made.value, n)
            for batch in batches:
                for piece in C.pieces(batch):
                    _, runs, items = found(windows, piece.column("text"))
                    hit = pa.array([bool(r) for r in runs], pa.bool_())
                    out = [piece.column("r1"), piece.column("r2"), pa.array(runs, _HIT.field("runs").type), pa.array(items, _HIT.field("items").type)]
                    yield pa.RecordBatch.from_arrays(out, names=["r1", "r2", "spans", "items"]).filter(hit)

        one = cut(rows.mapInArrow(run, "r1 long, r2 long, spans array<int>, items array<string>"))
        made.destroy()
        whole = one if whole is None else whole.unionByName(one)
    return whole.groupBy("r1", "r2").agg(F.flatten(F.collect_set("spans")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))


def _one_run(spans: list[int]) -> list[int]:
    return united(list(zip(spans[::2], spans[1::2], strict=True)))


def _digest(hits: DataFrame) -> DataFrame:
    n_hit = F.aggregate(F.sequence(F.lit(0), (F.size("runs") / 2).cast("int")), F.lit(0).cast("long"), lambda acc, i: acc + F.coalesce(F.get("runs", 2 * i + 1) - F.get("runs", 2 * i), F.lit(0)))
    return hits.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), (F.size("runs") > 0).alias("contaminated"), "items", "runs")


def contamination(docs: DataFrame, benchmark: DataFrame, n: int = 10, most_bytes: int = 16 << 20) -> DataFrame:
    """One row per document: its words, how many are hit, the items and the covered word runs. Narrow, if the items are one slice."""
    C.ship(docs.sparkSession)
    slices = Slices(benchmark, most_bytes)
    made = slices.part(0) if slices.n == 1 else docs.sparkSession.sparkContext.broadcast([])
    many = slices.n > 1
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *C.row_key(docs))
    if many:
        rows = rows.join(_hits(docs, slices, n), ["r1", "r2"], "left")

    def run(batches):
        windows = WindowSet(made.value, n)
        for batch in batches:
            for piece in C.pieces(batch):
                counts, runs, items = found(windows, piece.column("text"))
                if many:
                    runs, items = [_one_run(x or []) for x in piece.column("spans").to_pylist()], [x or [] for x in piece.column("items").to_pylist()]
                yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(counts, pa.int64()), pa.array(runs, _HIT.field("runs").type), pa.array(items, _HIT.field("items").type)], schema=_HIT)

    return _digest((rows if many else rows.drop("r1", "r2")).mapInArrow(run, HIT))


def clean_documents(docs: DataFrame, benchmark: DataFrame, n: int = 10, remove: str = "documents", most_bytes: int = 16 << 20) -> DataFrame:
    """Documents without what the benchmark holds, all columns kept: ``documents`` drops each that is hit, ``spans``
    cuts the hit words (and what stands between them) and keeps the rest; n_chars, if there, follows the text. Narrow,
    if the items are one slice."""
    C.ship(docs.sparkSession)
    slices = Slices(benchmark, most_bytes)
    made = slices.part(0) if slices.n == 1 else docs.sparkSession.sparkContext.broadcast([])
    row = F.struct(*[docs[c] for c in docs.columns]).alias("row")
    given = docs.select(row, F.col("text").cast("string").alias("text"))
    if slices.n > 1:
        given = docs.select(row, F.col("text").cast("string").alias("text"), *C.row_key(docs)).join(_hits(docs, slices, n), ["r1", "r2"], "left").select("row", "text", "spans")
    many = slices.n > 1

    def run(batches):
        windows = WindowSet(made.value, n)
        for batch in batches:
            for piece in C.pieces(batch):
                runs = [_one_run(x or []) for x in piece.column("spans").to_pylist()] if many else found(windows, piece.column("text"))[1]
                texts = [cut_runs(t, r) if r else t for t, r in zip(piece.column("text").to_pylist(), runs, strict=True)]
                out = pa.RecordBatch.from_arrays([piece.column("row"), pa.array(texts, pa.string())], names=["row", "text"])
                yield out.filter(pa.array([not r for r in runs], pa.bool_())) if remove == "documents" else out

    new = given.mapInArrow(run, T.StructType([given.schema["row"], T.StructField("text", T.StringType())]))

    def column(c: str):
        if remove == "spans" and c == "n_chars":
            return F.char_length("text").cast(docs.schema[c].dataType).alias(c)
        return F.col("text").cast(docs.schema[c].dataType) if c == "text" else F.col("row")[c].alias(c)

    return new.select(*[column(c) for c in docs.columns])


def cut_runs(text: str, runs) -> str:
    """A text without the words of the runs, and without what stands between words of one run."""
    data = np.frombuffer(text.encode(), np.uint8)
    starts, ends, _ = C.word_spans(C.LOWER[data], np.array([0, len(data)]), C.IS_WORD)
    body, out, at = data.tobytes(), [], 0
    for a, b in zip(runs[::2], runs[1::2], strict=True):
        out.append(body[at : starts[a]])
        at = int(ends[b - 1])
    return b"".join([*out, body[at:]]).decode()
