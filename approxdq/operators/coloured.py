"""Triangles and degrees of a graph of numbered vertices, by colours: no wedge and no single edge crosses a shuffle.

A vertex has a colour by a hash of its number. A unit holds the edges between two colours (or within one), packed, and is
written once to the checkpoint folder. Each task reads the units of up to three colours, with Spark and without a shuffle,
and finds in memory the triangles whose vertices have just these colours. More edges make more colours, not larger tasks.
"""

from __future__ import annotations

import math
import struct
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..checkpoints import checkpoint_folder, cut
from ..deploy import ship

#: Edges that a task holds, about.
HELD = 6_000_000
#: Pairs that are packed at once, and wedges that are looked up at once.
PACKED, LOOKED_UP = 3_000_000, 1 << 21
#: Tasks of one job; each is a scan of its own in the plan.
TASKS = 256

_UNIT = "unit int, x binary, y binary, n binary, to binary"
_COUNTS = "colour int, v binary, n binary"


# -- packed arrays ------------------------------------------------------------------------------------------


def put(a: np.ndarray, rising: bool = False) -> bytes:
    """64-bit numbers, as differences where they rise, by planes of bytes."""
    a = np.ascontiguousarray(a, np.int64).view(np.uint64)
    a = np.diff(a, prepend=np.uint64(0)) if rising else a
    width = max(1, -(-int(a.max()).bit_length() // 8)) if len(a) else 1
    planes = np.ascontiguousarray(a.view(np.uint8).reshape(-1, 8)[:, :width].T)
    return struct.pack("<BQ", width, len(a)) + pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def get(packed: bytes, rising: bool = False) -> np.ndarray:
    """What ``put`` packed: int64 where it rises or needs it, else uint32."""
    width, n = struct.unpack_from("<BQ", packed)
    planes = np.frombuffer(pa.decompress(memoryview(packed)[9:], n * width, codec="zstd"), np.uint8).reshape(width, n)
    out = np.zeros((n, 4 if width <= 4 and not rising else 8), np.uint8)
    for i in range(width):
        out[:, i] = planes[i]
    flat = out.view(np.uint32 if out.shape[1] == 4 else np.uint64).reshape(-1)
    return np.cumsum(flat, dtype=np.uint64).view(np.int64) if rising else flat if flat.dtype == np.uint32 else flat.view(np.int64)


def distinct(a: np.ndarray) -> np.ndarray:
    a = np.sort(a)
    return a[np.append(True, a[1:] != a[:-1])] if len(a) else a


def colours_of(v: np.ndarray, colours: int) -> np.ndarray:
    return (((v.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(colours)).astype(np.int64)


def pack(x: np.ndarray, y: np.ndarray) -> tuple[bytes, bytes, bytes, bytes]:
    """Distinct edges: vertices of both sides, and for each x the number of its edges and the places of their y."""
    xs, ys = distinct(x), distinct(y)
    key = distinct(np.searchsorted(xs, x) * len(ys) + np.searchsorted(ys, y))
    at, to = np.divmod(key, len(ys))
    return put(xs, True), put(ys, True), put(np.bincount(at, minlength=len(xs))), put(to)


def unpack(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    return get(row["x"], True), get(row["y"], True), get(row["n"]), get(row["to"])


# -- triangles in memory ------------------------------------------------------------------------------------


def closed(u: np.ndarray, v: np.ndarray, n: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Triangles among edges of vertices below n, each once. Edges point to the end of higher degree; the ends of each edge
    share what both point to, and the shorter list is looked up."""
    d = np.bincount(u, minlength=n) + np.bincount(v, minlength=n)
    turn = (d[u] > d[v]) | ((d[u] == d[v]) & (u > v))
    key = np.where(turn, v, u).astype(np.int64) * n + np.where(turn, u, v)
    del u, v, d, turn
    key.sort()
    a, b = (x.astype(np.int32) for x in np.divmod(key, n))
    out = np.bincount(a, minlength=n)
    start = np.append(0, np.cumsum(out)[:-1])
    bits = max(10, min(30, int(len(key) * 4).bit_length()))
    place = lambda k: (k.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - bits)
    maybe = np.zeros(1 << bits, bool)
    for i in range(0, len(key), LOOKED_UP):
        maybe[place(key[i : i + LOOKED_UP])] = True
    for i in range(0, len(key), LOOKED_UP // 4):
        x, y = a[i : i + LOOKED_UP // 4], b[i : i + LOOKED_UP // 4]
        x, y = x[out[y] > 0], y[out[y] > 0]
        few = np.minimum(out[x], out[y])
        ends = np.cumsum(few)
        lo = 0
        while lo < len(x):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + LOOKED_UP, "right")))
            p, q, k = x[lo:hi], y[lo:hi], few[lo:hi]
            lo = hi
            listed = np.where(out[p] <= out[q], p, q)
            first = np.cumsum(k) - k
            c = b[np.repeat(start[listed] - first, k) + np.arange(k.sum())]
            edge = np.repeat(np.arange(len(p)), k)
            wanted = np.where(listed == p, q, p).astype(np.int64)[edge] * n + c
            found = np.flatnonzero(maybe[place(wanted)])
            wanted = wanted[found]
            there = np.searchsorted(key, wanted)
            there[there == len(key)] = 0
            found = found[key[there] == wanted]
            if len(found):
                yield p[edge[found]], q[edge[found]], c[found]


def triangles_of(units: list[tuple[int, int, tuple]], colours: int, each: bool) -> tuple[int, list[tuple[int, np.ndarray, np.ndarray]]]:
    """Number of triangles of so many colours in these units, and (``each``) for each colour vertices and their triangles."""
    of = sorted({c for i, j, _ in units for c in (i, j)})
    if len(of) < colours:  # no edges between some
        return 0, []
    ids = {c: distinct(np.concatenate([e[s] for *ij, e in units for s in (0, 1) if ij[s] == c])) for c in of}
    base, n = {}, 0
    for c in of:
        base[c], n = n, n + len(ids[c])
    us, vs = [], []
    while units:
        i, j, (xs, ys, count, to) = units.pop()
        us.append(np.repeat((base[i] + np.searchsorted(ids[i], xs)).astype(np.int32), count))
        vs.append((base[j] + np.searchsorted(ids[j], ys)).astype(np.int32)[to])
        del xs, ys, count, to
    u, v = np.concatenate(us), np.concatenate(vs)
    del us, vs
    total, t = 0, np.zeros(n if each else 0, np.int64)
    edge = base[of[1]] if colours == 2 else 0
    for abc in closed(u, v, n):
        if edge:  # not those of one colour
            low = sum((w < edge).astype(np.int8) for w in abc)
            abc = tuple(w[(low > 0) & (low < 3)] for w in abc)
        total += len(abc[0])
        if each:
            for w in abc:
                t += np.bincount(w, minlength=n)
    parts = []
    if each:
        for c in of:
            own = t[base[c] : base[c] + len(ids[c])]
            at = np.flatnonzero(own)
            parts.append((c, ids[c][at], own[at]))
    return total, parts


# -- over Spark ---------------------------------------------------------------------------------------------


class Units:
    """The units of a graph, written. ``pairs`` are the edges (two columns of long; repeats, both directions, loops and nulls
    do no harm)."""

    def __init__(self, pairs: DataFrame, held: int | None = None):
        self.spark = ship(pairs.sparkSession)
        a, b = (F.col(c).cast("long") for c in pairs.columns[:2])
        pairs = pairs.select(a.alias("a"), b.alias("b")).where("a <> b")
        n, held = pairs.count(), held or HELD
        self.colours = colours = 1 if n <= held else max(2, math.ceil(math.sqrt(6 * n / held)))
        self.folder = f"{checkpoint_folder(self.spark)}/units-{uuid.uuid4().hex}"

        def deal(batches):
            a, b, n = [], [], 0
            for batch in batches:
                a.append(batch.column(0).to_numpy())
                b.append(batch.column(1).to_numpy())
                n += len(a[-1])
                if n >= PACKED:
                    yield from _dealt(np.concatenate(a), np.concatenate(b), colours)
                    a, b, n = [], [], 0
            if n:
                yield from _dealt(np.concatenate(a), np.concatenate(b), colours)

        def merge(key, table):
            x, y = [], []
            for row in table.to_batches(max_chunksize=1):
                xs, ys, count, to = unpack(row.to_pylist()[0])
                x.append(np.repeat(xs, count))
                y.append(ys[to])
            return pa.table([pa.array([key[0].as_py()], pa.int32()), *(pa.array([z], pa.binary()) for z in pack(np.concatenate(x), np.concatenate(y)))], names=[f.split()[0] for f in _UNIT.split(", ")])

        dealt = pairs.mapInArrow(deal, _UNIT).repartition(colours * (colours + 1) // 2, "unit")
        dealt.groupBy("unit").applyInArrow(merge, _UNIT).withColumn("of", F.col("unit")).write.partitionBy("of").option("compression", "none").parquet(self.folder)
        self.rows = self.spark.read.schema(_UNIT + ", of int").parquet(self.folder)

    def tasks(self) -> list[list[tuple[int, int]]]:
        """Units of each task: of three colours, of one and another, of one."""
        c = range(self.colours)
        return [[(i, j), (i, k), (j, k)] for i, j, k in combinations(c, 3)] + [[(i, i), (min(i, j), max(i, j))] for i in c for j in c if i != j] + [[(i, i)] for i in c]

    def triangles(self, each: bool = False) -> DataFrame:
        """Rows whose ``found`` add up to the number of triangles; ``each``: with vertices and their triangles, packed."""
        colours, names, tasks = self.colours, "found long, " + _COUNTS, self.tasks()

        def run(batches):
            for task, units in _by_task(batches):
                whole, parts = triangles_of([(*divmod(k, colours), unpack(row)) for k, row in units.items()], len({c for ij in tasks[task] for c in ij}), each)
                rows = [(whole if not i else 0, c, put(v, True), put(t)) for i, (c, v, t) in enumerate(parts)] or [(whole, None, None, None)]
                for r in rows:
                    yield pa.RecordBatch.from_arrays([pa.array([z], t) for z, t in zip(r, (pa.int64(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=[f.split()[0] for f in names.split(", ")])

        out = []
        for at in range(0, len(tasks), TASKS):
            scans = [self.rows.where(F.col("of").isin([i * colours + j for i, j in t])).coalesce(1).select(F.lit(at + n).alias("task"), *(f.split()[0] for f in _UNIT.split(", "))) for n, t in enumerate(tasks[at : at + TASKS])]
            while len(scans) > 1:
                scans = [x.unionAll(y) for x, y in zip(scans[::2], scans[1::2], strict=False)] + scans[len(scans) - len(scans) % 2 :]
            with _apart(self.spark):
                out.append(cut(scans[0].mapInArrow(run, names)))
        while len(out) > 1:
            out = [x.unionAll(y) for x, y in zip(out[::2], out[1::2], strict=False)] + out[len(out) - len(out) % 2 :]
        return out[0]

    def vertices(self, triangles: DataFrame | None = None) -> DataFrame:
        """For each colour: vertices, wedges (pairs of neighbours), and with triangles the sum of local coefficients."""
        colours = self.colours

        def degrees(batches):
            for batch in batches:
                for row in batch.to_pylist():
                    xs, ys, count, to = unpack(row)
                    for c, v, n in zip(divmod(row["unit"], colours), (xs, ys), (count, np.bincount(to, minlength=len(ys))), strict=True):
                        yield pa.RecordBatch.from_arrays([pa.array([c], pa.int32()), pa.array([put(v, True)], pa.binary()), pa.array([put(n)], pa.binary()), pa.array([False])], names=["colour", "v", "n", "closed"])

        def total(table):
            ids = np.zeros(0, np.int64)
            for v, t in zip(table["v"], table["closed"].to_pylist(), strict=True):
                ids = ids if t else distinct(np.append(ids, get(v.as_py(), True)))
            d, t = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
            for v, n, is_t in zip(table["v"], table["n"], table["closed"].to_pylist(), strict=True):
                (t if is_t else d)[np.searchsorted(ids, get(v.as_py(), True))] += get(n.as_py())
            c = np.where(d < 2, 0.0, 2.0 * t / np.maximum(1, d * (d - 1)))
            return pa.table({"vertices": [len(ids)], "wedges": [int((d * (d - 1) // 2).sum())], "c": [float(c.sum())]})

        counts = self.rows.select(*(f.split()[0] for f in _UNIT.split(", "))).mapInArrow(degrees, _COUNTS + ", closed boolean")
        if triangles is not None:
            counts = counts.unionAll(triangles.where("colour is not null").select("colour", "v", "n", F.lit(True)))
        return cut(counts.groupBy("colour").applyInArrow(total, "vertices long, wedges long, c double"))

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def _apart(spark: SparkSession) -> Iterator[None]:
    """Scans of one partition each stay tasks of their own in a union; Spark would make one partition of them all."""
    key = "spark.sql.unionOutputPartitioning"
    was = spark.conf.get(key, None)
    spark.conf.set(key, "false")
    try:
        yield
    finally:
        spark.conf.unset(key) if was is None else spark.conf.set(key, was)


def _dealt(a: np.ndarray, b: np.ndarray, colours: int) -> Iterator[pa.RecordBatch]:
    """Packed edges of each unit: the end of lower colour (or number, within a colour) first."""
    i, j = colours_of(a, colours), colours_of(b, colours)
    turn = (i > j) | ((i == j) & (a > b))
    unit = (np.where(turn, j, i) * colours + np.where(turn, i, j)).astype(np.uint16 if colours < 256 else np.int64)
    a, b = np.where(turn, b, a), np.where(turn, a, b)
    order = np.argsort(unit, kind="stable")
    a, b, unit = a[order], b[order], unit[order]
    ends = np.append(np.flatnonzero(unit[1:] != unit[:-1]) + 1, len(unit))
    for lo, hi in zip(np.append(0, ends[:-1]), ends, strict=True):
        yield pa.RecordBatch.from_arrays([pa.array([int(unit[lo])], pa.int32()), *(pa.array([z], pa.binary()) for z in pack(a[lo:hi], b[lo:hi]))], names=[f.split()[0] for f in _UNIT.split(", ")])


def _by_task(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, dict[int, dict]]]:
    """Units of each task; all rows of a task follow each other."""
    now, units = None, {}
    for batch in batches:
        for row in batch.to_pylist():
            if row["task"] != now and units:
                yield now, units
                units = {}
            now = row["task"]
            units[row["unit"]] = row
    if units:
        yield now, units
