"""Approximate nearest neighbours by an inverted multi-index.

Vectors are cut in two halves, each quantised by its own centroids (fitted on a bounded sample); a cell is a
pair of centroids. A query walks cells in the order of the summed distances of its halves, with a heap over
pairs, until the cells hold enough entries; those entries are reranked by exact inner products in doubles.

How many are enough is a share of all entries, found on the sample: the least share that gives ``recall`` there
for sample queries against brute force. Data without structure needs a large share, structured data a small one.

Every row is indexed but those whose vector is null, zero, of another length than most of the sample, or holds
null or non-finite components. A row given twice (same id, same vector) counts once. Of equal vectors only the
``k + 1`` smallest ids can be among the nearest (ties go to smaller ids), so just these are kept, which loses
nothing and spreads hot vectors. Cells are packed to units of ``UNIT`` entries, large cells split; queries are sent
to the units of their cells. Fewer candidates than k: all that were found.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common as C

UNIT, QUERY_BLOCK, QUERY_SPLIT, MOST_CENTROIDS = 4096, 256, 1 << 16, 512


def k_means(x: np.ndarray, k: int, rounds: int = 12, seed: int = 0) -> np.ndarray:
    r = np.random.default_rng(seed)
    c = x[r.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        own = nearest(x, c)
        n = np.bincount(own, minlength=len(c))
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        c[n > 0] = sums[n > 0] / n[n > 0, None]
    return c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return ((c * c).sum(1) - 2 * x @ c.T).argmin(1)


class MultiIndex:
    def __init__(self, sample: np.ndarray, centroids: int):
        self.half = sample.shape[1] // 2
        self.left, self.right = k_means(sample[:, : self.half], centroids, seed=0), k_means(sample[:, self.half :], centroids, seed=1)

    def cells(self, x: np.ndarray) -> np.ndarray:
        return nearest(x[:, : self.half], self.left) * len(self.right) + nearest(x[:, self.half :], self.right)

    def distances(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of a query's halves to the centroids; a larger inner product is nearer."""
        return -(self.left @ q[: self.half]), -(self.right @ q[self.half :])

    def visit(self, q: np.ndarray, sizes: np.ndarray, enough: float) -> list[int]:
        """Cells by rising summed distance until they hold ``enough`` entries."""
        a, b = self.distances(q)
        x, y = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
        xs, ys, a, b = x.tolist(), y.tolist(), a[x].tolist(), b[y].tolist()
        heap, out, held, done = [(a[0] + b[0], 0, 0)], [], 0, [0] * len(xs)  # done: columns opened in each row
        done[0] = 1
        while heap and held < enough:
            _, i, j = heapq.heappop(heap)
            cell = xs[i] * len(ys) + ys[j]
            if sizes[cell]:
                out.append(cell)
                held += int(sizes[cell])
            if j + 1 < len(ys):
                heapq.heappush(heap, (a[i] + b[j + 1], i, j + 1))
            if j == 0 and i + 1 < len(xs):
                heapq.heappush(heap, (a[i + 1] + b[0], i + 1, 0))
        return out

    def share_for(self, sample: np.ndarray, k: int, recall: float, queries: int = 200) -> float:
        """Least share of entries, walked in order, that holds ``recall`` of the true neighbours in the sample."""
        n = len(sample)
        if n <= k + 1:
            return 1.0
        cell = self.cells(sample)
        at = np.unique(np.linspace(0, n - 1, min(queries, n)).astype(int))
        places = []
        for i in at:
            scores = sample @ sample[i]
            scores[i] = -np.inf
            true = np.argpartition(-scores, k)[:k]
            a, b = self.distances(sample[i])
            d = (a[:, None] + b).ravel()[cell]
            places.append(np.searchsorted(np.sort(d), d[true], "right") / n)
        return float(min(1.0, np.quantile(np.concatenate(places), recall)))


def _vectors(column, width: int) -> np.ndarray:
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, width)


def valid_vectors(table: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    C.ship(table.sparkSession)
    v = F.col("v")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(v, lambda x: x != 0)
    return table.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v")).where(v.isNotNull() & F.col("id").isNotNull()).where(F.coalesce(fine, F.lit(False)))


def fit(vectors: DataFrame, centroids: int, sample_rows: int, seed: int = 0) -> tuple[np.ndarray, MultiIndex] | None:
    rows = vectors.orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(sample_rows).select("v").collect()
    if not rows:
        return None
    widths = [len(r.v) for r in rows]
    width = max(sorted(set(widths)), key=widths.count)
    sample = np.array([r.v for r in rows if len(r.v) == width])
    return sample, MultiIndex(sample, centroids)


def search(table: DataFrame, queries: F.Column, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", centroids: int = 32, sample_rows: int = 8192, recall: float = 0.95) -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest found for each row that ``queries`` (of column id) selects. Beyond a
    million rows the centroids of a half grow with the fourth root of the table (to ``MOST_CENTROIDS``), and the sample with them."""
    spark, vectors = table.sparkSession, valid_vectors(table, id_col, vec_col)
    grown = min(MOST_CENTROIDS, max(centroids, math.isqrt(math.isqrt(vectors.count()))))
    centroids, sample_rows = grown, sample_rows * grown // centroids
    fitted = fit(vectors, centroids, sample_rows)
    if fitted is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    sample, index = fitted
    width, share = sample.shape[1], index.share_for(sample, k, recall)
    vectors = vectors.where(F.size("v") == width)
    shared = spark.sparkContext.broadcast(index)
    few = vectors.dropDuplicates(["v", "id"]).withColumn("place", F.row_number().over(Window.partitionBy("v").orderBy("id"))).where(F.col("place") <= k + 1)

    def assign(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("id"), b.column("v"), pa.array(shared.value.cells(_vectors(b.column("v"), width)).astype(np.int32))], names=["id", "v", "cell"])

    entries = few.select("id", "v").mapInArrow(assign, "id long, v array<double>, cell int")
    n_cells = len(index.left) * len(index.right)  # bounds what comes to the driver
    sizes = np.zeros(n_cells, np.int64)
    for r in entries.groupBy("cell").count().collect():
        sizes[r["cell"]] = r["count"]
    split = np.maximum(1, -(-sizes // UNIT))
    unit_of = np.zeros(n_cells, np.int64)  # the first unit of each cell; split cells have units of their own
    unit, room = 0, UNIT
    for c in np.flatnonzero(sizes):
        if split[c] > 1:
            unit_of[c], unit, room = unit + 1, unit + int(split[c]), 0
        else:
            if sizes[c] > room:
                unit, room = unit + 1, UNIT
            unit_of[c], room = unit, room - int(sizes[c])
    layout = spark.sparkContext.broadcast((unit_of, split, sizes, share * float(sizes.sum())))
    asked = vectors.where(queries).dropDuplicates(["id", "v"])
    lanes = max(1, -(-asked.count() // QUERY_SPLIT))

    def place(batches):
        for b in batches:
            cell = b.column("cell").to_numpy()
            first, parts = layout.value[0][cell], layout.value[1][cell]
            yield pa.RecordBatch.from_arrays([pa.array((first + np.abs(b.column("id").to_numpy()) // 7 % parts).astype(np.int64)), b.column("id"), b.column("v"), b.column("cell")], names=["unit", "id", "v", "cell"])

    def route(batches):
        first, parts, sizes, enough = layout.value
        for b in batches:
            ids, q = b.column("id").to_pylist(), _vectors(b.column("v"), width)
            unit, row, cells = [], [], []
            for i in range(len(ids)):
                own: dict[int, list[int]] = {}
                for c in shared.value.visit(q[i], sizes, enough):
                    for p in range(int(parts[c])):
                        own.setdefault(int(first[c]) + p, []).append(c)
                unit += own
                row += [i] * len(own)
                cells += own.values()
            yield pa.RecordBatch.from_arrays([pa.array(unit, pa.int64()), pa.array(ids, pa.int64()).take(pa.array(row, pa.int64())), b.column("v").take(pa.array(row, pa.int64())), pa.array(cells, pa.list_(pa.int32()))], names=["unit", "id", "v", "cells"])

    placed = entries.mapInArrow(place, "unit long, id long, v array<double>, cell int").withColumn("lane", F.explode(F.sequence(F.lit(0), F.lit(lanes - 1))))
    routed = asked.mapInArrow(route, "unit long, id long, v array<double>, cells array<int>").withColumn("lane", F.pmod(F.xxhash64("id"), F.lit(lanes)).cast("int"))

    def rerank(key, left, right):
        left, right = left.combine_chunks().sort_by("id"), right.combine_chunks()
        out_q, out_v, out_s = [], [], []
        if len(left) and len(right):
            ids, cell, e = left["id"].to_numpy(), left["cell"].to_numpy(), _vectors(left["v"].combine_chunks(), width)
            names, seen = np.unique(cell, return_inverse=True)
            q_ids, q_all, q_cells = right["id"].to_numpy(), _vectors(right["v"].combine_chunks(), width), right["cells"].to_pylist()
            for at in range(0, len(q_ids), QUERY_BLOCK):
                q = q_all[at : at + QUERY_BLOCK]
                open_ = np.zeros((len(q), len(names)), bool)
                for i, cells in enumerate(q_cells[at : at + QUERY_BLOCK]):
                    open_[i, np.searchsorted(names, np.intersect1d(names, cells))] = True
                scores = np.where(open_[:, seen], q @ e.T, -np.inf)
                scores[q_ids[at : at + QUERY_BLOCK, None] == ids] = -np.inf
                n = min(k, len(ids))
                bar = np.partition(scores, len(ids) - n, axis=1)[:, len(ids) - n]
                for i in range(len(q)):
                    near = np.flatnonzero((scores[i] >= bar[i] - 1e-9 * max(1.0, abs(bar[i]) if np.isfinite(bar[i]) else 1.0)) & np.isfinite(scores[i]))
                    exact = (e[near] * q[i]).sum(1)
                    best = near[np.lexsort((ids[near], -exact))[:k]]
                    out_q += [int(q_ids[at + i])] * len(best)
                    out_v += ids[best].tolist()
                    out_s += (e[best] * q[i]).sum(1).tolist()
        return pa.table({"query_id": pa.array(out_q, pa.int64()), "vec_id": pa.array(out_v, pa.int64()), "score": pa.array(out_s, pa.float64())})

    found = placed.groupBy("unit", "lane").cogroup(routed.groupBy("unit", "lane")).applyInArrow(rerank, "query_id long, vec_id long, score double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def exact_search(table: DataFrame, query_ids: list[int], k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """Brute force for a bounded list of queries, to measure recall."""
    vectors = valid_vectors(table, id_col, vec_col).dropDuplicates(["id", "v"])
    asked = vectors.where(F.col("id").isin(query_ids)).select(F.col("id").alias("query_id"), F.col("v").alias("q"))
    score = F.aggregate(F.zip_with("q", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    pairs = vectors.join(F.broadcast(asked), F.col("id") != F.col("query_id")).select("query_id", F.col("id").alias("vec_id"), score.alias("score"))
    return pairs.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
