"""Graphs over the given tables: undirected, without loops or parallel edges, each edge in both directions."""

from __future__ import annotations

import re
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import table
from .mappings import LINKS_SQL, page_links

COMMERCE = [("lineitem", "concat('o', l_orderkey)", "concat('p', l_partkey)"), ("lineitem", "concat('o', l_orderkey)", "concat('s', l_suppkey)"), ("lineitem", "concat('p', l_partkey)", "concat('s', l_suppkey)"), ("orders", "concat('o', o_orderkey)", "concat('c', o_custkey)"), ("customer", "concat('c', c_custkey)", "concat('n', c_nationkey)"), ("supplier", "concat('s', s_suppkey)", "concat('n', s_nationkey)"), ("nation", "concat('n', n_nationkey)", "concat('r', n_regionkey)")]


def undirected(pairs: DataFrame) -> DataFrame:
    """src, dst in both directions from any pairs; nulls and loops go."""
    a, b = pairs.columns[:2]
    way = lambda x, y: F.struct(F.col(x).alias("src"), F.col(y).alias("dst"))
    return pairs.where(F.col(a) != F.col(b)).select(F.explode(F.array(way(a, b), way(b, a))).alias("e")).select("e.src", "e.dst").distinct()


def from_triples(triples: DataFrame) -> DataFrame:
    """Subjects and objects that are URIs or blank nodes; literals are no vertices."""
    return undirected(triples.where("o_kind <> 'literal'").select("s", "o"))


def commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [table(spark, sf_dir, t).select(F.expr(a).alias("a"), F.expr(b).alias("b")) for t, a, b in COMMERCE]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return undirected(whole)


#: Kinds of vertices of the commerce graph by letter, and the keys that can be numbered with a kind.
KINDS, MOST_KEY = "opscnr", 1 << 59


def _keys() -> list[tuple[str, list[tuple[str, str]]]]:
    """Table of each kind of edge, and letter and key column of both ends."""
    return [(t, [re.fullmatch(r"concat\('(\w)', (\w+)\)", x).groups() for x in ab]) for t, *ab in COMMERCE]


def commerce_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """v of the commerce graph, each once. Keys are made distinct before they are named."""
    with_end: dict[tuple[str, str, str], list[str]] = {}
    for t, (x, y) in _keys():
        with_end.setdefault((t, *x), []).append(y[1])
        with_end.setdefault((t, *y), []).append(x[1])
    keys: dict[str, list[DataFrame]] = {}
    for (t, kind, c), others in with_end.items():
        keys.setdefault(kind, []).append(table(spark, sf_dir, t).where(F.col(c).isNotNull() & F.coalesce(*others).isNotNull()).select(F.col(c).alias("key")))
    return reduce(DataFrame.unionAll, [reduce(DataFrame.unionAll, k).distinct().select(F.concat(F.lit(kind), "key").alias("v")) for kind, k in keys.items()])


def commerce_near(spark: SparkSession, sf_dir: str, names: list[str]) -> DataFrame:
    """v, nbr of these vertices of the commerce graph, each edge once: rows of the given tables with these keys."""
    parts = []
    for t, ends in _keys():
        for (kind, c), (other, d) in (ends, ends[::-1]):
            if own := [int(n[1:]) for n in names if n[0] == kind]:
                parts.append(table(spark, sf_dir, t).where(F.col(c).isin(own) & F.col(d).isNotNull()).select(F.concat(F.lit(kind), c).alias("v"), F.concat(F.lit(other), d).alias("nbr")))
    return reduce(DataFrame.unionAll, parts).distinct()


def commerce_numbered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The commerce graph for operators on numbered vertices: src, dst as eight times the key and the kind, each edge once or
    more, in one direction. With keys too large for that, the graph by name."""
    ends = [(table(spark, sf_dir, t), ab) for t, ab in _keys()]
    for whole, two in ends:
        # row groups are passed over by their least and largest keys
        if not whole.where(" or ".join(f"{c} < -{MOST_KEY} or {c} >= {MOST_KEY}" for _, c in two)).isEmpty():
            return commerce(spark, sf_dir)
    parts = [whole.select(*((F.col(c).cast("long") * 8 + KINDS.index(k)).alias(n) for n, (k, c) in zip(("src", "dst"), two, strict=True))) for whole, two in ends]
    return reduce(DataFrame.unionAll, parts).where("src is not null and dst is not null")


def web(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page to its origin, page to each target, target to its origin."""
    links = page_links(spark, sf_dir).select("s", "o")
    origin = lambda c: F.regexp_extract(c, r"^([A-Za-z][A-Za-z0-9+.-]*://[^/?#]*)", 1)
    pages = table(spark, sf_dir, "pages").select("url", origin(F.col("url")).alias("b"))
    return undirected(links.unionByName(pages.toDF("s", "o")).unionByName(links.select("o", origin(F.col("o"))).toDF("s", "o")))


#: Vectors that are sent to every task at most; beyond it blocks are joined.
MOST_VECTORS = 200_000


def knn(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """k nearest by cosine, by brute force in blocks: each task compares its rows with all vectors, a checked number."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v")).dropna()
    n = e.count()
    if n > MOST_VECTORS:
        raise ValueError("brute force is for bounded tables; use an index")
    rows = e.orderBy("vec_id").toPandas()
    ids, x = rows["vec_id"].to_numpy(), np.stack(rows["v"].to_numpy()) if n else np.zeros((0, 1))
    shared = spark.sparkContext.broadcast((ids, x / np.linalg.norm(x, axis=1, keepdims=True)))

    def near(batches):
        ids, unit = shared.value
        for b in batches:
            own = b.column("vec_id").to_numpy()
            at = np.searchsorted(ids, own)
            for i in range(0, len(at), 256):
                c = np.round(unit[at[i : i + 256]] @ unit.T, 9)
                c[np.arange(len(c)), at[i : i + 256]] = -np.inf
                best = np.stack([np.lexsort((ids, -r))[:k] for r in c])
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(own[i : i + 256], best.shape[1]).astype(str)), pa.array(ids[best.ravel()].astype(str))], names=["a", "b"])

    return undirected(e.select("vec_id").mapInArrow(near, "a string, b string"))


_BOTH = "SELECT DISTINCT src, dst FROM (SELECT a AS src, b AS dst FROM ({pairs}) UNION ALL SELECT b, a FROM ({pairs})) WHERE src <> dst"
_ORIGIN = "regexp_extract({c}, '^([A-Za-z][A-Za-z0-9+.-]*://[^/?#]*)', 1)"
SQL = {
    "commerce": _BOTH.format(pairs=" UNION ".join(f"SELECT {a} AS a, {b} AS b FROM {t}" for t, a, b in COMMERCE)),
    "web": _BOTH.format(pairs=f"SELECT s AS a, o AS b FROM ({LINKS_SQL}) UNION SELECT url, {_ORIGIN.format(c='url')} FROM pages UNION SELECT o, {_ORIGIN.format(c='o')} FROM ({LINKS_SQL})"),
    "knn": _BOTH.format(pairs="SELECT a, b FROM (SELECT x.vec_id::VARCHAR AS a, y.vec_id::VARCHAR AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY round(list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]), 9) DESC, y.vec_id) AS r FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE r <= 5"),
}
GRAPHS = {"commerce": commerce, "web": web, "knn": knn}
