"""The further metrics of the catalogue, each exact and (with k) from a sample of k units."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..checkpoints import cut
from ..functions.uris import fragment
from . import clustering, dereference, reservoir

# Native tests of literals by datatype.
_TESTS = {
    "integer": r"^[+-]?[0-9]+$",
    "decimal": r"^[+-]?[0-9]+([.][0-9]+)?$",
    "date": r"^[0-9]{4}-(0[1-9]|1[0-2])-(0[1-9]|[12][0-9]|3[01])$",
    "json": r"^\{.*\}$",
}


def ratio(df: DataFrame, good: Column) -> DataFrame:
    out = df.agg(F.count_if(good).alias("numer"), F.count(F.lit(1)).alias("denom"))
    return out.select("numer", "denom", F.when(F.col("denom") > 0, F.col("numer") / F.col("denom")).otherwise(0.0).alias("value"))


def _units(df: DataFrame, ids: list[str], k: int | None, seed: int) -> DataFrame:
    return df if k is None else reservoir.bottom_k(df, ids, k, seed)


def slash_uris(uris: DataFrame, k: int | None = None, seed: int = 0) -> DataFrame:
    """URIs (column uri) without a fragment."""
    return ratio(_units(uris.select("uri"), ["uri"], k, seed), fragment(F.col("uri")).isNull())


def forward_links(triples: DataFrame, k: int | None = None, seed: int = 0, fetch=dereference.snapshot_fetch) -> DataFrame:
    """Distinct URI objects that resolve."""
    links = triples.where("o_kind = 'uri' and p <> 'type'").select(F.col("o").alias("uri")).distinct()
    return ratio(dereference.classify(_units(links, ["uri"], k, seed), fetch), dereference.resolved())


def back_links(triples: DataFrame, k: int | None = None, seed: int = 0) -> DataFrame:
    """Subjects that some triple of the set has as its object: the form that needs no requests."""
    pages = _units(triples.select(F.col("s").alias("uri")).distinct(), ["uri"], k, seed)
    targets = triples.where("o_kind = 'uri'").select(F.col("o").alias("target")).distinct()
    return ratio(pages.join(targets, pages["uri"] == targets["target"], "left"), F.col("target").isNotNull())


def back_links_of_documents(uris: DataFrame, contents: DataFrame, k: int | None = None, seed: int = 0, fetch=dereference.snapshot_fetch) -> DataFrame:
    """URIs (column uri) whose own response document has a triple with them as object. contents: doc, o (what each document
    says); the document is the URI without fragment, if a request gets one."""
    got = fetch(_units(uris.select("uri").distinct(), ["uri"], k, seed)).select("uri", F.when(F.col("status").isin(200, 303), F.regexp_extract("uri", "^([^#]*)", 1)).alias("doc"))
    back = contents.select("doc", F.col("o").alias("uri")).distinct().withColumn("back", F.lit(True))
    return ratio(got.join(back, ["doc", "uri"], "left"), F.col("back").isNotNull())


def syntactic_accuracy(triples: DataFrame, k: int | None = None, seed: int = 0) -> DataFrame:
    """Typed literals whose text is of their datatype (strings always are)."""
    literals = triples.where("o_kind = 'literal' and o_datatype is not null").select("s", "p", "o", "o_datatype")
    good = F.lit(True)
    for kind, test in _TESTS.items():
        good = F.when(F.col("o_datatype") == kind, F.col("o").rlike(test)).otherwise(good)
    return ratio(_units(literals, ["s", "p", "o"], k, seed), good)


def damaged(triples: DataFrame, every: int = 20) -> DataFrame:
    """A test set: one typed literal in so many (by digest) gets a mark that spoils it."""
    from ..functions.keys import number, random_key

    hit = (F.col("o_kind") == "literal") & (F.pmod(number(random_key("damage", "s", "p")), F.lit(every)) == 0)
    return triples.withColumn("o", F.when(hit, F.concat(F.lit("?"), "o")).otherwise(F.col("o")))


def property_misuse(triples: DataFrame, vocabulary: DataFrame, k: int | None = None, seed: int = 0) -> DataFrame:
    """Triples that use a property of the vocabulary (p, kind, datatype; small, broadcast) as declared."""
    rows = _units(triples.select("s", "p", "o", "o_kind", "o_datatype"), ["s", "p", "o"], k, seed)
    known = rows.join(F.broadcast(vocabulary.select("p", "kind", "datatype")), "p", "left")
    return ratio(known, F.col("kind").isNotNull() & (F.col("o_kind") == F.col("kind")) & F.col("o_datatype").eqNullSafe(F.col("datatype")))


def disjoint_members(types: DataFrame, disjoint: DataFrame, k: int | None = None, seed: int = 0) -> DataFrame:
    """Instances without a pair of disjoint classes. types: s, o; disjoint: a, b (small, broadcast)."""
    subjects = _units(types.select("s").distinct(), ["s"], k, seed).select("s")
    pairs = F.broadcast(disjoint.select("a", "b"))
    x = types.select("s", F.col("o").alias("a")).join(pairs, "a")
    bad = x.join(types.select("s", F.col("o").alias("b")), ["s", "b"], "left_semi").select("s").distinct().withColumn("bad", F.lit(True))
    return ratio(subjects.join(bad, "s", "left"), F.col("bad").isNull())


def intensional_conciseness(triples: DataFrame, bits: int | None = None, k: int = 4, seed: int = 0) -> DataFrame:
    """Distinct extensions of predicates over predicates. Exact: an extension's signature adds up digests, so no order is
    needed: count and sums of two 32-bit parts over distinct (s, o). With ``bits``: each predicate has a Bloom
    filter of that size, and filters are compared; different filters tell extensions apart without a shuffle of triples. Only
    predicates that share a filter (copies, or full filters) are compared exactly."""
    from ..functions.keys import number, positions

    h = F.md5(F.concat_ws("|", "s", "o"))

    def exact(triples: DataFrame) -> DataFrame:
        rows = triples.select("p", "s", "o").distinct().select("p", number(h).alias("x"), number(F.substring(h, 9, 8)).alias("y"))
        return rows.groupBy("p").agg(F.struct(F.count(F.lit(1)), F.sum("x"), F.sum("y")).alias("sig"))

    if bits is None:
        by = exact(triples)
    else:
        at = triples.select("p", F.posexplode(positions(h, k, bits // k, seed)).alias("i", "at"))
        words = at.groupBy("p", "i", F.floor(F.col("at") / 64).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(at % 64 as int))")).alias("mask"))
        mix = F.xxhash64("i", "word", "mask")
        made = cut(words.groupBy("p").agg(F.struct(F.count(F.lit(1)), F.bit_xor(mix), F.sum(F.shiftrightunsigned(mix, 24))).alias("made")))
        shared = made.groupBy("made").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        alike = made.join(shared, "made", "left_semi").select(F.col("p").alias("like"))
        same = exact(triples.join(alike, F.col("p").eqNullSafe(F.col("like")), "left_semi")).select(F.col("p").alias("like"), "sig")
        by = made.join(same, F.col("p").eqNullSafe(F.col("like")), "left").select("p", F.struct("made", "sig").alias("sig"))
    return by.agg(F.count_distinct("sig").alias("numer"), F.count(F.lit(1)).alias("denom")).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))


def duplicate_instances(instances: DataFrame, flags: DataFrame | None = None) -> DataFrame:
    """Flagged instances over all: later ones of equal signatures, or those that a filter flags."""
    if flags is not None:
        return ratio(flags, F.col("is_dup"))
    groups = instances.groupBy("sig").agg(F.count(F.lit(1)).alias("n"))
    return groups.agg(F.coalesce(F.sum(F.col("n") - 1), F.lit(0)).alias("numer"), F.coalesce(F.sum("n"), F.lit(0)).alias("denom")).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))


def coverage(triples: DataFrame, predicates: list[str], k: int | None = None, seed: int = 0) -> DataFrame:
    """Filled (instance, expected predicate) cells over cells."""
    subjects = triples.select("s").distinct()
    own = _units(subjects, ["s"], k, seed).select("s")
    cells = triples.where(F.col("p").isin(predicates)).join(own, "s", "left_semi").select("s", "p").distinct().agg(F.count(F.lit(1)).alias("numer"))
    return cells.crossJoin(own.agg((F.count(F.lit(1)) * len(predicates)).alias("denom"))).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))


def interlink_quality(edges: DataFrame) -> DataFrame:
    """Each link (a < b) by what it adds to both ends, each link taken out by itself: their degrees with it, and the gain of
    local clustering. Without the link, an end has one neighbour less and loses the triangles that hold the link, so one
    listing of triangles tells all."""
    tri = clustering.triangles(edges)
    link = lambda x, y: F.struct(F.least(x, y).alias("a"), F.greatest(x, y).alias("b"))
    on = tri.select(F.explode(F.array(link("a", "b"), link("a", "c"), link("b", "c"))).alias("e")).select("e.a", "e.b")
    shared = on.groupBy("a", "b").agg(F.count(F.lit(1)).alias("t"))
    local = clustering.local(edges).select("v", "d", F.col("t").alias("tv"))
    of = lambda c: local.select(F.col("v").alias(c), F.col("d").alias(f"d_{c}"), F.col("tv").alias(f"t_{c}"))
    rate = lambda t, d: F.when(d < 2, 0.0).otherwise(2 * t / (d * (d - 1)))
    both = edges.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b")).join(shared, ["a", "b"], "left").join(of("a"), "a").join(of("b"), "b").withColumn("t", F.coalesce("t", F.lit(0)))
    gain = lambda c: rate(F.col(f"t_{c}"), F.col(f"d_{c}")) - rate(F.col(f"t_{c}") - F.col("t"), F.col(f"d_{c}") - 1)
    return both.select("a", "b", "d_a", "d_b", F.col("t").alias("shared"), gain("a").alias("gain_a"), gain("b").alias("gain_b"))


def interlink_reach(edges: DataFrame, links: DataFrame, steps: int = 50, seed: int = 0) -> DataFrame:
    """What walks from the ends of each link (a, b) reach: distinct vertices with the link and without it. edges: a written
    graph of at most ``clustering.MOST_EDGES``, whose lists are broadcast."""
    if edges.count() > clustering.MOST_EDGES:
        raise ValueError("reach needs lists of a bounded size; interlink_quality takes any graph")
    shared = edges.sparkSession.sparkContext.broadcast(clustering.Lists(edges))

    def run(batches):
        own = shared.value
        for batch in batches:
            pairs = list(zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), strict=True))
            ends = [[pc.index(own.names, x).as_py() for x in p] for p in pairs]
            reach = lambda x, y, less: len(set(own.path(x, steps, f"{x}-{y}", seed, less)))
            columns = [[reach(x, y, less) for x, y, less in rows] for rows in ([(a, b, None) for a, b in ends], [(a, b, b) for a, b in ends], [(b, a, None) for a, b in ends], [(b, a, a) for a, b in ends])]
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), *(pa.array(c, pa.int32()) for c in columns)], names=["a", "b", "reach_a", "without_a", "reach_b", "without_b"])

    return links.select("a", "b").mapInArrow(run, "a string, b string, reach_a int, without_a int, reach_b int, without_b int")


def relevant_terms(pages: DataFrame, top: int = 50, iterations: int = 10) -> DataFrame:
    """Share of title words that are among the top words of the body by PageRank over the graph of adjacent words."""
    words = lambda c: F.expr(f"filter(split(lower(regexp_replace({c}, '<[^>]*>', ' ')), '[^\\\\p{{L}}]+'), x -> length(x) > 2)")
    body = pages.select(words("html").alias("w"))
    pairs = body.select(F.explode(F.arrays_zip(F.expr("slice(w, 1, greatest(size(w) - 1, 0))").alias("a"), F.expr("slice(w, 2, greatest(size(w) - 1, 0))").alias("b"))).alias("t")).select("t.a", "t.b")
    from ..plans.graphs import undirected

    rank = clustering.pagerank(undirected(pairs), iterations=iterations)
    best = rank.select(F.round("rank", 9).alias("rank"), "v").orderBy(F.desc("rank"), "v").limit(top).select(F.col("v").alias("term"))
    title = pages.select(F.explode(words("regexp_extract(html, '<title>([^<]*)</title>', 1)")).alias("term")).distinct()
    return ratio(title.join(F.broadcast(best.withColumn("hit", F.lit(True))), "term", "left"), F.col("hit").isNotNull())


