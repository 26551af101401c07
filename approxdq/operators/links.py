"""Links to external providers, and the base URI they are judged by."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.uris import host, owner, owner_of_host
from . import reservoir

CLASSES = ("Dataset", "Ontology")


def from_declaration(triples: DataFrame) -> DataFrame:
    """pld of the subject that is declared a data set or ontology; the least, if there are several."""
    declared = triples.where((F.col("p") == "type") & F.col("o").rlike("[/#](" + "|".join(CLASSES) + ")$"))
    return declared.agg(F.min(owner(F.col("s"))).alias("pld"))


def from_majority(triples: DataFrame, approx: bool = False) -> DataFrame:
    """pld of most subjects (rows), ties to the least name; approx: from a sketch of heavy hitters."""
    if approx:
        plds = triples.select(owner(F.col("s")).alias("pld")).where("pld <> ''")
        return plds.agg(F.expr("approx_top_k(pld, 1)").alias("t")).select(F.col("t")[0]["item"].alias("pld"))
    plds = by_owner(triples, "s").where("pld <> ''")
    return plds.groupBy("pld").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "pld").limit(1).select("pld")


def by_owner(triples: DataFrame, column: str) -> DataFrame:
    """pld, n of URIs, a row for each host: a triple costs one look at its URI, and only hosts are resolved to owners."""
    hosts = triples.select(host(F.col(column)).alias("host")).groupBy("host").agg(F.count(F.lit(1)).alias("n"))
    return hosts.select(owner_of_host(F.col("host")).alias("pld"), "n")


def base_uri(triples: DataFrame, late: DataFrame | None = None) -> DataFrame:
    """The declared one, else that of the majority, which is only counted then (one row comes to the driver). ``late``: the same
    triples with subjects made where they are used, so that the look for a declaration makes few."""
    declared = from_declaration(triples if late is None else late)
    found = declared.first()[0]
    return triples.sparkSession.createDataFrame([(found,)], "pld string") if found is not None else from_majority(triples)


def objects(triples: DataFrame) -> DataFrame:
    return triples.where("o_kind = 'uri'").select(owner(F.col("s")).alias("spld"), owner(F.col("o")).alias("opld"))


def exact(triples: DataFrame, mode: str = "pair", base: DataFrame | None = None) -> DataFrame:
    """Share of URI objects of another owner. ``pair``: than the subject's; ``base``: than the base URI's (``base``, if
    it is known); ``distinct_over_total``: distinct such owners over URI objects."""
    if mode == "pair":
        uris = objects(triples)
        numer = F.count_if(F.col("opld") != F.col("spld"))
        return uris.agg(numer.alias("numer"), F.count(F.lit(1)).alias("denom")).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))
    uris = by_owner(triples.where("o_kind = 'uri'"), "o").withColumnRenamed("pld", "opld")
    based = uris.join(F.broadcast(base_uri(triples) if base is None else base))  # one row
    away = F.col("opld") != F.col("pld")
    numer = F.coalesce(F.sum(F.when(away, F.col("n"))), F.lit(0)) if mode == "base" else F.count_distinct(F.when(away, F.col("opld")))
    return based.agg(numer.alias("numer"), F.coalesce(F.sum("n"), F.lit(0)).alias("denom")).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))


def estimate(triples: DataFrame, k: int, unit: str = "occurrence", seed: int = 0, base: DataFrame | None = None) -> DataFrame:
    """From a reservoir of k objects: ``occurrence`` samples URI objects, ``distinct`` samples owners (then the number
    of URI objects is the denominator, and the result is exact once all owners fit). Triples with a ``rid`` (a 64-bit name
    of the row they come from) are sampled by a 64-bit hash of it, without their subjects; others by a digest of the triple,
    which another engine can repeat."""
    base = F.broadcast(base_uri(triples) if base is None else base)
    if unit == "distinct":
        owners = reservoir.bottom_k(objects(triples), ["opld"], k, seed, unit="distinct")
        away = owners.join(base).agg(F.count_if(F.col("opld") != F.col("pld")).alias("numer"))
        return away.crossJoin(objects(triples).agg(F.count(F.lit(1)).alias("denom"))).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))
    ids, form = (["rid", "p", "o"], "fast") if "rid" in triples.columns else (["s", "p", "o"], "md5")
    rows = triples.where("o_kind = 'uri'").select(*ids)
    sample = reservoir.bottom_k(rows, ids, k, seed, form).join(base)
    return sample.agg(F.count_if(owner(F.col("o")) != F.col("pld")).alias("numer"), F.count(F.lit(1)).alias("denom")).select("numer", "denom", (F.col("numer") / F.col("denom")).alias("value"))
