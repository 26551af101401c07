"""Dereferenceability: URIs that a request resolves to data, over all URIs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..checkpoints import cut
from ..functions.uris import owner
from ..plans import responses as offline
from . import reservoir

RDF = ("application/rdf+xml", "text/turtle", "application/n-triples", "application/ld+json")


def all_uris(triples: DataFrame, distinct: bool = True) -> DataFrame:
    """Subjects and objects that are URIs with a host, and their owners; predicates are taken as fine."""
    both = triples.select(F.explode(F.array(F.struct(F.col("s").alias("uri"), F.lit("uri").alias("kind")), F.struct(F.col("o").alias("uri"), F.col("o_kind").alias("kind")))).alias("t")).select("t.*")
    uris = both.where("kind = 'uri'").select("uri", owner(F.col("uri")).alias("pld")).where("pld <> ''")
    return uris.distinct() if distinct else uris


def outcome_class() -> Column:
    """What a response (uri, status, location, media, hops) amounts to."""
    last = F.element_at("hops", -1)
    rdf = F.col("media").isin(*RDF)
    loop = (F.size("hops") > 1) & (F.size(F.array_distinct(F.transform("hops", lambda h: h["uri"]))) < F.size("hops"))
    return F.when(loop, "loop").when(F.col("status").isNull(), "missing").when((F.col("status") == 303) & (last["status"] == 200) & rdf, "see-other").when((F.col("status") == 200) & rdf & (F.instr("uri", "#") > 0), "hash").when(F.col("status") == 200, "plain").when(F.col("status").between(300, 399), "redirect").when(F.col("status").between(400, 499), "client-error").when(F.col("status").between(500, 599), "server-error").otherwise("malformed")


def resolved() -> Column:
    return F.col("class").isin("see-other", "hash")


def snapshot_fetch(uris: DataFrame) -> DataFrame:
    return offline.snapshot(uris)


def classify(uris: DataFrame, fetch: Callable[[DataFrame], DataFrame] = snapshot_fetch) -> DataFrame:
    got = fetch(uris)
    return uris.join(got, "uri", "left").withColumn("class", outcome_class())


def score(classified: DataFrame) -> DataFrame:
    return classified.agg(F.count_if(resolved()).alias("numer"), F.count(F.lit(1)).alias("denom")).select("numer", "denom", F.when(F.col("denom") > 0, F.col("numer") / F.col("denom")).otherwise(0.0).alias("value"))


def exact(triples: DataFrame, fetch=snapshot_fetch) -> DataFrame:
    """Every distinct URI is requested."""
    return score(classify(all_uris(triples), fetch))


def domain_probe(plds: DataFrame, fetch=snapshot_fetch) -> DataFrame:
    """Owners that answer a request of their own (by the same ``fetch`` as all others): pld, alive. An owner is dead if that
    request fails on the server's side or has no answer."""
    probe = plds.select("pld", F.concat(F.lit("https://"), "pld", F.lit("/")).alias("uri")).distinct()
    return classify(probe, fetch).select("pld", (F.col("class").isin("missing") | F.coalesce(F.col("status") == 503, F.lit(False))).alias("dead")).select("pld", (~F.col("dead")).alias("alive"))


def sample(triples: DataFrame, domains: int, per_domain: int, seed: int = 0) -> DataFrame:
    return reservoir.two_level(all_uris(triples), "pld", ["uri"], domains, per_domain, seed)


def estimate(triples: DataFrame, domains: int, per_domain: int, seed: int = 0, probe: bool = True, weighting: str = "pooled", fetch=snapshot_fetch) -> DataFrame:
    """Two-level sample, then requests. probe: an owner that fails fails all its URIs without further requests.
    ``pooled``: resolved over sampled; ``stratified``: each owner's share weighted by its URIs."""
    uris = cut(sample(triples, domains, per_domain, seed).select("uri", "pld"))  # domains * per_domain rows at most
    if probe:
        alive = cut(domain_probe(uris, fetch))
        dead = uris.join(alive.where("not alive"), "pld", "left_semi").withColumn("class", F.lit("server-error"))
        live = classify(uris.join(alive.where("alive"), "pld", "left_semi"), fetch)
        got = live.select("uri", "pld", "class").unionByName(dead.select("uri", "pld", "class"))
    else:
        got = classify(uris, fetch).select("uri", "pld", "class")
    if weighting == "pooled":
        return score(got)
    sizes = all_uris(triples).groupBy("pld").agg(F.count(F.lit(1)).alias("n"))
    by = got.groupBy("pld").agg(F.count_if(resolved()).alias("ok"), F.count(F.lit(1)).alias("m")).join(sizes, "pld")
    return by.agg(F.sum("ok").alias("numer"), F.sum("m").alias("denom"), (F.sum(F.col("n") * F.col("ok") / F.col("m")) / F.sum("n")).alias("value"))


def cache_misses(uris: DataFrame, cache: DataFrame) -> DataFrame:
    return uris.join(cache.select("uri"), "uri", "left_anti")


def with_cache(uris: DataFrame, cache: DataFrame, fetch=snapshot_fetch) -> DataFrame:
    """The cache with what was missing."""
    return cache.unionByName(fetch(cache_misses(uris, cache)))


def requests(triples: DataFrame, domains: int, per_domain: int, seed: int = 0) -> DataFrame:
    """Requests of the estimate (a probe for each owner, then URIs of those alive) and of the exact form."""
    uris = cut(sample(triples, domains, per_domain, seed))
    alive = domain_probe(uris)
    n = uris.join(alive.where("alive"), "pld", "left_semi").agg(F.count(F.lit(1)).alias("uris"))
    return n.crossJoin(alive.agg(F.count(F.lit(1)).alias("probes"))).crossJoin(all_uris(triples).agg(F.count(F.lit(1)).alias("exact"))).select((F.col("uris") + F.col("probes")).alias("estimate"), "exact")
