"""The experiments: each metric exact and at its settings, on several data sets, with values and seconds.

Every function returns observations (dataset, metric, variant, params, numer, denom, value, exact, seconds);
``framework.deviation``, ``pivot``, ``best_setting`` and ``completed`` work on them.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .checkpoints import cut
from .deploy import small_methods
from .operators import bloom, clustering, conciseness, dereference, framework, links
from .plans import graphs, mappings
from .queries import SETS, SETTINGS, instance_set

DEREFERENCE = {"P1": (10, 1000), "P2": (50, 100), "P3": (50, 10000), "P4": (100, 1000)}
LINKS = {"P1": 5000, "P2": 10000, "P3": 20000, "P4": 50000}
FACTORS = (0.1, 0.5, 0.7, 1.0)
_SCHEMA = framework.OBSERVATION.rsplit(",", 1)[0]


def _observe(spark: SparkSession, runs: list[tuple[str, str, str, dict, bool, Callable[[], DataFrame]]]) -> DataFrame:
    rows = []
    for dataset, metric, variant, params, exact, make in runs:
        got, seconds = framework.timed(lambda make=make: make().first().asDict())
        rows.append((dataset, metric, variant, {k: str(v) for k, v in params.items()}, got.get("numer"), got.get("denom"), None if got["value"] is None else float(got["value"]), exact, seconds))
    return spark.createDataFrame(rows, _SCHEMA)


def dereferenceability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as they are, and with every owner dead."""
    runs = []
    for name, dead in (("pages", False), ("dead", True)):
        fetch = lambda u, dead=dead: dereference.offline.snapshot(u, dead)
        t = mappings.triples(spark, sf_dir, "pages")
        runs.append((name, "dereferenceability", "exact", {}, True, lambda t=t, f=fetch: dereference.exact(t, f)))
        runs += [(name, "dereferenceability", p, {"domains": g, "uris": k}, False, lambda t=t, f=fetch, g=g, k=k: dereference.estimate(t, g, k, fetch=f)) for p, (g, k) in DEREFERENCE.items()]
    return _observe(spark, runs)


def external_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = []
    for name in ("orders", "lineitem", "customer", "pages"):
        t = mappings.triples(spark, sf_dir, name)
        runs.append((name, "external_links", "exact", {}, True, lambda t=t: links.exact(t, "base")))
        runs += [(name, "external_links", p, {"k": k}, False, lambda t=t, k=k: links.estimate(t, k)) for p, k in LINKS.items()]
    return _observe(spark, runs)


def extensional_conciseness(spark: SparkSession, sf_dir: str, sets=tuple(SETS), policy: str = "balanced") -> DataFrame:
    runs = []
    for name in sets:
        i = instance_set(spark, sf_dir, name)
        runs.append((name, "conciseness", "exact", {}, True, lambda i=i: conciseness.exact(i)))
        runs += [(name, "conciseness", f"P{n}", {"filters": k, "bits": m}, False, lambda i=i, k=k, m=m: conciseness.estimate(i, k, m, policy=policy)) for n, (k, m) in enumerate(SETTINGS, 1)]
    return _observe(spark, runs)


def clustering_coefficient(spark: SparkSession, sf_dir: str, factors=FACTORS, shots: int = 5000) -> DataFrame:
    runs = []
    for name, make in graphs.GRAPHS.items():
        e = make(spark, sf_dir).persist()
        runs.append((name, "clustering", "exact", {}, True, lambda e=e: clustering.exact(e)))
        runs += [(name, "clustering", f"m={m}", {"m": m}, False, lambda e=e, m=m: clustering.estimate(clustering.walk(e, m), e)) for m in factors]
        runs.append((name, "clustering", "one_shot", {"r": shots}, False, lambda e=e: clustering.one_shot(e, shots)))
    return _observe(spark, runs)


def _ladder_links(spark: SparkSession, dataset: str, t: DataFrame, late: DataFrame) -> list:
    """The base URI is found once, in the seconds of the exact value."""
    base: list[DataFrame] = []

    def run(make: Callable[[DataFrame], DataFrame]) -> DataFrame:
        with small_methods(spark):
            if not base:
                base.append(cut(links.base_uri(t, late)))  # one row
            return cut(make(base[0]))

    return [(dataset, "external_links", "exact", {}, True, lambda: run(lambda b: links.exact(t, "base", b))), (dataset, "external_links", "P4", {}, False, lambda: run(lambda b: links.estimate(t, LINKS["P4"], base=b)))]


def ladder(spark: SparkSession, *sf_dirs: str) -> DataFrame:
    """Run time of exact and estimate against size, all four metrics: views of rising size, in each folder."""
    runs = []
    for d in sf_dirs:
        at = d.rstrip("/").rsplit("/", 1)[-1]
        t = mappings.triples(spark, d, "pages")
        runs += [(f"{at} pages", "dereferenceability", "exact", {}, True, lambda t=t: dereference.exact(t)), (f"{at} pages", "dereferenceability", "P3", {}, False, lambda t=t: dereference.estimate(t, *DEREFERENCE["P3"]))]
        for v in ("customer", "orders", "lineitem"):
            runs += _ladder_links(spark, f"{at} {v}", *(mappings.triples(spark, d, v, kind="uri", early=early) for early in (True, False)))
        for v in ("part", "orders", "lineitem"):
            i = instance_set(spark, d, v)
            runs += [(f"{at} {v}", "conciseness", "exact", {}, True, lambda i=i: conciseness.exact(i)), (f"{at} {v}", "conciseness", "sketch", {}, False, lambda i=i: conciseness.sketch(i)), (f"{at} {v}", "conciseness", "P3", {}, False, lambda i=i: conciseness.estimate(i, *SETTINGS[2]))]
        numbered, named = graphs.commerce_numbered(spark, d), graphs.commerce(spark, d)  # the walk looks up tables; the graph by name is never made
        walk = lambda named=named, d=d: clustering.estimate(clustering.walk_by(lambda names: graphs.commerce_near(spark, d, names), graphs.commerce_vertices(spark, d), 0.1), named)
        runs += [(f"{at} commerce", "clustering", "exact", {}, True, lambda e=numbered: clustering.exact(e)), (f"{at} commerce", "clustering", "m=0.1", {}, False, walk)]
        for v in graphs.GRAPHS:
            if v == "commerce":
                continue
            e = cut(graphs.GRAPHS[v](spark, d))
            runs += [(f"{at} {v}", "clustering", "exact", {}, True, lambda e=e: clustering.exact(e)), (f"{at} {v}", "clustering", "m=0.1", {}, False, lambda e=e: clustering.estimate(clustering.walk(e, 0.1), e))]
    return _observe(spark, runs)


def reset_policies(spark: SparkSession, sf_dir: str, name: str = "orders") -> DataFrame:
    """Rates of false positives and false negatives of each policy at each setting."""
    i, out = instance_set(spark, sf_dir, name), None
    for policy in ("balanced", "reservoir", "biased", "biased_single", "none"):
        for n, (k, m) in enumerate(SETTINGS, 1):
            one = framework.flag_errors(bloom.flag_balanced(i, m, k=k, policy=policy), i).withColumn("policy", F.lit(policy)).withColumn("setting", F.lit(f"P{n}"))
            out = one if out is None else out.unionByName(one)
    return out


def grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All values, metric and variant by data set."""
    whole = dereferenceability(spark, sf_dir).unionByName(external_links(spark, sf_dir)).unionByName(extensional_conciseness(spark, sf_dir)).unionByName(clustering_coefficient(spark, sf_dir))
    return framework.pivot(whole, sorted({r.dataset for r in whole.select("dataset").distinct().collect()}))


def main() -> None:
    """python -m approxdq.experiments SF_DIR"""
    import sys

    spark = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").getOrCreate()
    sf_dir = sys.argv[1]
    for run in (dereferenceability, external_links, extensional_conciseness, clustering_coefficient):
        rows = run(spark, sf_dir)
        rows.select("dataset", "metric", "variant", "value", F.round("seconds", 3).alias("seconds")).show(100, False)
        framework.deviation(rows).show(100, False)


if __name__ == "__main__":
    main()
