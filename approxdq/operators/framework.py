"""Registry of metrics, assessment of data sets, measures of cost and accuracy, metadata and reports."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

OBSERVATION = "dataset string, metric string, variant string, params map<string,string>, numer bigint, denom bigint, value double, exact boolean, seconds double, computed_at timestamp"


class MetricRegistry:
    """Named metrics; users add their own. direction: whether a high value is good, bad, or open to reading."""

    def __init__(self):
        self.metrics: dict[str, tuple[Callable[..., DataFrame], str, bool]] = {}

    def register(self, name: str, fn: Callable[..., DataFrame], direction: str = "higher", exact: bool = True) -> None:
        if name in self.metrics:
            raise ValueError(f"{name} is registered")
        self.metrics[name] = (fn, direction, exact)

    def direction(self, name: str) -> str:
        return self.metrics[name][1]


def default_registry() -> MetricRegistry:
    from . import catalog, clustering, conciseness, dereference, instances, links
    from ..plans import graphs

    r = MetricRegistry()
    sigs = lambda t: instances.from_any(t).select("sig", F.xxhash64("s").alias("seq"))
    r.register("dereferenceability", dereference.exact)
    r.register("dereferenceability_estimate", lambda t, domains=50, per_domain=10_000: dereference.estimate(t, domains, per_domain), exact=False)
    r.register("external_links", links.exact)
    r.register("external_links_estimate", lambda t, k=50_000: links.estimate(t, k), exact=False)
    r.register("conciseness", lambda t: conciseness.exact(sigs(t)))
    r.register("conciseness_estimate", lambda t, k=10, bits=1_000_000: conciseness.estimate(sigs(t), k, bits), exact=False)
    # High cohesion may also mean links without meaning.
    r.register("clustering", lambda t: clustering.exact(graphs.from_triples(t)), direction="open")
    r.register("clustering_estimate", lambda t, m=1.0: _walked(graphs.from_triples(t), m), direction="open", exact=False)
    r.register("slash_uris", lambda t: catalog.slash_uris(t.select(F.col("s").alias("uri")).distinct()))
    r.register("syntactic_accuracy", catalog.syntactic_accuracy)
    r.register("intensional_conciseness", catalog.intensional_conciseness)
    return r


def _walked(edges: DataFrame, m: float) -> DataFrame:
    from . import clustering

    return clustering.estimate(clustering.walk(edges, m), edges)


def assess(spark: SparkSession, dataset: str, triples: DataFrame, metrics: Iterable[str], registry: MetricRegistry | None = None, params: dict[str, dict] | None = None, keep: bool = True) -> DataFrame:
    """OBSERVATION rows of one data set; triples are read once and kept on disk while the metrics run."""
    from pyspark import StorageLevel

    registry, params, rows = registry or default_registry(), params or {}, []
    own = triples.persist(StorageLevel.DISK_ONLY) if keep else triples
    try:
        for name in metrics:
            fn, _, exact = registry.metrics[name]
            given = params.get(name, {})
            got, seconds = timed(lambda fn=fn, given=given: fn(own, **given).first())
            found = got.asDict()
            rows.append((dataset, name, "exact" if exact else "estimate", {k: str(v) for k, v in given.items()}, found.get("numer"), found.get("denom"), None if found["value"] is None else float(found["value"]), exact, seconds))
    finally:
        if keep:
            own.unpersist()
    return spark.createDataFrame(rows, OBSERVATION.rsplit(",", 1)[0]).withColumn("computed_at", F.current_timestamp())


# -- measures -----------------------------------------------------------------------------------------------


def timed(fn: Callable[[], object]) -> tuple[object, float]:
    start = time.perf_counter()
    out = fn()
    return out, time.perf_counter() - start


def deviation(observations: DataFrame) -> DataFrame:
    """Each estimate against the exact value of its data set and metric: absolute, and relative where exact isn't 0."""
    exact = observations.where("exact").select("dataset", "metric", F.col("value").alias("exact_value"), F.col("seconds").alias("exact_seconds"))
    out = observations.where("not exact").join(exact, ["dataset", "metric"])
    gap = F.abs(F.col("value") - F.col("exact_value"))
    return out.select("dataset", "metric", "variant", "value", "exact_value", gap.alias("absolute"), F.when(F.col("exact_value") != 0, gap / F.abs("exact_value")).alias("relative"), F.when(F.col("seconds") > 0, F.col("exact_seconds") / F.col("seconds")).alias("speedup"), "seconds")


def completed(observations: DataFrame, limit_s: float) -> DataFrame:
    """Data sets that each metric and variant finished within the time box."""
    return observations.groupBy("metric", "variant").agg(F.count_if(F.col("seconds") <= limit_s).alias("completed"), F.count(F.lit(1)).alias("runs"))


def flag_errors(flags: DataFrame, instances: DataFrame) -> DataFrame:
    """False positives (flagged, though the first of its signature) and false negatives, with their rates."""
    first = instances.groupBy("sig").agg(F.min("seq").alias("first"))
    both = flags.select("seq", "sig", "is_dup").join(first, "sig").withColumn("true", F.col("seq") > F.col("first"))
    out = both.agg(F.count_if(F.col("is_dup") & ~F.col("true")).alias("fp"), F.count_if(~F.col("is_dup") & F.col("true")).alias("fn"), F.count_if(~F.col("true")).alias("firsts"), F.count_if("true").alias("repeats"))
    return out.select("fp", "fn", F.when(F.col("firsts") > 0, F.col("fp") / F.col("firsts")).otherwise(0.0).alias("fpr"), F.when(F.col("repeats") > 0, F.col("fn") / F.col("repeats")).otherwise(0.0).alias("fnr"))


def replicate(fn: Callable[[int], float], seeds: Iterable[int]) -> dict[str, float]:
    """Mean, standard deviation and half-width of the 95 % interval over seeds."""
    import statistics

    values = [fn(s) for s in seeds]
    sd = statistics.stdev(values) if len(values) > 1 else 0.0
    return {"mean": statistics.fmean(values), "sd": sd, "half_width": 1.96 * sd / len(values) ** 0.5}


def best_setting(deviations: DataFrame, limit_s: float | None = None) -> DataFrame:
    """The variant of least deviation for each data set and metric, ties to the name; with ``limit_s``, among those that
    took so long at most."""
    deviations = deviations if limit_s is None else deviations.where(F.col("seconds") <= limit_s)
    return deviations.groupBy("dataset", "metric").agg(F.min_by("variant", F.struct("absolute", "variant")).alias("best"), F.min("absolute").alias("absolute"))


# -- metadata and reports -----------------------------------------------------------------------------------

_CUBE = "https://quality.example.org/"


def as_triples(observations: DataFrame) -> DataFrame:
    """Observations as triples about their data set."""
    node = F.concat(F.lit("_:"), F.md5(F.concat_ws("|", "dataset", "metric", "variant")))
    uri = lambda p, o: F.struct(F.lit(_CUBE + p).alias("p"), F.concat(F.lit(_CUBE), o).alias("o"), F.lit("uri").alias("o_kind"), F.lit(None).cast("string").alias("o_datatype"))
    text = lambda p, o, d: F.struct(F.lit(_CUBE + p).alias("p"), o.cast("string").alias("o"), F.lit("literal").alias("o_kind"), F.lit(d).alias("o_datatype"))
    rows = F.array(uri("dataset", F.col("dataset")), uri("metric", F.col("metric")), text("variant", F.col("variant"), "string"), text("value", F.round("value", 6).cast("decimal(18,6)"), "decimal"))
    return observations.select(node.alias("s"), F.explode(rows).alias("t")).select("s", "t.*").where("o is not null")


def register_view(observations: DataFrame, name: str = "quality") -> None:
    observations.createOrReplaceTempView(name)


def by_dataset(observations: DataFrame) -> DataFrame:
    return observations.orderBy("dataset", "metric", "variant")


def pivot(observations: DataFrame, datasets: list[str]) -> DataFrame:
    """Metric and variant by data set; the columns are given, so no extra pass finds them."""
    return observations.groupBy("metric", "variant").pivot("dataset", datasets).agg(F.first("value"))


def observation(dataset: str, metric: str, variant: str, value: float, exact: bool, seconds: float = 0.0) -> Row:
    return Row(dataset=dataset, metric=metric, variant=variant, value=value, exact=exact, seconds=seconds)
