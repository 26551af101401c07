"""Registered queries of the metric engine and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .checkpoints import cut
from .functions import udfs, uris
from .functions.keys import number, random_key
from .operators import bloom, catalog, clustering, conciseness, dereference, framework, instances, links, relational, reservoir
from .plans import graphs, mappings
from .plans.responses import outcome_sql
from .sources import ntriples
from .sources.tables import table
from .streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, fn: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = fn
    if sql:
        ORACLES[name] = sql


# -- SQL pieces ---------------------------------------------------------------------------------------------


def pld_sql(u: str) -> str:
    host = f"lower(regexp_extract({u}, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1))"
    rules = "|".join(s.replace(".", r"\.") for s in uris.SUFFIXES)
    return rf"CASE WHEN regexp_extract({host}, '([^.]+\.(?:{rules}))$', 1) <> '' THEN regexp_extract({host}, '([^.]+\.(?:{rules}))$', 1) ELSE regexp_extract({host}, '([^.]+\.[^.]+)$', 1) END"


def key_sql(seed: int, *parts: str) -> str:
    return "md5(concat_ws('|', '{}', {}))".format(seed, ", ".join(parts))


def num_sql(key: str) -> str:
    return f"('0x' || substr({key}, 1, 8))::BIGINT"


T = mappings.triples_sql
_ALL_URIS = lambda t: f"SELECT DISTINCT uri, {pld_sql('uri')} AS pld FROM (SELECT s AS uri FROM ({t}) UNION ALL SELECT o FROM ({t}) WHERE o_kind = 'uri') WHERE {pld_sql('uri')} <> ''"
_OK = "CASE WHEN k = '303' OR (k = '200-rdf' AND instr(uri, '#') > 0) THEN 1 ELSE 0 END"

# -- views --------------------------------------------------------------------------------------------------

for _v in ("customer", "supplier", "part", "orders", "lineitem", "geo", "pages", "documents", "events", "conversations", "benchmark"):
    add(f"triples_{_v}", lambda s, d, v=_v: mappings.triples(s, d, v), T(_v))

add("uri_parts", lambda s, d: uris.parts(table(s, d, "pages").select(F.col("url").alias("uri"))), f"""
SELECT url AS uri, lower(regexp_extract(url, '^([A-Za-z][A-Za-z0-9+.-]*):', 1)) AS scheme, lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1)) AS host, {pld_sql('url')} AS pld,
 regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)', 1) AS path, CASE WHEN instr(url, '#') > 0 THEN regexp_extract(url, '#(.*)$', 1) END AS ref FROM pages""")
add("pld_counts", lambda s, d: dereference.all_uris(mappings.triples(s, d, "pages")).groupBy("pld").agg(F.count(F.lit(1)).alias("n")), f"SELECT pld, count(*) AS n FROM ({_ALL_URIS(T('pages'))}) GROUP BY pld")
add("resolve_hrefs", lambda s, d: mappings.page_links(s, d).select("s", "o"), f"SELECT s, o FROM ({mappings.LINKS_SQL})")
add("uri_objects", lambda s, d: mappings.triples(s, d, "orders").where("o_kind = 'uri' and p in ('customer', 'type') and o like 'https://%' and s is not null").groupBy("p").agg(F.count(F.lit(1)).alias("n")), f"SELECT p, count(*) AS n FROM ({T('orders')}) WHERE o_kind = 'uri' AND p IN ('customer', 'type') AND o LIKE 'https://%' GROUP BY p")
add("literals", lambda s, d: mappings.triples(s, d, "part").where("o_kind = 'literal' and o_datatype = 'integer' and cast(o as int) between 10 and 20"), f"SELECT * FROM ({T('part')}) WHERE o_kind = 'literal' AND o_datatype = 'integer' AND try_cast(o AS INT) BETWEEN 10 AND 20")


def _round_trip(s, d):
    return ntriples.parse(ntriples.lines(mappings.triples(s, d, "customer"))).select("s", "p", "o", "o_kind", "o_datatype")


add("parse_ntriples", _round_trip, T("customer"))

# -- reservoirs ---------------------------------------------------------------------------------------------

_ORDER_SAMPLE = f"SELECT o_orderkey, {key_sql(7, 'o_orderkey')} AS key FROM orders ORDER BY key, o_orderkey LIMIT 500"
add("reservoir_global", lambda s, d: reservoir.bottom_k(table(s, d, "orders").select("o_orderkey"), ["o_orderkey"], 500, 7), _ORDER_SAMPLE)
add("reservoir_by_owner", lambda s, d: reservoir.bottom_k_by(dereference.all_uris(mappings.triples(s, d, "pages")), "pld", ["uri"], 5, 7), f"SELECT uri, pld, key FROM (SELECT *, row_number() OVER (PARTITION BY pld ORDER BY key, uri) AS r FROM (SELECT *, {key_sql(7, 'uri')} AS key FROM ({_ALL_URIS(T('pages'))}))) WHERE r <= 5")


def _two_level_sql(g: int, k: int, seed: int = 0) -> str:
    u = _ALL_URIS(T("pages"))
    chosen = f"SELECT pld FROM (SELECT DISTINCT pld FROM ({u})) ORDER BY {key_sql(seed, 'pld')}, pld LIMIT {g}"
    return f"SELECT uri, pld, key FROM (SELECT *, row_number() OVER (PARTITION BY pld ORDER BY key, uri) AS r FROM (SELECT *, {key_sql(seed, 'uri')} AS key FROM ({u}) WHERE pld IN ({chosen}))) WHERE r <= {k}"


add("reservoir_two_level", lambda s, d: dereference.sample(mappings.triples(s, d, "pages"), 10, 20), _two_level_sql(10, 20))
add("reservoir_distinct", lambda s, d: reservoir.bottom_k(table(s, d, "events").select("user_id"), ["user_id"], 50, 3, unit="distinct"), f"SELECT user_id, {key_sql(3, 'user_id')} AS key FROM (SELECT DISTINCT user_id FROM events) ORDER BY key, user_id LIMIT 50")


def _merged(s, d):
    o = table(s, d, "orders").select("o_orderkey")
    halves = [reservoir.bottom_k(o.where(F.col("o_orderkey") % 2 == i), ["o_orderkey"], 500, 7) for i in (0, 1)]
    return reservoir.merge(*halves, ["o_orderkey"], 500)


add("reservoir_merge", _merged, _ORDER_SAMPLE)
add("reservoir_sequential", lambda s, d: reservoir.sequential_df(table(s, d, "orders"), "o_orderkey", 500, "o_orderkey", 7))
add("reservoir_skipping", lambda s, d: reservoir.sequential_df(table(s, d, "orders"), "o_orderkey", 500, "o_orderkey", 7, reservoir.skipping))
add("reservoir_bernoulli", lambda s, d: reservoir.bernoulli(table(s, d, "orders").select("o_orderkey"), 0.05, 7))
add("reservoir_stratified", lambda s, d: reservoir.stratified(table(s, d, "orders").select("o_orderkey", "o_orderstatus"), "o_orderstatus", {"F": 0.1, "O": 0.05, "P": 0.2}, 7))

# -- dereferencing ------------------------------------------------------------------------------------------


def _fetched(u: str, dead: bool = False) -> str:
    return f"SELECT uri, pld, {outcome_sql('uri', 'pld', dead)} AS k FROM ({u})"


def _score_sql(rows: str) -> str:
    return f"SELECT sum(ok)::BIGINT AS numer, count(*) AS denom, sum(ok) / count(*) AS value FROM (SELECT {_OK} AS ok FROM ({rows}))"


def _estimate_sql(g: int, k: int) -> str:
    probe = "('0x' || substr(md5('dead|' || pld), 1, 8))::BIGINT % 10 = 0"
    return f"SELECT sum(ok)::BIGINT AS numer, count(*) AS denom, sum(ok) / count(*) AS value FROM (SELECT CASE WHEN {probe} THEN 0 ELSE {_OK} END AS ok FROM ({_fetched(_two_level_sql(g, k))}))"


_PAGES = lambda s, d: mappings.triples(s, d, "pages")
add("dereference_exact", lambda s, d: dereference.exact(_PAGES(s, d)), _score_sql(_fetched(_ALL_URIS(T("pages")))))
for _n, (_g, _k) in enumerate(((10, 1000), (50, 100), (50, 10000), (100, 1000)), 1):
    add(f"dereference_p{_n}", lambda s, d, g=_g, k=_k: dereference.estimate(_PAGES(s, d), g, k), _estimate_sql(_g, _k))
add("dereference_dead_owner", lambda s, d: dereference.exact(_PAGES(s, d), lambda u: dereference.offline.snapshot(u, all_dead=True)), _score_sql(_fetched(_ALL_URIS(T("pages")), True)))
add("dereference_classes", lambda s, d: dereference.classify(dereference.all_uris(_PAGES(s, d))).groupBy("class").agg(F.count(F.lit(1)).alias("n")), f"SELECT CASE WHEN k = '303' THEN 'see-other' WHEN k = '200-rdf' AND instr(uri, '#') > 0 THEN 'hash' WHEN k LIKE '200%' THEN 'plain' WHEN k = 'loop' THEN 'loop' WHEN k = '404' THEN 'client-error' WHEN k IN ('500', '503') THEN 'server-error' ELSE 'malformed' END AS class, count(*) AS n FROM ({_fetched(_ALL_URIS(T('pages')))}) GROUP BY 1")
add("cache_misses", lambda s, d: dereference.cache_misses(dereference.all_uris(_PAGES(s, d)).select("uri"), dereference.offline.snapshot(table(s, d, "pages").select(F.col("url").alias("uri")))), f"SELECT uri FROM ({_ALL_URIS(T('pages'))}) WHERE uri NOT IN (SELECT url FROM pages)")
add("dereference_cache_misses", lambda s, d: dereference.with_cache(dereference.all_uris(_PAGES(s, d)).select("uri"), dereference.offline.snapshot(table(s, d, "pages").select(F.col("url").alias("uri")))).groupBy("status").agg(F.count(F.lit(1)).alias("n")), f"SELECT CASE WHEN k LIKE '200%' THEN 200 WHEN k = 'loop' THEN 301 WHEN k = 'malformed' THEN 0 ELSE k::INT END AS status, count(*) AS n FROM ({_fetched(_ALL_URIS(T('pages')))}) GROUP BY 1")
add("dereference_stratified", lambda s, d: dereference.estimate(_PAGES(s, d), 50, 100, weighting="stratified").select("numer", "denom", F.round("value", 9).alias("value")), f"""
WITH got AS (SELECT pld, sum(CASE WHEN ('0x' || substr(md5('dead|' || pld), 1, 8))::BIGINT % 10 = 0 THEN 0 ELSE {_OK} END) AS ok, count(*) AS m FROM ({_fetched(_two_level_sql(50, 100))}) GROUP BY pld), sizes AS (SELECT pld, count(*) AS n FROM ({_ALL_URIS(T('pages'))}) GROUP BY pld)
SELECT sum(ok)::BIGINT AS numer, sum(m)::BIGINT AS denom, round(sum(n * ok / m) / sum(n), 9) AS value FROM got JOIN sizes USING (pld)""")
add("join_responses", lambda s, d: dereference.classify(dereference.all_uris(_PAGES(s, d))).select("uri", "pld", "status"), f"SELECT uri, pld, CASE WHEN k LIKE '200%' THEN 200 WHEN k = 'loop' THEN 301 WHEN k = 'malformed' THEN 0 ELSE k::INT END AS status FROM ({_fetched(_ALL_URIS(T('pages')))})")
add("uris_resolved", lambda s, d: dereference.all_uris(_PAGES(s, d)).join(dereference.classify(dereference.all_uris(_PAGES(s, d))).where(dereference.resolved()).select("uri"), "uri", "left_semi"), f"SELECT uri, pld FROM ({_fetched(_ALL_URIS(T('pages')))}) WHERE {_OK} = 1")
add("requests_issued", lambda s, d: dereference.requests(_PAGES(s, d), 50, 100), f"SELECT count(*) FILTER (WHERE NOT dead) + count(DISTINCT pld) AS estimate, (SELECT count(*) FROM ({_ALL_URIS(T('pages'))})) AS exact FROM (SELECT pld, ('0x' || substr(md5('dead|' || pld), 1, 8))::BIGINT % 10 = 0 AS dead FROM ({_two_level_sql(50, 100)}))")

# -- links --------------------------------------------------------------------------------------------------

_LINK_VIEWS = ("orders", "lineitem")


_LINK_ROWS = {"orders": ("o_orderkey",), "lineitem": ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")}


def _trade_rows(s, d):
    """The same triples with names of their rows, for samples that need no twin in another engine."""
    each = [mappings.triples(s, d, v, kind="uri", row=row) for v, row in _LINK_ROWS.items()]
    return reduce(DataFrame.unionByName, each).unionByName(mappings.declaration(s).withColumn("rid", F.lit(0).cast("long")))


def _declared(s, d):
    """Owner of the data set that these triples declare; only triples of types are made for it."""
    return links.from_declaration(mappings.triples(s, d, "orders", ("type",)).unionByName(mappings.declaration(s)))


def _trade(s, d, early=False):
    return mappings.triples(s, d, "orders", kind="uri", early=early).unionByName(mappings.triples(s, d, "lineitem", kind="uri", early=early)).unionByName(mappings.declaration(s))


_TRADE_SQL = f"SELECT * FROM ({T('orders')}) UNION ALL SELECT * FROM ({T('lineitem')}) UNION ALL SELECT 'https://sales.example.net/', 'type', '{mappings.VOCAB}Dataset', 'uri', NULL"
_OBJ = lambda t: f"SELECT s, p, o, {pld_sql('s')} AS spld, {pld_sql('o')} AS opld FROM ({t}) WHERE o_kind = 'uri'"
_BASE = "'sales.example.net'"
_MAJORITY = lambda t: f"SELECT pld FROM (SELECT {pld_sql('s')} AS pld FROM ({t})) WHERE pld <> '' GROUP BY pld ORDER BY count(*) DESC, pld LIMIT 1"
_R = lambda n: f"SELECT {n}::BIGINT AS numer, count(*) AS denom, {n} / count(*) AS value"
add("links_pair", lambda s, d: links.exact(_trade(s, d), "pair"), f"{_R('count_if(opld <> spld)')} FROM ({_OBJ(_TRADE_SQL)})")
add("links_base", lambda s, d: links.exact(_trade(s, d), "base", _declared(s, d)), f"{_R(f'count_if(opld <> {_BASE})')} FROM ({_OBJ(_TRADE_SQL)})")
add("links_distinct", lambda s, d: links.exact(_trade(s, d), "distinct_over_total"), f"{_R(f'count(DISTINCT opld) FILTER (WHERE opld <> {_BASE})')} FROM ({_OBJ(_TRADE_SQL)})")
add("links_pages_none", lambda s, d: links.exact(_PAGES(s, d).where("p = 'link'"), "pair"), f"{_R('count_if(opld <> spld)')} FROM ({_OBJ(mappings.LINKS_SQL)})")
add("links_nations", lambda s, d: _nation_links(s, d), "SELECT count_if(c_nationkey <> s_nationkey)::BIGINT AS numer, count(*) AS denom, count_if(c_nationkey <> s_nationkey) / count(*) AS value FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey")


def _nation_links(s, d):
    """Customer to supplier links of each item, through the hosts of their nations."""
    item = table(s, d, "lineitem").select("l_orderkey", "l_suppkey").join(table(s, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    both = item.join(table(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey").join(table(s, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), "l_suppkey")
    host = lambda n: F.concat(F.lit("https://n"), F.col(n), F.lit(".example.org/"))
    return links.exact(both.select(host("c_nationkey").alias("s"), F.lit("buys").alias("p"), host("s_nationkey").alias("o"), F.lit("uri").alias("o_kind")), "pair")


for _n, _k in enumerate((5000, 10000, 20000, 50000), 1):
    _s = f"SELECT opld FROM ({_OBJ(_TRADE_SQL)}) ORDER BY {key_sql(0, 's', 'p', 'o')}, s, p, o LIMIT {_k}"
    add(f"links_p{_n}", lambda s, d, k=_k: links.estimate(_trade(s, d, True), k, base=_declared(s, d)), f"{_R(f'count_if(opld <> {_BASE})')} FROM ({_s})")
    add(f"links_fast_p{_n}", lambda s, d, k=_k: links.estimate(_trade_rows(s, d), k, base=_declared(s, d)))
add("links_reservoir_owners", lambda s, d: links.estimate(_trade(s, d), 5000, unit="distinct"), f"{_R(f'count(DISTINCT opld) FILTER (WHERE opld <> {_BASE})')} FROM ({_OBJ(_TRADE_SQL)})")
add("base_uri_declared", lambda s, d: links.from_declaration(_trade(s, d)), f"SELECT {_BASE} AS pld")
add("base_uri_majority", lambda s, d: links.from_majority(mappings.triples(s, d, "customer")), _MAJORITY(T("customer")))
add("base_uri_resolved", lambda s, d: links.base_uri(mappings.triples(s, d, "customer")), _MAJORITY(T("customer")))
add("distinct_plds", lambda s, d: links.objects(_trade(s, d)).agg(F.count_distinct("opld").alias("n")), f"SELECT count(DISTINCT opld) AS n FROM ({_OBJ(_TRADE_SQL)})")

# -- conciseness --------------------------------------------------------------------------------------------

#: set: table, seq, signature columns (SQL that holds in both engines)
SETS = {
    "orders": ("orders", "o_orderkey", ["o_custkey", "o_orderstatus", "o_orderpriority"]),
    "documents": ("documents", "doc_id", ["text"]),
    "part": ("part", "p_partkey", ["p_brand", "p_type", "p_size"]),
    "lineitem": ("lineitem", "l_orderkey", [mappings.money("l_quantity"), mappings.money("l_discount"), mappings.money("l_tax"), "l_returnflag", "l_linestatus"]),
    "events": ("events", "event_id", ["user_id", "event_type"]),
    "pages": ("pages", "page_id", ["html"]),
}


def instance_set(s: SparkSession, d: str, name: str) -> DataFrame:
    t, seq, columns = SETS[name]
    return instances.from_columns(table(s, d, t), seq, columns)


def _set_sql(name: str) -> str:
    return instances.from_columns_sql(*SETS[name])


_FIRST = lambda i: f"SELECT count(DISTINCT sig) AS numer, count(*) AS denom, count(DISTINCT sig) / count(*) AS value FROM ({i})"
_STRICT = lambda i: f"SELECT count_if(n = 1)::BIGINT AS numer, sum(n)::BIGINT AS denom, count_if(n = 1) / sum(n) AS value FROM (SELECT sig, count(*) AS n FROM ({i}) GROUP BY sig)"
for _v in SETS:
    add(f"conciseness_{_v}", lambda s, d, v=_v: conciseness.exact(instance_set(s, d, v)), _FIRST(_set_sql(_v)))
add("conciseness_strict", lambda s, d: conciseness.exact(instance_set(s, d, "orders"), "strict"), _STRICT(_set_sql("orders")))
add("conciseness_pairwise", lambda s, d: conciseness.pairwise(instance_set(s, d, "part")), _FIRST(_set_sql("part")))
_INST = lambda t: f"SELECT s, md5(string_agg(c, '' ORDER BY c)) AS sig, count(*)::INT AS n_pairs FROM (SELECT DISTINCT s, length(p)::VARCHAR || ':' || p || length(o)::VARCHAR || ':' || o AS c FROM ({t})) GROUP BY s"
_PART = ("brand", "kind", "size")
add("instances_any", lambda s, d: instances.from_any(mappings.triples(s, d, "part", _PART)), _INST(T("part", _PART)))
add("instances_sorted", lambda s, d: instances.from_sorted(mappings.triples(s, d, "part", _PART).withColumn("seq", F.lit(0))), _INST(T("part", _PART)))
add("conciseness_triples", lambda s, d: conciseness.exact(instances.from_any(mappings.triples(s, d, "part", _PART)).select("sig")), _FIRST(_INST(T("part", _PART))))
SETTINGS = ((2, 1_000), (5, 10_000), (10, 100_000), (15, 10_000_000))


def _classic_sql(k: int, bits: int, keep: str) -> str:
    size = bits // k
    at = f"SELECT seq, sig, i, {num_sql(key_sql(0, 'i::VARCHAR', 'sig'))} % {size} AS pos FROM ({_set_sql('orders')}), range({k}) t(i)"
    flags = f"SELECT seq, bool_and(first < seq) AS is_dup FROM (SELECT seq, min(seq) OVER (PARTITION BY i, pos) AS first FROM ({at})) GROUP BY seq"
    return keep.format(flags=flags)


for _n, (_k, _m) in enumerate(SETTINGS, 1):
    add(f"conciseness_classic_p{_n}", lambda s, d, k=_k, m=_m: conciseness.of_flags(bloom.flag_classic(instance_set(s, d, "orders"), k, m)), _classic_sql(_k, _m, "SELECT count_if(NOT is_dup)::BIGINT AS numer, count(*) AS denom, count_if(NOT is_dup) / count(*) AS value FROM ({flags})"))
    add(f"conciseness_balanced_p{_n}", lambda s, d, k=_k, m=_m: conciseness.estimate(instance_set(s, d, "orders"), k, m))


def _policies(s, d):
    out = None
    for policy in ("balanced", "reservoir", "biased", "biased_single", "none"):
        one = conciseness.estimate(instance_set(s, d, "orders"), 10, 100_000, policy=policy).withColumn("policy", F.lit(policy))
        out = one if out is None else out.unionByName(one)
    return out


def _shards(s, d):
    out = None
    for n in (1, 4, 16):
        for form in ("murmur128", "md5"):
            one = conciseness.estimate(instance_set(s, d, "orders"), 10, 100_000, shards=n, form=form).withColumn("variant", F.lit(f"{form}, {n} shards"))
            out = one if out is None else out.unionByName(one)
    return out


add("conciseness_policies", _policies)
add("conciseness_shards", _shards)
for _v in ("documents", "part", "lineitem", "events", "pages"):
    add(f"conciseness_balanced_{_v}", lambda s, d, v=_v: _settings(s, d, v))


def _settings(s, d, v):
    out = None
    for n, one in enumerate(conciseness.estimates(instance_set(s, d, v), list(SETTINGS)), 1):
        one = one.withColumn("setting", F.lit(f"P{n}"))
        out = one if out is None else out.unionByName(one)
    return out


_THETA = f"SELECT * FROM ({_set_sql('orders')}) WHERE {num_sql(key_sql(0, 'sig'))} / 4294967296.0 < 0.1"
add("conciseness_sampled", lambda s, d: conciseness.sampled(instance_set(s, d, "orders"), 0.1), _FIRST(_THETA))
add("conciseness_sampled_strict", lambda s, d: conciseness.sampled(instance_set(s, d, "orders"), 0.1, "strict"), _STRICT(_THETA))
add("conciseness_sketch", lambda s, d: conciseness.sketch(instance_set(s, d, "orders")))
add("conciseness_prefiltered", lambda s, d: conciseness.prefiltered(instance_set(s, d, "orders")), _FIRST(_set_sql("orders")))
add("conciseness_quotient", lambda s, d: conciseness.of_flags(bloom.flag_quotient(instance_set(s, d, "orders"), shards=4)), _FIRST(_set_sql("orders")))
add("flag_errors", lambda s, d: framework.flag_errors(bloom.flag_classic(instance_set(s, d, "orders"), 5, 10_000), instance_set(s, d, "orders")), _classic_sql(5, 10_000, f"""SELECT fp, fn, fp / firsts AS fpr, fn / repeats AS fnr FROM (SELECT count_if(is_dup AND NOT t)::BIGINT AS fp, count_if(NOT is_dup AND t)::BIGINT AS fn, count_if(NOT t) AS firsts, count_if(t) AS repeats FROM (SELECT is_dup, seq > min(seq) OVER (PARTITION BY sig) AS t FROM ({{flags}}) JOIN ({_set_sql('orders')}) USING (seq)))"""))
add("flag_errors_balanced", lambda s, d: framework.flag_errors(bloom.flag_balanced(instance_set(s, d, "orders"), 100_000, k=10), instance_set(s, d, "orders")))


def _membership(s, d):
    """A filter of all labelled documents, probed by all documents."""
    docs, labelled = (table(s, d, t).select(F.col("doc_id").cast("string").alias("v")) for t in ("documents", "labels"))
    made = bloom.build(labelled, "v", 4, 65_536)
    return bloom.might_contain(docs, "v", made, 4, 65_536).agg(F.count_if("hit").alias("hits"), F.count(F.lit(1)).alias("n"))


_BITS = lambda frm: f"SELECT v, i, {num_sql(key_sql(0, 'i::VARCHAR', 'v'))} % 16384 AS pos FROM ({frm}), range(4) t(i)"
add("bloom_membership", _membership, f"SELECT sum(c) FILTER (WHERE hit)::BIGINT AS hits, sum(c)::BIGINT AS n FROM (SELECT v, bool_and(b.pos IS NOT NULL) AS hit FROM ({_BITS('SELECT DISTINCT doc_id::VARCHAR AS v FROM documents')}) a LEFT JOIN (SELECT DISTINCT i, pos FROM ({_BITS('SELECT doc_id::VARCHAR AS v FROM labels')})) b USING (i, pos) GROUP BY v) JOIN (SELECT doc_id::VARCHAR AS v, count(*) AS c FROM documents GROUP BY 1) USING (v)")

# -- clustering ---------------------------------------------------------------------------------------------

_G = graphs.SQL
_DEG = lambda g: f"SELECT src AS v, count(*) AS d FROM ({g}) GROUP BY src"


def _local_sql(g: str) -> str:
    return f"""WITH e AS MATERIALIZED ({g}), dg AS MATERIALIZED (SELECT src AS v, count(*) AS d FROM e GROUP BY src),
up AS MATERIALIZED (SELECT e.src, e.dst, y.d AS dd FROM e JOIN dg x ON e.src = x.v JOIN dg y ON e.dst = y.v WHERE (x.d, e.src) < (y.d, e.dst)),
tri AS (SELECT a.src AS a, a.dst AS b, b.dst AS c FROM up a JOIN up b ON a.src = b.src AND (a.dd, a.dst) < (b.dd, b.dst) SEMI JOIN e ON e.src = a.dst AND e.dst = b.dst),
tri_at AS (SELECT v, count(*) AS t FROM (SELECT unnest([a, b, c]) AS v FROM tri) GROUP BY v),
loc AS (SELECT dg.v, d, coalesce(t, 0) AS t, CASE WHEN d < 2 THEN 0 ELSE 2.0::DOUBLE * coalesce(t, 0) / (d * (d - 1)) END AS c FROM dg LEFT JOIN tri_at USING (v))
"""


def _graph(s, d, g):
    """A graph, written once for the several reads of an estimate."""
    return cut(graphs.GRAPHS[g](s, d))


add("graph_degrees", lambda s, d: clustering.degrees(graphs.commerce(s, d)), _DEG(_G["commerce"]))
_VAL = lambda df: df.withColumn("value", F.round("value", 9))
for _g in ("commerce", "web", "knn"):
    add(f"clustering_exact_{_g}", lambda s, d, g=_g: _VAL(clustering.exact(graphs.commerce_numbered(s, d) if g == "commerce" else _graph(s, d, g))), _local_sql(_G[_g]) + "SELECT round(avg(c), 9) AS value, count(*) AS vertices FROM loc")
add("clustering_local", lambda s, d: clustering.local(_graph(s, d, "web")).withColumn("c", F.round("c", 9)), _local_sql(_G["web"]) + "SELECT v, d, t::BIGINT AS t, round(c, 9) AS c FROM loc")
add("triangles", lambda s, d: clustering.count_triangles(graphs.commerce_numbered(s, d)), _local_sql(_G["commerce"]) + "SELECT count(*) AS n FROM tri")
add("clustering_global", lambda s, d: _VAL(clustering.exact_global(graphs.commerce_numbered(s, d))), _local_sql(_G["commerce"]) + "SELECT sum(t)::BIGINT AS closed, sum(d * (d - 1) // 2)::BIGINT AS wedges, round(sum(t) / sum(d * (d - 1) // 2), 9) AS value FROM loc")
add("clustering_normalised", lambda s, d: clustering.exact(_graph(s, d, "web")).select(F.round(clustering.normalise(F.col("value")), 9).alias("clipped"), F.round(clustering.normalise(F.col("value"), "complement"), 9).alias("complement")), _local_sql(_G["web"]) + "SELECT round(least(1, greatest(0, avg(c))), 9) AS clipped, round(1 - least(1, greatest(0, avg(c))), 9) AS complement FROM loc")
add("clustering_pairs", lambda s, d: _VAL(clustering.exact_pairs(_graph(s, d, "web"))), _local_sql(_G["web"]) + "SELECT round(avg(c), 9) AS value, count(*) AS vertices FROM loc")


def _walk_sql(g: str, m: float, out: str) -> str:
    return f"""WITH RECURSIVE e AS MATERIALIZED ({g}), nb AS MATERIALIZED (SELECT src AS v, dst AS nbr, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS i, count(*) OVER (PARTITION BY src) AS d FROM e),
r AS (SELECT greatest(3, floor({m} * pow(ln(count(DISTINCT src)), 2) + 0.5)) AS r FROM e),
w(step, v) AS (SELECT 1, (SELECT v FROM (SELECT DISTINCT src AS v FROM e) ORDER BY md5('1|start|' || v), v LIMIT 1) UNION ALL
 SELECT step + 1, nbr FROM w JOIN nb ON nb.v = w.v AND nb.i = ('0x' || substr(md5('1|0|' || step), 1, 8))::BIGINT % nb.d WHERE step < (SELECT r FROM r)),
wd AS (SELECT step, w.v, d, lag(w.v) OVER (ORDER BY step) AS a, lead(w.v) OVER (ORDER BY step) AS b FROM w JOIN (SELECT DISTINCT v, d FROM nb) USING (v)),
f AS (SELECT wd.*, CASE WHEN a IS NOT NULL AND b IS NOT NULL THEN (EXISTS (SELECT 1 FROM e WHERE src = a AND dst = b))::INT END AS closed FROM wd)
{out}"""


_EST = "SELECT count(*) AS steps, round(avg(CASE WHEN closed IS NOT NULL THEN CASE WHEN d > 1 THEN closed / (d - 1) ELSE 0 END END) / avg(1 / d), 9) AS value FROM f"


def _walked(s, d, g, m, **kw):
    edges = graphs.commerce_numbered(s, d) if g == "commerce" else _graph(s, d, g)
    if not clustering.numbered(edges) and g == "commerce":  # keys too large to number
        edges = cut(edges)
    return clustering.walk(edges, m, seed=1, kinds=graphs.KINDS, **kw), edges


for _label, _m in (("m01", 0.1), ("m05", 0.5), ("m07", 0.7), ("m10", 1.0)):
    add(f"clustering_walk_{_label}", lambda s, d, m=_m: _VAL(clustering.estimate(*_walked(s, d, "commerce", m))), _walk_sql(_G["commerce"], _m, _EST))
add("clustering_walk_web", lambda s, d: _VAL(clustering.estimate(*_walked(s, d, "web", 1.0))), _walk_sql(_G["web"], 1.0, _EST))
add("clustering_walk_knn", lambda s, d: _VAL(clustering.estimate(*_walked(s, d, "knn", 1.0))), _walk_sql(_G["knn"], 1.0, _EST))
add("walk_wedges", lambda s, d: clustering.wedges(*_walked(s, d, "web", 1.0)).select("step", "v", "d", "closed"), _walk_sql(_G["web"], 1.0, "SELECT step, v, d, closed FROM f"))
add("clustering_walk_long", lambda s, d: _VAL(clustering.estimate(*_walked(s, d, "commerce", 100.0, walkers=64, start="degree"))))
add("clustering_walk_global", lambda s, d: _VAL(clustering.estimate(*_walked(s, d, "commerce", 100.0, walkers=64, start="degree"), kind="global")))


def _one_shot_sql(g: str, r: int) -> str:
    pick = lambda side: f"arg_min(dst, md5('1|{side}|' || slot || '|' || dst))"
    return f"""WITH e AS MATERIALIZED ({g}), slots AS (SELECT src || '>' || dst AS slot, src AS c FROM e ORDER BY md5('1|' || src || '|' || dst), src, dst LIMIT {r}),
dr AS (SELECT slot, {pick('l')} AS a, {pick('r')} AS b, count(*) AS d FROM slots JOIN e ON c = src GROUP BY slot)
SELECT round(avg(CASE WHEN d > 1 THEN (EXISTS (SELECT 1 FROM e WHERE e.src = dr.a AND e.dst = dr.b))::INT / (d - 1) ELSE 0 END) / avg(1 / d), 9) AS value, count(*) AS steps FROM dr"""


add("clustering_one_shot", lambda s, d: _VAL(clustering.one_shot(_graph(s, d, "web"), 2000, 1)), _one_shot_sql(_G["web"], 2000))
add("clustering_one_shot_commerce", lambda s, d: _VAL(clustering.one_shot(_graph(s, d, "commerce"), 5000, 1)), _one_shot_sql(_G["commerce"], 5000))
add("join_edges", lambda s, d: (lambda e: e.join(clustering.degrees(e).hint("merge").withColumnRenamed("v", "dst"), "dst").groupBy("src").agg(F.sum("d").alias("around")))(_graph(s, d, "commerce")), f"SELECT src, sum(d)::BIGINT AS around FROM ({_G['commerce']}) JOIN ({_DEG(_G['commerce'])}) ON dst = v GROUP BY src")
add("components_web", lambda s, d: clustering.connected(graphs.web(s, d)).groupBy("component").agg(F.count(F.lit(1)).alias("n")), f"WITH RECURSIVE e AS MATERIALIZED ({_G['web']}), r(v, c) AS (SELECT DISTINCT src, src FROM e UNION SELECT e.dst, r.c FROM r JOIN e ON e.src = r.v WHERE r.c < e.dst), m AS (SELECT v, min(c) AS component FROM r GROUP BY v) SELECT component, count(*) AS n FROM m GROUP BY component")

# -- catalogue ----------------------------------------------------------------------------------------------

_RATIO = lambda good, frm: f"SELECT count_if({good})::BIGINT AS numer, count(*) AS denom, count_if({good}) / count(*) AS value FROM ({frm})"
_SAMPLED = lambda frm, ids, k: f"SELECT * FROM ({frm}) ORDER BY {key_sql(0, *ids)}, {', '.join(ids)} LIMIT {k}"
_LINKED = f"SELECT DISTINCT o AS uri FROM ({mappings.LINKS_SQL})"
_FWD = lambda frm: f"SELECT uri, {outcome_sql('uri', pld_sql('uri'))} AS k FROM ({frm})"
add("forward_links", lambda s, d: catalog.forward_links(_PAGES(s, d).where("p = 'link'")), _RATIO(f"{_OK} = 1", _FWD(_LINKED)))
add("forward_links_sampled", lambda s, d: catalog.forward_links(_PAGES(s, d).where("p = 'link'"), k=300), _RATIO(f"{_OK} = 1", _FWD(_SAMPLED(_LINKED, ["uri"], 300))))
add("back_links", lambda s, d: catalog.back_links(mappings.triples(s, d, "customer").unionByName(mappings.triples(s, d, "orders"))), _RATIO("o IS NOT NULL", f"SELECT s, o FROM (SELECT DISTINCT s FROM ({T('customer')} UNION ALL {T('orders')})) LEFT JOIN (SELECT DISTINCT o FROM ({T('customer')} UNION ALL {T('orders')}) WHERE o_kind = 'uri') ON s = o"))
_SELF = f"SELECT u.url AS uri, l.o IS NOT NULL AND k IN ('303', '200-rdf', '200-html') AS good FROM (SELECT DISTINCT url, {outcome_sql('url', pld_sql('url'))} AS k FROM pages) u LEFT JOIN (SELECT DISTINCT s, o FROM ({mappings.LINKS_SQL})) l ON l.s = regexp_extract(u.url, '^([^#]*)', 1) AND l.o = u.url"
_OWN = lambda s, d: (table(s, d, "pages").select(F.col("url").alias("uri")), mappings.page_links(s, d).select(F.col("s").alias("doc"), "o"))
add("back_links_documents", lambda s, d: catalog.back_links_of_documents(*_OWN(s, d)), _RATIO("good", _SELF))
add("back_links_documents_sampled", lambda s, d: catalog.back_links_of_documents(*_OWN(s, d), k=100), _RATIO("good", _SAMPLED(_SELF, ["uri"], 100)))
add("slash_uris", lambda s, d: catalog.slash_uris(table(s, d, "pages").select(F.col("url").alias("uri"))), _RATIO("instr(url, '#') = 0", "SELECT url FROM pages"))
add("slash_uris_sampled", lambda s, d: catalog.slash_uris(table(s, d, "pages").select(F.col("url").alias("uri")), k=100), _RATIO("instr(uri, '#') = 0", _SAMPLED("SELECT url AS uri FROM pages", ["uri"], 100)))
_DAMAGED = f"SELECT s, p, CASE WHEN o_kind = 'literal' AND ('0x' || substr(md5('damage|' || s || '|' || p), 1, 8))::BIGINT % 20 = 0 THEN '?' || o ELSE o END AS o, o_datatype FROM ({T('orders')} UNION ALL {T('events')}) WHERE o_kind = 'literal' AND o_datatype IS NOT NULL"
_PARSES = r"CASE o_datatype WHEN 'integer' THEN regexp_matches(o, '^[+-]?[0-9]+$') WHEN 'decimal' THEN regexp_matches(o, '^[+-]?[0-9]+([.][0-9]+)?$') WHEN 'date' THEN regexp_matches(o, '^[0-9]{4}-(0[1-9]|1[0-2])-(0[1-9]|[12][0-9]|3[01])$') WHEN 'json' THEN regexp_matches(o, '^\{.*\}$') ELSE true END"
_HURT = lambda s, d: catalog.damaged(mappings.triples(s, d, "orders").unionByName(mappings.triples(s, d, "events")))
add("syntactic_accuracy", lambda s, d: catalog.syntactic_accuracy(_HURT(s, d)), _RATIO(_PARSES, _DAMAGED))
add("syntactic_accuracy_sampled", lambda s, d: catalog.syntactic_accuracy(_HURT(s, d), k=2000), _RATIO(_PARSES, _SAMPLED(_DAMAGED, ["s", "p", "o"], 2000)))


def _vocabulary(s):
    rows = sorted({(p, k, t) for p, _, k, t in mappings.VIEWS["orders"][2] if p != "status"}, key=str)
    return s.createDataFrame(rows, "p string, kind string, datatype string")


add("property_misuse", lambda s, d: catalog.property_misuse(mappings.triples(s, d, "orders"), _vocabulary(s)), _RATIO("p <> 'status'", T("orders")))
add("property_misuse_sampled", lambda s, d: catalog.property_misuse(mappings.triples(s, d, "orders"), _vocabulary(s), k=2000), _RATIO("p <> 'status'", _SAMPLED(T("orders"), ["s", "p", "o"], 2000)))
_CLASH = "https://schema.example.org/"


def _types(s, d):
    own = mappings.triples(s, d, "customer", ("type",)).unionByName(mappings.triples(s, d, "supplier", ("type",))).select("s", "o")
    clash = own.where(F.pmod(number(random_key("clash", "s")), F.lit(25)) == 0).select("s", F.lit(_CLASH + "Supplier").alias("o"))
    return own.unionByName(clash)


_TYPES = f"SELECT s, o FROM ({T('customer', ('type',))} UNION ALL {T('supplier', ('type',))})"
add("disjoint_members", lambda s, d: catalog.disjoint_members(_types(s, d), s.createDataFrame([(_CLASH + "Customer", _CLASH + "Supplier")], "a string, b string")), _RATIO("NOT (ends_with(o, 'Customer') AND ('0x' || substr(md5('clash|' || s), 1, 8))::BIGINT % 25 = 0)", _TYPES))

add("disjoint_members_sampled", lambda s, d: catalog.disjoint_members(_types(s, d), s.createDataFrame([(_CLASH + "Customer", _CLASH + "Supplier")], "a string, b string"), k=100), _RATIO("NOT (contains(s, '/customer/') AND ('0x' || substr(md5('clash|' || s), 1, 8))::BIGINT % 25 = 0)", _SAMPLED(f"SELECT DISTINCT s FROM ({_TYPES})", ["s"], 100)))


def _copied(s, d):
    t = mappings.triples(s, d, "orders").select("s", "p", "o")
    return t.unionByName(t.where("p = 'status'").select("s", F.lit("state").alias("p"), "o"))


add("intensional_conciseness", lambda s, d: catalog.intensional_conciseness(_copied(s, d)), f"SELECT count(DISTINCT sig) AS numer, count(*) AS denom, count(DISTINCT sig) / count(*) AS value FROM (SELECT p, md5(string_agg(s || '|' || o, ',' ORDER BY s, o)) AS sig FROM (SELECT s, p, o FROM ({T('orders')}) UNION SELECT s, 'state', o FROM ({T('orders')}) WHERE p = 'status') GROUP BY p)")
add("intensional_conciseness_filter", lambda s, d: catalog.intensional_conciseness(_copied(s, d), bits=1 << 16), ORACLES["intensional_conciseness"])
add("duplicate_instances", lambda s, d: catalog.duplicate_instances(instance_set(s, d, "documents")), f"SELECT count(*) - count(DISTINCT sig) AS numer, count(*) AS denom, (count(*) - count(DISTINCT sig)) / count(*) AS value FROM ({_set_sql('documents')})")
add("duplicate_instances_filter", lambda s, d: catalog.duplicate_instances(None, bloom.flag_classic(instance_set(s, d, "orders"), 5, 10_000)), _classic_sql(5, 10_000, "SELECT count_if(is_dup)::BIGINT AS numer, count(*) AS denom, count_if(is_dup) / count(*) AS value FROM ({flags})"))
_COV = "SELECT (SELECT count(*) FROM (SELECT DISTINCT s, p FROM ({t}) WHERE p IN ('quality', 'toxic') AND s IN (SELECT s FROM ({u}))))::BIGINT AS numer, count(*) * 2 AS denom, (SELECT count(*) FROM (SELECT DISTINCT s, p FROM ({t}) WHERE p IN ('quality', 'toxic') AND s IN (SELECT s FROM ({u})))) / (count(*) * 2) AS value FROM ({u})"
_DOCS = f"SELECT DISTINCT s FROM ({T('documents')})"
add("coverage", lambda s, d: catalog.coverage(mappings.triples(s, d, "documents"), ["quality", "toxic"]), _COV.format(t=T("documents"), u=_DOCS))
add("coverage_sampled", lambda s, d: catalog.coverage(mappings.triples(s, d, "documents"), ["quality", "toxic"], k=200), _COV.format(t=T("documents"), u=_SAMPLED(_DOCS, ["s"], 200)))
_GAIN = lambda c: f"round(CASE WHEN d_{c} < 2 THEN 0 ELSE 2.0::DOUBLE * t_{c} / (d_{c} * (d_{c} - 1)) END - CASE WHEN d_{c} < 3 THEN 0 ELSE 2.0::DOUBLE * (t_{c} - shared) / ((d_{c} - 1) * (d_{c} - 2)) END, 9) AS gain_{c}"
add("interlink_quality", lambda s, d: catalog.interlink_quality(_graph(s, d, "web")).withColumn("gain_a", F.round("gain_a", 9)).withColumn("gain_b", F.round("gain_b", 9)), _local_sql(_G["web"]) + f"""SELECT a, b, d_a, d_b, shared, {_GAIN('a')}, {_GAIN('b')} FROM (SELECT e.src AS a, e.dst AS b, x.d AS d_a, y.d AS d_b, x.t::BIGINT AS t_a, y.t::BIGINT AS t_b, coalesce(n, 0)::BIGINT AS shared FROM e JOIN loc x ON e.src = x.v JOIN loc y ON e.dst = y.v
LEFT JOIN (SELECT p.src AS a, q.src AS b, count(*) AS n FROM e p JOIN e q ON p.dst = q.dst AND p.src < q.src GROUP BY 1, 2) z ON z.a = e.src AND z.b = e.dst WHERE e.src < e.dst)""")
add("interlink_reach", lambda s, d: (lambda e: catalog.interlink_reach(e, reservoir.bottom_k(e.where("src < dst"), ["src", "dst"], 500, 1).select(F.col("src").alias("a"), F.col("dst").alias("b"))))(_graph(s, d, "web")))
add("relevant_terms", lambda s, d: catalog.relevant_terms(table(s, d, "pages")))
add("pagerank_web", lambda s, d: clustering.pagerank(graphs.web(s, d), iterations=3).select("v", F.round("rank", 8).alias("rank")), f"WITH e AS MATERIALIZED ({_G['web']}), dg AS (SELECT src AS v, count(*) AS d FROM e GROUP BY src), r1 AS MATERIALIZED (SELECT dst AS v, 0.15 + 0.85 * sum(1.0::DOUBLE / d) AS r FROM e JOIN dg ON src = v GROUP BY dst), r2 AS MATERIALIZED (SELECT dst AS v, 0.15 + 0.85 * sum(r / d) AS r FROM e JOIN dg ON src = dg.v JOIN r1 ON src = r1.v GROUP BY dst), r3 AS (SELECT dst AS v, 0.15 + 0.85 * sum(r / d) AS r FROM e JOIN dg ON src = dg.v JOIN r2 ON src = r2.v GROUP BY dst) SELECT v, round(r, 8) AS rank FROM r3")

# -- measures, framework, experiments -----------------------------------------------------------------------


def _observed(s, d):
    """Conciseness of four sets, exact and by plain filters of the four settings."""
    out = None
    for v in ("orders", "documents", "part", "events"):
        rows = [conciseness.exact(instance_set(s, d, v)).withColumn("variant", F.lit("exact"))]
        rows += [conciseness.of_flags(bloom.flag_classic(instance_set(s, d, v), k, m)).withColumn("variant", F.lit(f"P{n}")) for n, (k, m) in enumerate(SETTINGS, 1)]
        for r in rows:
            one = r.select(F.lit(v).alias("dataset"), F.lit("conciseness").alias("metric"), "variant", F.round("value", 9).alias("value"), (F.col("variant") == "exact").alias("exact"), F.lit(None).cast("double").alias("seconds"))
            out = one if out is None else out.unionByName(one)
    return cut(out)  # 20 rows, read several times


def _observed_sql() -> str:
    rows = []
    for v in ("orders", "documents", "part", "events"):
        rows.append(f"SELECT '{v}' AS dataset, 'conciseness' AS metric, 'exact' AS variant, round(value, 9) AS value, true AS exact FROM ({_FIRST(_set_sql(v))})")
        for n, (k, m) in enumerate(SETTINGS, 1):
            q = _classic_sql(k, m, "SELECT count_if(NOT is_dup) / count(*) AS value FROM ({flags})").replace(_set_sql("orders"), _set_sql(v))
            rows.append(f"SELECT '{v}', 'conciseness', 'P{n}', round(value, 9), false FROM ({q})")
    return " UNION ALL ".join(rows)


_DEV = f"SELECT a.dataset, a.metric, a.variant, a.value, b.value AS exact_value, round(abs(a.value - b.value), 9) AS absolute, round(abs(a.value - b.value) / abs(b.value), 9) AS relative FROM ({_observed_sql()}) a JOIN ({_observed_sql()}) b ON a.dataset = b.dataset AND NOT a.exact AND b.exact"
add("deviation_table", lambda s, d: framework.deviation(_observed(s, d)).select("dataset", "metric", "variant", "value", "exact_value", F.round("absolute", 9).alias("absolute"), F.round("relative", 9).alias("relative")), _DEV)
add("best_setting", lambda s, d: framework.best_setting(framework.deviation(_observed(s, d)).withColumn("absolute", F.round("absolute", 9))), f"SELECT dataset, metric, arg_min(variant, (absolute, variant)) AS best, min(absolute) AS absolute FROM ({_DEV}) GROUP BY ALL")
_SECONDS = {"P1": 1.0, "P2": 2.0, "P3": 3.0, "P4": 4.0}
add("best_setting_in_time", lambda s, d: framework.best_setting(framework.deviation(_observed(s, d)).withColumn("absolute", F.round("absolute", 9)).withColumn("seconds", F.element_at(F.create_map(*[F.lit(x) for kv in _SECONDS.items() for x in kv]), F.col("variant"))), 2.5), f"SELECT dataset, metric, arg_min(variant, (absolute, variant)) AS best, min(absolute) AS absolute FROM ({_DEV}) WHERE variant IN ('P1', 'P2') GROUP BY ALL")


def _state(s, d):
    """Bytes that each estimate holds: the sampled URIs, the bits of the filters."""
    rows = [dereference.sample(_PAGES(s, d), g, k).agg(F.sum(F.octet_length("uri")).alias("bytes")).select(F.lit("dereferenceability").alias("metric"), F.lit(f"P{n}").alias("variant"), "bytes") for n, (g, k) in enumerate(((10, 1000), (50, 100), (50, 10000), (100, 1000)), 1)]
    rows.append(s.createDataFrame([("conciseness", f"P{n}", m // 8) for n, (_, m) in enumerate(SETTINGS, 1)], "metric string, variant string, bytes long"))
    return reduce(DataFrame.unionByName, rows)


add("state_bytes", _state, " UNION ALL ".join([f"SELECT 'dereferenceability' AS metric, 'P{n}' AS variant, sum(octet_length(encode(uri)))::BIGINT AS bytes FROM ({_two_level_sql(g, k)})" for n, (g, k) in enumerate(((10, 1000), (50, 100), (50, 10000), (100, 1000)), 1)] + [f"SELECT 'conciseness', 'P{n}', {m // 8}::BIGINT" for n, (_, m) in enumerate(SETTINGS, 1)]))


def _ladder(s, d):
    from .experiments import ladder

    return ladder(s, d).select("dataset", "metric", "variant", "value", "exact", "seconds")


add("size_ladder_runtime", _ladder)
add("quality_grid", lambda s, d: framework.pivot(_observed(s, d), ["orders", "documents", "part", "events"]), "SELECT metric, variant, " + ", ".join(f"max(value) FILTER (WHERE dataset = '{v}') AS {v}" for v in ("orders", "documents", "part", "events")) + f" FROM ({_observed_sql()}) GROUP BY metric, variant")
add("observations_as_triples", lambda s, d: framework.as_triples(_observed(s, d)), f"""WITH o AS ({_observed_sql()}), n AS (SELECT *, '_:' || md5(dataset || '|' || metric || '|' || variant) AS s FROM o)
SELECT s, 'https://quality.example.org/dataset' AS p, 'https://quality.example.org/' || dataset AS o, 'uri' AS o_kind, NULL::VARCHAR AS o_datatype FROM n UNION ALL SELECT s, 'https://quality.example.org/metric', 'https://quality.example.org/' || metric, 'uri', NULL FROM n
UNION ALL SELECT s, 'https://quality.example.org/variant', variant, 'literal', 'string' FROM n UNION ALL SELECT s, 'https://quality.example.org/value', round(value, 6)::DECIMAL(18, 6)::VARCHAR, 'literal', 'decimal' FROM n""")
add("quality_cube", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("quality").alias("good"), F.count_if(F.col("toxic") == 1).alias("toxic")), "SELECT lang, source, count(*) AS n, sum(quality)::BIGINT AS good, count_if(toxic = 1)::BIGINT AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (lang, source)")
add("quality_rollup", lambda s, d: table(s, d, "documents").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n")), "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")


def _assessed(s, d):
    got = framework.assess(s, "customer", mappings.triples(s, d, "customer"), ["external_links", "conciseness", "slash_uris", "syntactic_accuracy", "intensional_conciseness"])
    return got.select("dataset", "metric", "variant", "numer", "denom", F.round("value", 9).alias("value"), "exact")


add("assess_customer", _assessed)
add("quality_rules", lambda s, d: relational.quality_rules(table(s, d, "orders"), ["o_orderkey"], {"o_totalprice": (0.0, 400000.0)}), "SELECT count(*) AS n_rows, count(DISTINCT o_orderkey) AS n_keys, " + ", ".join(f"count_if({c} IS NULL)::BIGINT AS null_{c}" for c in ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")) + ", count_if(o_totalprice < 0 OR o_totalprice > 400000)::BIGINT AS out_o_totalprice FROM orders")
add("foreign_keys", lambda s, d: relational.orphans(table(s, d, "lineitem"), "l_orderkey", table(s, d, "orders"), "o_orderkey"), "SELECT count(*) AS orphans FROM lineitem ANTI JOIN orders ON l_orderkey = o_orderkey")

# -- operators around the metrics ---------------------------------------------------------------------------

add("events_tumbling", lambda s, d: streams.tumbling(table(s, d, "events")).withColumn("total", F.round("total", 4)), "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
add("events_sliding", lambda s, d: streams.sliding(table(s, d, "events")), "SELECT start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY start")
add("events_session", lambda s, d: streams.sessions(table(s, d, "events")), 'SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", count(*) AS n FROM (SELECT *, sum(o) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT *, coalesce((ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE)::INT, 1) AS o FROM events)) GROUP BY user_id, k')
_CLICKS = "SELECT user_id, ts, max(value) AS value FROM events WHERE event_type <> (SELECT min(event_type) FROM events) GROUP BY user_id, ts"


def _asof(s, d):
    e = table(s, d, "events")
    first = e.agg(F.min("event_type").alias("m"))
    left = e.join(F.broadcast(first), F.col("event_type") == F.col("m")).select("event_id", "user_id", "ts")
    right = e.join(F.broadcast(first), F.col("event_type") != F.col("m")).groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return relational.as_of(left, right, "user_id", "ts", "value")


add("events_asof", _asof, f"SELECT l.event_id, l.user_id, l.ts, r.value AS last_value FROM (SELECT * FROM events WHERE event_type = (SELECT min(event_type) FROM events)) l ASOF LEFT JOIN ({_CLICKS}) r ON l.user_id = r.user_id AND l.ts >= r.ts")
add("events_within_10m", lambda s, d: (lambda e: streams.within(e, e, "user_id", 10))(table(s, d, "events").select("user_id", "ts", "event_id")), "SELECT a.event_id AS id, b.event_id AS id2 FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
add("events_late", lambda s, d: streams.late(table(s, d, "events")).withColumn("seen", F.max("ts").over(Window.partitionBy("event_type").orderBy("arrival", "event_id"))).agg(F.count_if(F.col("ts") < F.col("seen") - F.expr("INTERVAL 1 HOURS")).alias("late"), F.count(F.lit(1)).alias("n")), "SELECT count_if(ts < seen - INTERVAL 1 HOUR)::BIGINT AS late, count(*) AS n FROM (SELECT ts, max(ts) OVER (PARTITION BY event_type ORDER BY CASE WHEN event_id % 50 = 0 THEN ts + INTERVAL 2 HOUR ELSE ts END, event_id) AS seen FROM events)")
add("value_bands", lambda s, d: relational.bands(table(s, d, "part"), "p_retailprice", s.createDataFrame([(float(i * 250), float(i * 250 + 250)) for i in range(12)], "lo double, hi double")).groupBy("lo").agg(F.count(F.lit(1)).alias("n")), "SELECT lo, count(*) AS n FROM part JOIN (SELECT i * 250.0::DOUBLE AS lo FROM range(12) t(i)) ON p_retailprice >= lo AND p_retailprice < lo + 250 GROUP BY lo")
add("range_join", lambda s, d: relational.range_join(table(s, d, "customer").select("c_custkey", "c_acctbal"), table(s, d, "supplier").select("s_suppkey", F.col("s_acctbal").alias("lo"), (F.col("s_acctbal") + 5).alias("hi")), "c_acctbal", "lo", "hi", 50.0).select("c_custkey", "s_suppkey"), "SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON c_acctbal >= s_acctbal AND c_acctbal < s_acctbal + 5")
_GRID = lambda s, d: table(s, d, "lineitem").select(F.col("l_linenumber").alias("g")).distinct().crossJoin(table(s, d, "orders").select(F.year("o_orderdate").alias("k")).distinct())
add("param_grid", _GRID, "SELECT g, k::INT AS k FROM (SELECT DISTINCT l_linenumber AS g FROM lineitem), (SELECT DISTINCT year(o_orderdate) AS k FROM orders)")
_CH, _SH = (f"SELECT DISTINCT regexp_extract(s, '^(https://[^/]*)', 1) AS h FROM ({T(v)})" for v in ("customer", "supplier"))
_HOSTS = lambda s, d, v: mappings.triples(s, d, v).select(F.regexp_extract("s", "^(https://[^/]*)", 1).alias("h")).distinct()
add("hosts_union", lambda s, d: _HOSTS(s, d, "customer").union(_HOSTS(s, d, "supplier")).distinct(), f"{_CH} UNION {_SH}")
add("hosts_intersect", lambda s, d: _HOSTS(s, d, "customer").intersect(_HOSTS(s, d, "supplier")), f"{_CH} INTERSECT {_SH}")
add("hosts_except", lambda s, d: _HOSTS(s, d, "customer").exceptAll(_HOSTS(s, d, "supplier")), f"{_CH} EXCEPT ALL {_SH}")
add("documents_in_benchmark", lambda s, d: mappings.triples(s, d, "documents", ("digest",)).join(mappings.triples(s, d, "benchmark").select("o"), "o", "left_semi").select("s"), f"SELECT s FROM ({T('documents', ('digest',))}) WHERE o IN (SELECT o FROM ({T('benchmark')}))")


def _ranks(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    b = Window.partitionBy("c_nationkey").orderBy(F.desc(F.floor(F.col("c_acctbal") / 1000)))
    run = w.rowsBetween(-2, 0)
    return table(s, d, "customer").select("c_custkey", F.row_number().over(w).alias("r"), F.rank().over(b).alias("rk"), F.dense_rank().over(b).alias("dr"), F.ntile(4).over(w).alias("q"), F.lag("c_custkey").over(w).alias("prev"), F.lead("c_custkey").over(w).alias("next"), F.first("c_custkey").over(w).alias("top"), F.round(F.avg("c_acctbal").over(run), 4).alias("avg3"), F.round(F.percent_rank().over(b), 6).alias("pr"))


add("ranking", _ranks, "SELECT c_custkey, row_number() OVER w AS r, rank() OVER b AS rk, dense_rank() OVER b AS dr, ntile(4) OVER w AS q, lag(c_custkey) OVER w AS prev, lead(c_custkey) OVER w AS next, first(c_custkey) OVER w AS top, round(avg(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS avg3, round(percent_rank() OVER b, 6) AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey), b AS (PARTITION BY c_nationkey ORDER BY floor(c_acctbal / 1000) DESC)")
add("json_props", lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")), "SELECT event_id, json_extract_string(props, '$.k')::INT AS k FROM events")
add("sketches", lambda s, d: table(s, d, "events").agg(F.approx_count_distinct("user_id", 0.01).alias("users_hll"), F.expr("hll_sketch_estimate(hll_sketch_agg(user_id))").alias("users_hll2"), F.expr("theta_sketch_estimate(theta_sketch_agg(user_id))").alias("users_theta"), F.percentile_approx("value", [0.5, 0.9]).alias("quantiles"), F.expr("approx_top_k(event_type, 3)").alias("top")))
add("scan_parquet", lambda s, d: table(s, d, "lineitem").where("l_quantity > 45").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")), "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity > 45 GROUP BY 1")
add("size_ladder", lambda s, d: mappings.triples(s, d, "lineitem").groupBy("o_kind").agg(F.count(F.lit(1)).alias("n")), f"SELECT o_kind, count(*) AS n FROM ({T('lineitem')}) GROUP BY 1")


# -- functions for SQL users, and joins that are not above ---------------------------------------------------


def _sql(text: str):
    def run(s, d):
        udfs.register(s)
        views = {n: table(s, d, n) for n in ("customer", "orders", "events", "nation") if f"{{{n}}}" in text}
        return s.sql(text, **views)

    return run


add("udf_murmur", _sql("SELECT c_custkey, h.h1, h.h2 FROM (SELECT c_custkey, murmur3_128(c_name) AS h FROM {customer})"))
add("udaf_reservoir", _sql("SELECT event_type, array_join(reservoir_agg(cast(user_id AS string)), ',') AS users FROM {events} GROUP BY event_type"), "SELECT event_type, string_agg(u, ',' ORDER BY r) AS users FROM (SELECT event_type, u, row_number() OVER (PARTITION BY event_type ORDER BY md5('0|' || u), u) AS r FROM (SELECT DISTINCT event_type, user_id::VARCHAR AS u FROM events)) WHERE r <= 16 GROUP BY event_type")
add("udtf_ntriples", _sql("SELECT t.* FROM (SELECT concat('<https://n/', n_nationkey, '> <name> \"', n_name, '\" .') AS line FROM {nation}) x, LATERAL ntriples_parse(x.line) t"), "SELECT 'https://n/' || n_nationkey AS s, 'name' AS p, n_name AS o, 'literal' AS o_kind FROM nation")
add("udtf_walk", _sql("SELECT w.* FROM walk_steps(TABLE(SELECT concat('n', n_nationkey) AS src, concat('r', n_regionkey) AS dst FROM {nation}) WITH SINGLE PARTITION, 200, 1) w"))
add("lateral_last_orders", _sql("SELECT c_custkey, o.o_orderkey FROM (SELECT DISTINCT c_custkey FROM {customer}) c, LATERAL (SELECT o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey NULLS LAST) AS r FROM {orders}) WHERE o_custkey = c_custkey AND r <= 2) o"), "SELECT c_custkey, o_orderkey FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders SEMI JOIN customer ON o_custkey = c_custkey) WHERE r <= 2")
add("full_join_keys", lambda s, d: table(s, d, "labels").select(F.col("doc_id").alias("a")).join(table(s, d, "pages").select(F.col("page_id").alias("b")), F.col("a") == F.col("b"), "full"), "SELECT doc_id AS a, page_id AS b FROM labels FULL JOIN pages ON doc_id = page_id")
add("shuffle_hash_join", lambda s, d: table(s, d, "orders").join(table(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
add("cosine_to_first", lambda s, d: (lambda e: e.crossJoin(F.broadcast(e.orderBy("vec_id").limit(1).select(F.col("v").alias("u")))).select("vec_id", F.round(F.aggregate(F.zip_with("v", "u", lambda a, b: a * b), F.lit(0.0), lambda x, y: x + y), 6).alias("c")))(table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))), "SELECT vec_id, round(list_inner_product(embedding::DOUBLE[], (SELECT embedding::DOUBLE[] FROM embeddings ORDER BY vec_id LIMIT 1)), 6) AS c FROM embeddings")
