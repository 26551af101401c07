"""The given tables as triples. A mapping is data: subject, and predicate, object, kind and datatype of each column.

Objects are SQL expressions that hold in Spark and in DuckDB, so the same mapping makes the plan and its twin.
Expansion is narrow: one explode, no shuffle (a join only where the subject's host is in another table).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import table

VOCAB = "https://schema.example.org/"


def money(c: str) -> str:
    return f"cast(cast({c} as decimal(18, 2)) as string)"


def text(c: str) -> str:
    return f"cast({c} as string)"


def cls(name: str) -> tuple[str, str, str, str | None]:
    return ("type", f"'{VOCAB}{name}'", "uri", None)


ITEM = "md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, {q}, {e}, {d}, {t}, l_returnflag, l_linestatus, cast(cast(l_shipdate as date) as string)))".format(q=money("l_quantity"), e=money("l_extendedprice"), d=money("l_discount"), t=money("l_tax"))

#: view: tables (the first joined with the second on the condition), subject, [(predicate, object, kind, datatype)]
VIEWS: dict[str, tuple[tuple[str, ...], str, list[tuple[str, str, str, str | None]]]] = {
    "customer": (("customer",), "concat('https://n', c_nationkey, '.example.org/customer/', c_custkey)", [cls("Customer"), ("name", "c_name", "literal", "string"), ("segment", "c_mktsegment", "literal", "string"), ("balance", money("c_acctbal"), "literal", "decimal"), ("nation", "concat('https://geo.example.org/nation/', c_nationkey)", "uri", None)]),
    "supplier": (("supplier",), "concat('https://n', s_nationkey, '.example.org/supplier/', s_suppkey)", [cls("Supplier"), ("name", "s_name", "literal", "string"), ("balance", money("s_acctbal"), "literal", "decimal"), ("nation", "concat('https://geo.example.org/nation/', s_nationkey)", "uri", None)]),
    "part": (("part",), "concat('https://parts.example.com/part/', p_partkey)", [cls("Part"), ("brand", "p_brand", "literal", "string"), ("kind", "p_type", "literal", "string"), ("size", text("p_size"), "literal", "integer")]),
    "orders": (("orders", "customer", "o_custkey = c_custkey"), "concat('https://sales.example.net/order/', o_orderkey)", [cls("Order"), ("customer", "concat('https://n', c_nationkey, '.example.org/customer/', c_custkey)", "uri", None), ("status", "o_orderstatus", "literal", "string"), ("priority", "o_orderpriority", "literal", "string"), ("date", "cast(cast(o_orderdate as date) as string)", "literal", "date"), ("total", money("o_totalprice"), "literal", "decimal")]),
    "lineitem": (("lineitem", "supplier", "l_suppkey = s_suppkey"), f"concat('https://sales.example.net/item/', {ITEM})", [("order", "concat('https://sales.example.net/order/', l_orderkey)", "uri", None), ("part", "concat('https://parts.example.com/part/', l_partkey)", "uri", None), ("supplier", "concat('https://n', s_nationkey, '.example.org/supplier/', s_suppkey)", "uri", None), ("quantity", money("l_quantity"), "literal", "decimal"), ("discount", money("l_discount"), "literal", "decimal"), ("tax", money("l_tax"), "literal", "decimal"), ("flag", "l_returnflag", "literal", "string"), ("status", "l_linestatus", "literal", "string")]),
    "geo": (("nation",), "concat('https://geo.example.org/nation/', n_nationkey)", [cls("Nation"), ("name", "n_name", "literal", "string"), ("region", "concat('https://geo.example.org/region/', n_regionkey)", "uri", None)]),
    "pages": (("pages",), "url", [cls("Page"), ("language", "regexp_extract(html, 'lang=\"([a-z]+)\"', 1)", "literal", "string"), ("title", "regexp_extract(html, '<title>([^<]*)</title>', 1)", "literal", "string")]),
    "documents": (("documents", "labels", "doc_id = label_id"), "concat('https://', source, '.example.org/doc/', doc_id)", [("digest", "md5(text)", "literal", "string"), ("language", "lang", "literal", "string"), ("length", text("n_chars"), "literal", "integer"), ("quality", text("quality"), "literal", "integer"), ("toxic", text("toxic"), "literal", "integer")]),
    "events": (("events",), "concat('urn:event:', event_id)", [("user", "concat('urn:user:', user_id)", "uri", None), ("kind", "event_type", "literal", "string"), ("value", money("value"), "literal", "decimal"), ("props", "props", "literal", "json")]),
    "conversations": (("conversations",), "concat('urn:conv:', conv_id, ':', turn)", [("role", "role", "literal", "string"), ("digest", "md5(text)", "literal", "string"), ("next", "concat('urn:conv:', conv_id, ':', turn + 1)", "uri", None)]),
    "benchmark": (("benchmark",), "concat('urn:bench:', item_id)", [("digest", "md5(text)", "literal", "string")]),
}


def source(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    names, _, _ = VIEWS[view]
    base = table(spark, sf_dir, names[0])
    if len(names) == 1:
        return base
    if names[1] == "labels":
        return base.join(table(spark, sf_dir, "labels").select(F.col("doc_id").alias("label_id"), "quality", "toxic"), F.expr(names[2]), "left")
    return base.join(table(spark, sf_dir, names[1]), F.expr(names[2]))


def triples(spark: SparkSession, sf_dir: str, view: str, predicates: tuple[str, ...] = (), kind: str | None = None, early: bool = False, row: tuple[str, ...] = ()) -> DataFrame:
    """s, p, o, o_kind, o_datatype of a view (only these predicates or this kind of objects, if given; columns that
    aren't needed aren't read). ``early``: subjects are made once a row, for plans that use them in each triple; else
    where they are used. ``row``: columns that tell the rows apart; their hash is added as ``rid``, a name of the row
    that costs less than its subject."""
    _, subject, columns = VIEWS[view]
    each = [F.struct(F.lit(p).alias("p"), F.expr(o).cast("string").alias("o"), F.lit(k).alias("o_kind"), F.lit(d).cast("string").alias("o_datatype")) for p, o, k, d in columns if (not predicates or p in predicates) and kind in (None, k)]
    base = source(spark, sf_dir, view)
    names = [F.expr(subject).alias("s")] + ([F.xxhash64(*row).alias("rid")] if row else [])
    whole = base.select(*names, F.array(*each).alias("ts")).select("*", F.explode("ts").alias("t")).drop("ts") if early else base.select(*names, F.explode(F.array(*each)).alias("t"))
    out = whole.select("*", "t.*").drop("t").where("o is not null")
    return out.unionByName(page_links(spark, sf_dir)) if view == "pages" and (not predicates or "link" in predicates) else out


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A triple for each reference of a page, resolved against it."""
    from ..functions.uris import resolve

    refs = table(spark, sf_dir, "pages").select(F.col("url").alias("s"), F.explode(F.expr("""regexp_extract_all(html, 'href="([^"]*)"', 1)""")).alias("ref"))
    return refs.select("s", F.lit("link").alias("p"), resolve(F.col("s"), F.col("ref")).alias("o"), F.lit("uri").alias("o_kind"), F.lit(None).cast("string").alias("o_datatype"))


def triples_sql(view: str, predicates: tuple[str, ...] = ()) -> str:
    """The same rows in DuckDB."""
    names, subject, columns = VIEWS[view]
    origin = {1: names[0]}.get(len(names)) or (f"{names[0]} LEFT JOIN (SELECT doc_id AS label_id, quality, toxic FROM labels) ON {names[2]}" if names[1] == "labels" else f"{names[0]} JOIN {names[1]} ON {names[2]}")
    each = [f"SELECT {subject} AS s, '{p}' AS p, {o} AS o, '{k}' AS o_kind, {repr(d) if d else 'NULL'}::VARCHAR AS o_datatype FROM {origin} WHERE {o} IS NOT NULL" for p, o, k, d in columns if not predicates or p in predicates]
    if view == "pages" and (not predicates or "link" in predicates):
        each.append(LINKS_SQL)
    return " UNION ALL ".join(each)


LINKS_SQL = """SELECT s, 'link' AS p, CASE WHEN regexp_matches(ref, '^[A-Za-z][A-Za-z0-9+.-]*:') THEN ref WHEN ref LIKE '#%' THEN regexp_extract(s, '^([^#]*)', 1) || ref WHEN ref LIKE '/%' THEN regexp_extract(s, '^([A-Za-z][A-Za-z0-9+.-]*://[^/?#]*)', 1) || ref ELSE regexp_extract(s, '^([A-Za-z][A-Za-z0-9+.-]*://[^?#]*/)', 1) || ref END AS o, 'uri' AS o_kind, NULL::VARCHAR AS o_datatype
FROM (SELECT url AS s, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS ref FROM pages)"""


def declaration(spark: SparkSession) -> DataFrame:
    """The triple by which a data set names itself."""
    return spark.createDataFrame([("https://sales.example.net/", "type", f"{VOCAB}Dataset", "uri", None)], "s string, p string, o string, o_kind string, o_datatype string")
