"""What a fetch of each URI gives: an offline snapshot, a function of the URI's digest.

The owner may be dead (every request fails); else a URI redirects to a document (303), is one (200, RDF), is a
web page (200, HTML), fails (404, 500), loops, or answers something malformed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.keys import number, random_key
from ..functions.uris import owner

#: Upper ends of the shares of 100, in order.
SHARES = (("303", 25), ("200-rdf", 55), ("200-html", 75), ("404", 90), ("500", 95), ("loop", 98), ("malformed", 100))
DEAD = 10  # one owner in so many


def outcome(uri: Column, all_dead: bool = False) -> Column:
    draw = F.pmod(number(random_key("uri", uri)), F.lit(100))
    alive = F
    for k, (name, end) in enumerate(SHARES):
        alive = F.when(draw < end, name) if k == 0 else alive.when(draw < end, name)
    return F.when(F.lit(all_dead) | (F.pmod(number(random_key("dead", owner(uri))), F.lit(DEAD)) == 0), "503").otherwise(alive)


def snapshot(uris: DataFrame, all_dead: bool = False) -> DataFrame:
    """RESPONSE rows of distinct URIs: uri, status, location, media, hops."""
    kind = outcome(F.col("uri"), all_dead)
    out = uris.select("uri").distinct().withColumn("kind", kind)
    status = F.when(F.col("kind").isin("200-rdf", "200-html"), 200).when(F.col("kind") == "loop", 301).when(F.col("kind") == "malformed", 0).otherwise(F.col("kind").cast("int"))
    target = F.concat(F.regexp_extract("uri", "^([^#]*)", 1), F.lit(".rdf"))
    location = F.when(F.col("kind") == "303", target).when(F.col("kind") == "loop", F.col("uri"))
    media = F.when(F.col("kind").isin("303", "200-rdf"), "application/rdf+xml").when(F.col("kind") == "200-html", "text/html")
    hop = lambda s, u: F.struct(F.lit(s).alias("status"), u.alias("uri"))
    hops = F.when(F.col("kind") == "303", F.array(hop(303, F.col("uri")), hop(200, target))).when(F.col("kind") == "loop", F.array(*[hop(301, F.col("uri"))] * 3)).otherwise(F.array(F.struct(status.alias("status"), F.col("uri").alias("uri"))))
    return out.select("uri", status.alias("status"), location.alias("location"), media.alias("media"), hops.alias("hops"))


def outcome_sql(uri: str, pld: str, all_dead: bool = False) -> str:
    draw = f"(('0x' || substr(md5('uri|' || {uri}), 1, 8))::BIGINT % 100)"
    dead = "true" if all_dead else f"('0x' || substr(md5('dead|' || {pld}), 1, 8))::BIGINT % {DEAD} = 0"
    return f"CASE WHEN {dead} THEN '503' " + " ".join(f"WHEN {draw} < {end} THEN '{name}'" for name, end in SHARES) + " END"
