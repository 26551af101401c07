"""N-Triples lines to and from triples, with native functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_LINE = r'^\s*(<[^>]*>|_:\S+)\s+<([^>]*)>\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"(?:@[A-Za-z0-9-]+|\^\^<[^>]*>)?)\s*\.\s*(?:#.*)?$'


def _plain(text: Column) -> Column:
    return F.when(text.startswith("<"), F.regexp_replace(text, "^<|>$", "")).otherwise(text)


def _escape(text: Column) -> Column:
    for a, b in (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t")):
        text = F.replace(text, F.lit(a), F.lit(b))
    return text


def _unescape(text: Column) -> Column:
    mark = "\x00"  # holds escaped backslashes while the others are replaced
    text = F.replace(text, F.lit("\\\\"), F.lit(mark))
    for a, b in (('\\"', '"'), ("\\n", "\n"), ("\\r", "\r"), ("\\t", "\t")):
        text = F.replace(text, F.lit(a), F.lit(b))
    return F.replace(text, F.lit(mark), F.lit("\\"))


def parse(lines: DataFrame, column: str = "value") -> DataFrame:
    """s, s_kind, p, o, o_kind, o_datatype, o_lang; lines that are no triple are dropped."""
    line = F.col(column)
    got = lines.where(line.rlike(_LINE)).select(*[F.regexp_extract(line, _LINE, i).alias(n) for i, n in ((1, "a"), (2, "p"), (3, "b"))])
    literal = F.col("b").startswith('"')
    return got.select(
        _plain(F.col("a")).alias("s"),
        F.when(F.col("a").startswith("<"), "uri").otherwise("bnode").alias("s_kind"),
        "p",
        F.when(literal, _unescape(F.regexp_extract("b", r'^"((?:[^"\\]|\\.)*)"', 1))).otherwise(_plain(F.col("b"))).alias("o"),
        F.when(literal, "literal").when(F.col("b").startswith("<"), "uri").otherwise("bnode").alias("o_kind"),
        F.when(literal & F.col("b").rlike(r"\^\^<[^>]*>$"), F.regexp_extract("b", r"\^\^<([^>]*)>$", 1)).alias("o_datatype"),
        F.when(literal & F.col("b").rlike(r'"@[A-Za-z0-9-]+$'), F.regexp_extract("b", r'"@([A-Za-z0-9-]+)$', 1)).alias("o_lang"),
    )


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    return parse(spark.read.text(path))


def lines(triples: DataFrame) -> DataFrame:
    """One line of text (column value) for each triple."""
    term = F.when(F.col("o_kind") == "uri", F.concat(F.lit("<"), "o", F.lit(">"))).when(F.col("o_kind") == "bnode", F.col("o")).otherwise(F.concat(F.lit('"'), _escape(F.col("o")), F.lit('"'), F.when(F.col("o_datatype").isNotNull(), F.concat(F.lit("^^<"), "o_datatype", F.lit(">"))).otherwise("")))
    subject = F.when(F.col("s").startswith("_:"), F.col("s")).otherwise(F.concat(F.lit("<"), "s", F.lit(">")))
    return triples.select(F.concat(subject, F.lit(" <"), "p", F.lit("> "), term, F.lit(" .")).alias("value"))


def write_ntriples(triples: DataFrame, path: str) -> None:
    lines(triples).write.text(path)
