"""URIs by native string functions: parts, owner domain, resolution of references."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Registries below which an owner has one label; anything else: the last two labels.
SUFFIXES = ("example.com", "example.net", "example.org")


def scheme(uri: Column) -> Column:
    return F.lower(F.regexp_extract(uri, r"^([A-Za-z][A-Za-z0-9+.-]*):", 1))


def host(uri: Column) -> Column:
    return F.lower(F.regexp_extract(uri, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))


def path(uri: Column) -> Column:
    return F.regexp_extract(uri, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)", 1)


def fragment(uri: Column) -> Column:
    """What follows #; null without."""
    return F.when(F.instr(uri, "#") > 0, F.regexp_extract(uri, r"#(.*)$", 1))


def owner(uri: Column, suffixes: tuple[str, ...] = SUFFIXES) -> Column:
    """The pay-level domain of a URI with a host; an empty string without one."""
    return owner_of_host(host(uri), suffixes)


def owner_of_host(name: Column, suffixes: tuple[str, ...] = SUFFIXES) -> Column:
    rules = "|".join(s.replace(".", r"\.") for s in suffixes)
    below = F.regexp_extract(name, rf"([^.]+\.(?:{rules}))$", 1)
    return F.when(below != "", below).otherwise(F.regexp_extract(name, r"([^.]+\.[^.]+)$", 1))


def resolve(base: Column, ref: Column) -> Column:
    """A reference against the page that holds it: absolute, root-relative, or a fragment of it."""
    origin = F.regexp_extract(base, r"^([A-Za-z][A-Za-z0-9+.-]*://[^/?#]*)", 1)
    folder = F.regexp_extract(base, r"^([A-Za-z][A-Za-z0-9+.-]*://[^?#]*/)", 1)
    return F.when(ref.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), ref).when(ref.startswith("#"), F.concat(F.regexp_extract(base, r"^([^#]*)", 1), ref)).when(ref.startswith("/"), F.concat(origin, ref)).otherwise(F.concat(F.when(folder != "", folder).otherwise(F.concat(origin, F.lit("/"))), ref))


def parts(df, column: str = "uri"):
    u = F.col(column)
    return df.select(u.alias("uri"), scheme(u).alias("scheme"), host(u).alias("host"), owner(u).alias("pld"), path(u).alias("path"), fragment(u).alias("ref"))
