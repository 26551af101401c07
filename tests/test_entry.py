"""Every registered query of the metric engine against its DuckDB twin, on the smallest tables."""

import math

import duckdb
import pytest

import __spark_entry__ as entry
from approxdq import queries as metrics

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else f"{v:.7g}"
    return str(v)


def rows(names, data):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple(plain(r[i]) for i in order) for r in data)


@pytest.fixture(scope="module")
def db(sf_dir):
    c = duckdb.connect()
    c.sql("set timezone = 'UTC'")
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(metrics.QUERIES))
def test_query(spark, sf_dir, db, name):
    df = metrics.QUERIES[name](spark, sf_dir)
    got = rows(df.columns, df.collect())
    if name in metrics.ORACLES:
        want = db.execute(metrics.ORACLES[name])
        assert sorted(df.columns) == sorted(d[0] for d in want.description)
        assert got == rows([d[0] for d in want.description], want.fetchall())
    else:
        assert got


def test_entry(spark):
    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries()) and set(metrics.QUERIES) <= set(entry.queries())
