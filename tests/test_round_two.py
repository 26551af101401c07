"""Findings of the second round: each of these failed before."""

import time

import numpy as np
import pandas as pd

from approxdq import queries
from approxdq.operators import bloom, catalog, clustering, conciseness
from approxdq.plans import graphs


def test_lateral_orders_hold_over_partitions(spark, tmp_path):
    rng = np.random.default_rng(1)
    n = 20_000
    orders = pd.DataFrame({"o_orderkey": np.arange(n), "o_custkey": rng.integers(0, 500, n), "o_totalprice": rng.random(n).round(3)})
    orders.to_parquet(tmp_path / "orders.parquet")
    pd.DataFrame({"c_custkey": np.append(np.arange(0, 1000), 7)}).to_parquet(tmp_path / "customer.parquet")
    best = orders.sort_values(["o_totalprice", "o_orderkey"], ascending=[False, True]).groupby("o_custkey").head(2)
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        got = queries.QUERIES["lateral_last_orders"](spark, str(tmp_path)).collect()
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    assert sorted((r.c_custkey, r.o_orderkey) for r in got) == sorted(zip(best["o_custkey"].tolist(), best["o_orderkey"].tolist(), strict=True))


def test_full_filters_do_not_merge_extensions(spark):
    rows = [(f"s{i}", p, f"{p[0]}{i}") for i in range(2000) for p in ("alpha", "beta")] + [(f"s{i}", "also", f"a{i}") for i in range(2000)]
    t = spark.createDataFrame(rows, "s string, p string, o string")
    assert catalog.intensional_conciseness(t, bits=256).first().asDict() == catalog.intensional_conciseness(t).first().asDict() == {"numer": 2, "denom": 3, "value": 2 / 3}


def test_plain_filter_sends_no_bits_to_the_driver(spark):
    """Joins of the replay are merged, and a repeated seq is one element as before."""
    rows = spark.createDataFrame([(i, f"{i % 40:032x}") for i in range(100)], "seq long, sig string")
    flags = bloom.flag_classic(rows, 2, 1 << 12)
    assert "BroadcastHashJoin" not in flags._jdf.queryExecution().executedPlan().toString()
    assert {r.seq: r.is_dup for r in flags.collect()} == {i: i >= 40 for i in range(100)}


def test_grid_comes_from_given_tables(spark, sf_dir):
    df = queries.QUERIES["param_grid"](spark, sf_dir)
    assert {f.rsplit("/", 1)[-1] for f in df.inputFiles()} == {"lineitem.parquet", "orders.parquet"} and df.count() > 1


def test_walk_by_look_ups_equals_walk_by_lists(spark, monkeypatch):
    """Also where the drawn neighbour of a hub is looked up by its number."""
    monkeypatch.setattr(clustering.Files, "FEW", 2)
    pairs = spark.createDataFrame([("h", f"v{i}") for i in range(12)] + [(f"v{i}", f"v{i + 1}") for i in range(11)], "a string, b string")
    edges = graphs.undirected(pairs)
    few, many = ({(r.walker, r.step): r for r in clustering.walk(edges, seed=3, walkers=2, steps=12, most_edges=m).collect()} for m in (10**6, 0))
    assert few == many and len(few) == 12


def test_quotient_filter_is_made_once_a_shard(spark):
    """Slots for 64 million hashes a shard: made for each row, they took minutes."""
    rows = spark.createDataFrame([(i, f"{i % 700:032x}") for i in range(1000)], "seq long, sig string")
    start = time.perf_counter()
    assert {r.seq: r.is_dup for r in bloom.flag_quotient(rows, 26, 10, shards=1).collect()} == {i: i >= 700 for i in range(1000)}
    assert time.perf_counter() - start < 60


def test_pairwise_sends_blocks_and_not_instances(spark):
    """A baseline of some sixty thousand instances: a row for each two blocks, and each instance once; a repeated seq is two instances."""
    rows = spark.range(60_000).selectExpr("cast(id / 2 as long) as seq", "md5(cast(id % 45000 as string)) as sig")
    start = time.perf_counter()
    assert conciseness.pairwise(rows, 8192).first().asDict() == {"numer": 45_000, "denom": 60_000, "value": 0.75}
    assert time.perf_counter() - start < 120
    assert conciseness.pairwise(rows.limit(0)).first().value == 1.0


def test_seen_elements_draw_no_numbers():
    """Flags and state equal those of elements added one by one; with room in the filter, numbers are drawn for few."""
    sig, seq = [f"s{i * i % 997 % 150}" for i in range(4000)], list(range(4000))
    for policy in ("balanced", "reservoir", "biased", "biased_single", "none"):
        for bits, few in ((400, False), (40_000, True)):
            one, all_, drawn = bloom.ResettingFilter(4, bits, policy), bloom.ResettingFilter(4, bits, policy), []
            want = [one.add(*x) for x in zip(*bloom.draws(sig, seq, 4, bits // 4, 0), strict=True)]
            got = []
            for i in range(0, 4000, 500):
                def random(r, i=i):
                    drawn.extend(r)
                    return bloom.chances([sig[i + x] for x in r], [seq[i + x] for x in r], 4, bits // 4, 0)
                got += all_.add_all(bloom.places(sig[i : i + 500], 4, bits // 4, 0), random)
            assert got == want and all_.state() == one.state() and (len(drawn) < 1500 or not few)


def test_triangles_by_colours_equal_joins(spark, monkeypatch):
    """Vertices, degrees, triangles and coefficients of numbered edges, in one task and in many; repeats, loops, nulls and the
    largest numbers do no harm, and no units are left. Hubs and two cliques give triangles of one, two and three colours."""
    from approxdq.operators import coloured

    rng = np.random.default_rng(3)
    pairs = rng.integers(0, 40, (260, 2)).tolist() + [(None, 3), (5, None), (6, 6), (7, -(2**63)), (2**63 - 1, 7), (-(2**63), 2**63 - 1)] + [(100, i) for i in range(40)] + [(i, j) for i in range(200, 206) for j in range(200, 206)]
    rows = spark.createDataFrame(pairs, "src long, dst long")
    named = graphs.undirected(rows.select(rows.src.cast("string"), rows.dst.cast("string")))
    want = clustering.exact(named).first(), clustering.exact_global(named).first(), clustering.triangles(named).count()
    for held in (10_000, 250):
        monkeypatch.setattr(coloured, "HELD", held)
        units = coloured.Units(rows)
        assert (units.colours > 2) == (held < 300)
        units.drop()
        got = clustering.exact(rows).first()
        assert got.vertices == want[0].vertices and abs(got.value - want[0].value) < 1e-12
    none = clustering.exact(rows.limit(0)).first()
    assert none.vertices == 0 and none.value is None


def test_exact_clustering_writes_no_names(spark, sf_dir, monkeypatch):
    """The commerce graph as it is read, in many tasks: no edge by name is written."""
    from approxdq.operators import coloured

    want = queries.clustering.exact(graphs.commerce(spark, sf_dir)).first()
    monkeypatch.setattr(coloured, "HELD", 8000)
    monkeypatch.setattr(queries, "cut", None)
    got = queries.QUERIES["clustering_exact_commerce"](spark, sf_dir).first()
    assert got.vertices == want.vertices and got.value == round(want.value, 9)


def test_keys_too_large_to_number(spark, tmp_path):
    """The graph by name takes their place."""
    n = 1 << 59
    pd.DataFrame({"l_orderkey": [n, n, 1], "l_partkey": [-n, 2, 2], "l_suppkey": [3, 3, 3]}).to_parquet(tmp_path / "lineitem.parquet")
    for name, columns in (("orders", ("o_orderkey", "o_custkey")), ("customer", ("c_custkey", "c_nationkey")), ("supplier", ("s_suppkey", "s_nationkey")), ("nation", ("n_nationkey", "n_regionkey"))):
        pd.DataFrame({c: [3] for c in columns}).to_parquet(tmp_path / f"{name}.parquet")
    assert graphs.commerce_numbered(spark, str(tmp_path)).dtypes[0] == ("src", "string")
    assert queries.QUERIES["clustering_exact_commerce"](spark, str(tmp_path)).first().vertices == graphs.commerce(spark, str(tmp_path)).select("src").distinct().count()


def test_global_coefficient_of_numbered_edges(spark, sf_dir, monkeypatch):
    from approxdq.operators import coloured

    monkeypatch.setattr(coloured, "HELD", 8000)
    monkeypatch.setattr(queries, "cut", None)
    want = queries.clustering.exact_global(graphs.commerce(spark, sf_dir)).first()
    got = queries.QUERIES["clustering_global"](spark, sf_dir).first()
    assert (got.closed, got.wedges) == (want.closed, want.wedges) and got.closed > 0


def test_triangles_of_numbered_edges(spark, sf_dir, monkeypatch):
    from approxdq.operators import coloured

    monkeypatch.setattr(coloured, "HELD", 8000)
    monkeypatch.setattr(queries, "cut", None)
    assert queries.QUERIES["triangles"](spark, sf_dir).first().n == queries.clustering.triangles(graphs.commerce(spark, sf_dir)).count() > 0
    assert clustering.count_triangles(spark.createDataFrame([], "src long, dst long")).first().n == 0
