"""The four metrics on a small example worked out by hand, samples, filters and walks by their laws."""

import math
import random
import statistics

import pytest
from pyspark.sql import functions as F

from approxdq.functions import murmur, uris
from approxdq.operators import bloom, catalog, clustering, conciseness, dereference, framework, instances, links, relational, reservoir
from approxdq.plans import graphs
from approxdq.sources import ntriples, tables

A, B = "https://a.example.org/", "https://b.example.com/"
ROWS = [("a1", "knows", "a2"), ("a2", "knows", "a3"), ("a3", "knows", "a1"), ("a3", "seeAlso", B + "b9"), ("a1", "label", '"x'), ("a5", "label", '"y'), ("a5", "knows", "a1"), ("doc#6", "label", '"y'), ("doc#6", "knows", "a1"), ("doc#6", "knows", "a1")]
TRIPLE = "s string, p string, o string, o_kind string, o_datatype string, seq long"


@pytest.fixture(scope="module")
def triples(spark):
    term = lambda x: x if x.startswith("http") else A + x
    return spark.createDataFrame([(A + s, p, o[1:] if o[0] == '"' else term(o), "literal" if o[0] == '"' else "uri", "string" if o[0] == '"' else None, i) for i, (s, p, o) in enumerate(ROWS, 1)], TRIPLE)


def answer(uris_):
    """a1, a2: 303 to 200 RDF; a3: 200 HTML; a5: 404; doc#6: 200 RDF; b: 503."""
    u = F.col("uri")
    rdf, n = F.lit("application/rdf+xml"), F.lit(None).cast("string")
    status = F.when(u.isin(A + "a1", A + "a2"), 303).when(u.isin(A + "a3", A + "doc#6"), 200).when(u == A + "a5", 404).otherwise(503)
    hop = lambda s, x: F.struct(s.alias("status"), x.alias("uri"))
    hops = F.when(status == 303, F.array(hop(F.lit(303), u), hop(F.lit(200), F.concat(u, F.lit(".rdf"))))).otherwise(F.array(hop(status, u)))
    return uris_.select("uri").distinct().select("uri", status.alias("status"), n.alias("location"), F.when((status == 303) | (u == A + "doc#6"), rdf).when(status == 200, "text/html").alias("media"), hops.alias("hops"))


def one(df):
    return df.first()


def test_hand_example(triples):
    assert one(dereference.exact(triples, answer))[:2] == (3, 6)
    assert one(dereference.estimate(triples, 10, 10, probe=False, fetch=answer))[:2] == (3, 6)
    assert one(catalog.slash_uris(dereference.all_uris(triples)))[:2] == (5, 6)
    assert one(links.base_uri(triples)).pld == "a.example.org"
    for mode in ("pair", "base", "distinct_over_total"):
        assert one(links.exact(triples, mode))[:2] == (1, 7)
    own = instances.from_any(triples).join(triples.groupBy("s").agg(F.min("seq").alias("seq")), "s")
    assert one(conciseness.exact(own)).value == 0.8 and one(conciseness.exact(own, "strict")).value == 0.6
    assert one(conciseness.pairwise(own)).value == 0.8 and one(conciseness.estimate(own, 5, 10_000)).value == 0.8
    assert one(catalog.duplicate_instances(own)).value == 0.2 and one(conciseness.prefiltered(own)).value == 0.8
    edges = graphs.from_triples(triples)
    assert math.isclose(one(clustering.exact(edges)).value, 0.25) and one(clustering.exact(edges)).vertices == 6
    assert math.isclose(one(clustering.exact_global(edges)).value, 0.3) and math.isclose(one(clustering.exact_pairs(edges)).value, 0.25)


def test_dead_owner_needs_no_requests(triples):
    got = dereference.estimate(triples, 10, 10, fetch=answer)
    assert one(got).denom == 6 and one(dereference.exact(triples, lambda u: dereference.offline.snapshot(u, all_dead=True))).value == 0


def test_cache_only_fetches_what_is_missing(triples):
    uris_ = dereference.all_uris(triples).select("uri")
    cache = answer(uris_.where("uri like '%a1'"))
    assert dereference.cache_misses(uris_, cache).count() == 5 and dereference.with_cache(uris_, cache, answer).count() == 6


@pytest.mark.parametrize("kernel", [reservoir.sequential, reservoir.skipping])
def test_sequential_reservoirs_are_uniform(kernel):
    hits = [0] * 20
    for seed in range(4000):
        sample = kernel(range(20), 5, seed)
        assert len(set(sample)) == 5
        for x in sample:
            hits[x] += 1
    assert all(abs(h - 1000) < 150 for h in hits)
    assert kernel(range(3), 5) == [0, 1, 2] and kernel(range(5), 0) == [] and kernel([], 4) == []


def test_bottom_k_is_uniform_and_merges(spark):
    df = spark.range(200).withColumnRenamed("id", "x")
    hits = [r.x for seed in range(40) for r in reservoir.bottom_k(df, ["x"], 50, seed).collect()]
    assert len(hits) == 2000 and abs(statistics.fmean(hits) - 99.5) < 6
    whole = {r.x for r in reservoir.bottom_k(df, ["x"], 20, 1).collect()}
    halves = [reservoir.bottom_k(df.where(F.col("x") % 2 == i), ["x"], 20, 1) for i in (0, 1)]
    assert {r.x for r in reservoir.merge(*halves, ["x"], 20).collect()} == whole
    assert reservoir.bottom_k(df, ["x"], 0).count() == 0 and reservoir.bottom_k(df, ["x"], 999).count() == 200
    nulls = spark.createDataFrame([(None,), (1,), (1,)], "x int")
    assert reservoir.bottom_k(nulls, ["x"], 5).count() == 2 and reservoir.bottom_k(nulls, ["x"], 5, unit="distinct").count() == 1


def test_two_level_limits_groups_and_items(spark):
    df = spark.range(300).select((F.col("id") % 10).alias("g"), F.col("id").alias("x"))
    for unit in ("distinct", "occurrence"):
        got = reservoir.two_level(df, "g", ["x"], 3, 4, group_unit=unit).groupBy("g").count().collect()
        assert len(got) == 3 and all(r["count"] == 4 for r in got)
    assert reservoir.capacity(100, 10, 10_000) == 100 and reservoir.capacity(10**9, 100, 10_000) == 100


def test_classic_filter_is_the_sequential_one(spark):
    r = random.Random(0)
    sigs = [f"{r.randrange(60):032x}" for _ in range(150)]
    inst = spark.createDataFrame(list(enumerate(sigs)), "seq long, sig string")
    flags = {x.seq: x.is_dup for x in bloom.flag_classic(inst, 3, 90).collect()}
    import hashlib

    bits, want = [set() for _ in range(3)], {}
    for seq, s in enumerate(sigs):
        at = [int(hashlib.md5(f"0|{i}|{s}".encode()).hexdigest()[:8], 16) % 30 for i in range(3)]
        want[seq] = all(p in b for p, b in zip(at, bits))
        for p, b in zip(at, bits):
            b.add(p)
    assert flags == want


def test_resetting_filter_settings_behave_as_reported(spark):
    """More memory brings the value nearer; resets let copies through, so an estimate can be above the exact value."""
    r = random.Random(0)
    inst = spark.createDataFrame([(i, f"{r.randrange(3000):032x}") for i in range(5000)], "seq long, sig string").cache()
    exact = one(conciseness.exact(inst)).value
    got = [one(conciseness.estimate(inst, k, m)).value for k, m in ((2, 1000), (10, 100_000), (15, 10_000_000))]
    assert abs(got[0] - exact) > abs(got[2] - exact) < 0.01
    errors = one(framework.flag_errors(bloom.flag_balanced(inst, 10_000, k=5), inst))
    assert errors.fn > 0
    sharded = one(conciseness.estimate(inst, 15, 10_000_000, shards=8)).value
    assert abs(sharded - exact) < 0.01
    again = [one(conciseness.estimate(inst, 5, 10_000, seed=3)).value for _ in range(2)]
    assert again[0] == again[1]
    inst.unpersist()


def test_filter_state_and_quotient_filter():
    f = bloom.ResettingFilter(3, 300)
    at, where, chance = bloom.draws([f"s{i}" for i in range(80)], list(range(80)), 3, 100, 0)
    for i in range(80):
        f.add(at[i], where[i], chance[i])
    g = bloom.ResettingFilter(3, 300, state=f.state())
    assert g.bits == f.bits and g.load == f.load and g.seen == f.seen
    q = bloom.QuotientFilter(8, 12)
    assert not q.add(12345) and q.add(12345) and 12345 in q and 12345 in q.grow() and 999 in bloom.QuotientFilter(8, 12).merge(q) or 12345 in q
    assert bloom.filters_for(0.01) == round(math.log(0.01) / math.log(1 - 1 / math.e)) and bloom.bits_for(1000, 0.01) == 9586


def test_murmur_vectors():
    # Published results of the x64 128-bit form, seed 0.
    assert murmur.murmur3_128([b""]).tolist() == [[0, 0]]
    assert [f"{x:016x}" for x in murmur.murmur3_128([b"hello"])[0].tolist()] == ["cbd8a7b341bd9b02", "5b1e906a48ae1d19"]


def test_walk_estimates_agree_with_exact(spark):
    r = random.Random(1)
    pairs = {tuple(sorted(r.sample(range(60), 2))) for _ in range(300)}
    edges = graphs.undirected(spark.createDataFrame([(f"v{a}", f"v{b}") for a, b in pairs], "a string, b string")).cache()
    exact = one(clustering.exact(edges)).value
    long = clustering.walk(edges, seed=2, walkers=16, start="degree", steps=40_000)
    assert abs(one(clustering.estimate(long, edges)).value - exact) < 0.04
    assert abs(one(clustering.one_shot(edges, 600, 3)).value - exact) < 0.12
    assert abs(one(clustering.estimate(long, edges, "global")).value - one(clustering.exact_global(edges)).value) < 0.04
    walks = [clustering.wedges(clustering.walk(edges, seed=4, walkers=3, steps=45, most_edges=m), edges) for m in (10**6, 0)]
    lists, joins = (sorted((tuple(x) for x in w.select("walker", "step", "v", "d", "before", "after", "closed").collect()), key=str) for w in walks)
    assert lists == joins
    assert clustering.steps_for(18630, 1.0) == 97 and clustering.steps_for(2, 0.1) == 3
    edges.unpersist()


def test_components_and_pagerank(spark):
    edges = graphs.undirected(spark.createDataFrame([(f"{i:03}", f"{i + 1:03}") for i in range(40) if i != 20], "a string, b string"))
    got = {r.v: r.component for r in clustering.connected(edges).collect()}
    assert {got[f"{i:03}"] for i in range(21)} == {"000"} and {got[f"{i:03}"] for i in range(21, 41)} == {"021"}
    assert math.isclose(clustering.pagerank(edges, iterations=4).agg(F.sum("rank")).first()[0], 41, rel_tol=1e-9)


def test_uris(spark):
    df = spark.createDataFrame([("https://m.shop.example.net/a/b?x#f",), ("http://www.site.co/x",), ("urn:x:1",)], "uri string")
    got = [tuple(r) for r in uris.parts(df).collect()]
    assert got[0] == ("https://m.shop.example.net/a/b?x#f", "https", "m.shop.example.net", "shop.example.net", "/a/b", "f")
    assert got[1][3] == "site.co" and got[2][3] == "" and got[2][5] is None
    refs = spark.createDataFrame([("http://h.org/d/p?q#z", r) for r in ("/r", "#y", "n", "https://o.org/")], "b string, r string")
    assert [r[0] for r in refs.select(uris.resolve(F.col("b"), F.col("r"))).collect()] == ["http://h.org/r", "http://h.org/d/p?q#y", "http://h.org/d/n", "https://o.org/"]


def test_ntriples_round_trip(spark, tmp_path):
    rows = [("http://a/s", "http://a/p", 'say "hi"\n\\t', "literal", "http://t"), ("_:b1", "http://a/p", "http://o", "uri", None), ("http://a/s", "http://a/p", "_:b2", "bnode", None)]
    df = spark.createDataFrame(rows, "s string, p string, o string, o_kind string, o_datatype string")
    ntriples.write_ntriples(df, str(tmp_path / "t"))
    got = ntriples.read_ntriples(spark, str(tmp_path / "t"))
    assert sorted(map(str, got.select(*df.columns).collect())) == sorted(map(str, df.collect()))


@pytest.mark.parametrize("form", tables.FORMATS)
def test_formats_round_trip(spark, tmp_path, form):
    df = spark.createDataFrame([(1, "a", 1.5), (2, "b,\"c", None)], "k long, s string, v double")
    tables.write(df, str(tmp_path / form), form)
    assert sorted(map(tuple, tables.read(spark, str(tmp_path / form), form, df.schema).collect())) == sorted(map(tuple, df.collect()))


def test_framework(spark, triples):
    r = framework.default_registry()
    r.register("n_triples", lambda t: t.agg(F.count(F.lit(1)).alias("numer"), F.lit(1).alias("denom"), F.count(F.lit(1)).cast("double").alias("value")), "open")
    assert r.direction("clustering") == "open"
    with pytest.raises(ValueError):
        r.register("clustering", None)
    got = framework.assess(spark, "hand", triples, ["external_links", "conciseness", "clustering", "n_triples"], r)
    values = {x.metric: x.value for x in got.collect()}
    assert values["n_triples"] == 10 and math.isclose(values["external_links"], 1 / 7) and values["conciseness"] == 0.8 and math.isclose(values["clustering"], 0.25)
    framework.register_view(got)
    assert spark.sql("select count(*) from quality where seconds > 0").first()[0] == 4
    assert framework.as_triples(got).count() == 16 and framework.pivot(got, ["hand"]).count() == 4
    both = got.unionByName(got.where("metric = 'conciseness'").withColumn("exact", F.lit(False)).withColumn("value", F.col("value") * 1.05).withColumn("variant", F.lit("P1")))
    dev = framework.deviation(both)
    assert math.isclose(one(dev).relative, 0.05, rel_tol=1e-6) and one(framework.best_setting(dev)).best == "P1"
    assert one(framework.completed(got, 1e9).where("metric = 'clustering'")).completed == 1
    rep = framework.replicate(lambda s: float(s), [1, 2, 3])
    assert rep["mean"] == 2 and rep["sd"] == 1


def test_joins_around(spark):
    left = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k int, t int")
    right = spark.createDataFrame([(1, 2, 10.0), (1, 5, 20.0), (2, 10, 30.0)], "k int, t int, v double")
    got = {(r.k, r.t): r.last_v for r in relational.as_of(left, right, "k", "t", "v").collect()}
    assert got == {(1, 5): 20.0, (1, 1): None, (2, 9): None}
    a, b = spark.createDataFrame([(x / 2,) for x in range(40)], "p double"), spark.createDataFrame([(1.0, 3.0), (2.5, 2.6), (10.0, 19.0)], "lo double, hi double")
    assert relational.range_join(a, b, "p", "lo", "hi", 1.5).count() == a.crossJoin(b).where("p >= lo and p < hi").count()


def test_experiments_show_what_is_reported(spark, sf_dir):
    from approxdq import experiments

    links_ = framework.deviation(experiments.external_links(spark, sf_dir)).collect()
    assert all(r.absolute < 0.05 for r in links_)
    dead = [r.value for r in experiments.dereferenceability(spark, sf_dir).where("dataset = 'dead'").collect()]
    assert len(dead) == 5 and set(dead) == {0.0}
    con = experiments.extensional_conciseness(spark, sf_dir, ("orders", "part"))
    dev = {(r.dataset, r.variant): r.absolute for r in framework.deviation(con).collect()}
    assert all(dev[d, "P4"] <= dev[d, "P1"] and dev[d, "P4"] < 0.02 for d in ("orders", "part"))


def replay(instances, k, bits, seed):
    """The balanced resetting filter in plain Python, bit by bit."""
    size, planes, out = bits // k, [set() for _ in range(k)], {}
    ordered = sorted(instances)
    at, where, chance = bloom.draws([s for _, s in ordered], [q for q, _ in ordered], k, size, seed)
    for i, row in enumerate(ordered):
        seen = all(at[i][j] in planes[j] for j in range(k))
        out.setdefault(row, []).append(seen)
        if not seen:
            for j in range(k):
                if chance[i][j] < len(planes[j]) / size:
                    planes[j].discard(where[i][j])
            for j in range(k):
                planes[j].add(at[i][j])
    return out


@pytest.mark.parametrize("k,bits", [(2, 1_000), (5, 10_000)])
def test_resetting_filter_flag_for_flag(spark, sf_dir, k, bits):
    from approxdq.queries import instance_set

    own = instance_set(spark, sf_dir, "lineitem")
    rows = [(r.seq, r.sig) for r in own.collect()]
    want = {x: sorted(v) for x, v in replay(rows, k, bits, 0).items()}
    for n in (3, 8):
        got = {}
        for r in bloom.flag_balanced(own.repartition(n), bits, k=k).collect():
            got.setdefault((r.seq, r.sig), []).append(r.is_dup)
        assert {x: sorted(v) for x, v in got.items()} == want


def test_quotient_filter_of_slots():
    r = random.Random(3)
    for q, rem in ((3, 8), (6, 5), (4, 12)):
        f, held = bloom.QuotientFilter(q, rem), set()
        full = (1 << (q + rem)) - 1
        for _ in range(400):
            h = r.randrange(full + 1) if r.random() < 0.7 else r.randrange(8) << rem | r.randrange(4)
            bits = f.q + f.r
            assert f.add(h) == (h in held) and bits == q + rem
            held.add(h)
            assert h in f
            if len(held) > 0.8 * (1 << 12):
                break
        assert sorted(f.hashes()) == sorted(held) and f.count == len(held)
        assert all((h in f) == (h in held) for h in range(min(full + 1, 3000)))


def test_probe_asks_the_given_fetch(spark, triples):
    uris_ = dereference.all_uris(triples)
    alive = {r.pld: r.alive for r in dereference.domain_probe(uris_, answer).collect()}
    assert alive == {"a.example.org": False, "b.example.com": False}  # 503 for the owners' own pages
    up = lambda u: answer(u).withColumn("status", F.when(F.col("uri") == A, 200).otherwise(F.col("status")))
    assert {r.pld: r.alive for r in dereference.domain_probe(uris_, up).collect()} == {"a.example.org": True, "b.example.com": False}
    assert one(dereference.estimate(triples, 10, 10, fetch=up))[:2] == (3, 6)


def test_links_gain_and_reach(spark):
    edges = graphs.undirected(spark.createDataFrame([("a", "b"), ("b", "c"), ("a", "c"), ("c", "d"), ("d", "e")], "a string, b string"))
    got = {(r.a, r.b): r for r in catalog.interlink_quality(edges).collect()}
    for (a, b), r in got.items():
        without = edges.where(~((F.col("src").isin(a, b)) & (F.col("dst").isin(a, b))))
        was, now = ({x.v: x.c for x in clustering.local(e).collect()} for e in (without, edges))
        assert math.isclose(r.gain_a, now[a] - was.get(a, 0)) and math.isclose(r.gain_b, now[b] - was.get(b, 0))
    reach = {(r.a, r.b): r for r in catalog.interlink_reach(edges, edges.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b")), steps=400).collect()}
    assert all((r.reach_a, r.reach_b) == (5, 5) for r in reach.values())
    assert (reach["d", "e"].without_a, reach["d", "e"].without_b) == (4, 1) and (reach["c", "d"].without_a, reach["c", "d"].without_b) == (3, 2)


def test_links_by_row_names(spark, sf_dir):
    """Samples by row names: all of the triples give the exact share, smaller ones come near it, and seeds differ."""
    from approxdq import queries

    rows, base = queries._trade_rows(spark, sf_dir).cache(), queries._declared(spark, sf_dir)
    exact = links.exact(rows, "base", base).first()
    assert links.estimate(rows, exact.denom, base=base).first() == exact
    got = [links.estimate(rows, 2000, seed=seed, base=base).first() for seed in range(3)]
    assert all(r.denom == 2000 and abs(r.value - exact.value) < 4 * math.sqrt(exact.value * (1 - exact.value) / 2000) for r in got)
    assert len({r.numer for r in got}) > 1
    rows.unpersist()
