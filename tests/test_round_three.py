"""Long streams in ranges and walks that only look up, against the forms that hold all at once."""

import numpy as np
from pyspark.sql import functions as F

from approxdq import queries
from approxdq.experiments import _ladder_links, ladder
from approxdq.operators import bloom, clustering, conciseness, links
from approxdq.plans import graphs, mappings


def stream(spark, n, values):
    return spark.range(n).select(F.when(F.col("id") > 0, F.col("id") / 3).cast("long").alias("seq"), F.md5(F.pmod(F.xxhash64("id"), F.lit(values)).cast("string")).alias("sig"))


def test_ranges_of_a_stream_count_as_the_single_stream(spark):
    k, bits = 4, 100
    inst = stream(spark, 20_000, 900).where("seq is not null")
    want = bloom.flag_balanced(inst, bits, k=k).agg(F.count_if(~F.col("is_dup")), F.count(F.lit(1))).first()
    assert bloom.count_balanced(inst, bits, k=k) == tuple(want)
    got = conciseness.estimate(inst, k, bits).first()
    assert (got.numer, got.denom) == tuple(want)
    # with next to nothing read before a range, its first bits are wrong, and it is read again
    inst = inst.where("seq < 1000")
    want = bloom.flag_balanced(inst, bits, k=k).agg(F.count_if(~F.col("is_dup")), F.count(F.lit(1))).first()
    assert bloom.count_balanced(inst, bits, k=k, forgets=1) == tuple(want)


def test_ranges_with_one_crowded_seq(spark):
    inst = stream(spark, 20_000, 900).where("seq is not null").withColumn("seq", F.when(F.col("seq").between(1500, 5000), 1500).otherwise(F.col("seq")))
    want = bloom.flag_balanced(inst, 100, k=4).agg(F.count_if(~F.col("is_dup")), F.count(F.lit(1))).first()
    assert bloom.count_balanced(inst, 100, k=4) == tuple(want)


def test_short_streams_and_filters_that_keep_all_stay_single(spark):
    assert bloom.count_balanced(stream(spark, 500, 90), 400, k=4) is None
    assert bloom.count_balanced(stream(spark, 20_000, 900), 100, k=4, policy="none") is None


def test_walk_by_look_ups_is_the_walk(spark, sf_dir):
    edges = graphs.commerce(spark, sf_dir).persist()
    vertices = graphs.commerce_vertices(spark, sf_dir)
    assert sorted(r.v for r in vertices.collect()) == sorted(r.src for r in edges.select("src").distinct().collect())
    near = lambda names: graphs.commerce_near(spark, sf_dir, names)
    want = clustering.walk(edges, seed=5, steps=8).collect()
    for most in (10**6, 3):
        assert clustering.walk_by(near, vertices, seed=5, steps=8, most=most).collect() == want
    edges.unpersist()


def test_ladder_never_makes_the_commerce_graph_by_name(spark, sf_dir, monkeypatch):
    """At 60 times sf0.1 that alone ran out of time: both directions of 118 million edges, written, joined and sorted by name."""
    made = []
    monkeypatch.setattr(clustering, "local", lambda e, f=clustering.local: made.append(e) or f(e))
    monkeypatch.setattr(clustering, "walk", lambda e, *a, f=clustering.walk, **k: made.append(e) or f(e, *a, **k))
    got = {(r.dataset.split()[-1], r.metric, r.variant): r.value for r in ladder(spark, sf_dir).collect()}
    assert len(got) == 23
    commerce = {r.src for r in graphs.commerce(spark, sf_dir).limit(1).collect()}
    assert len(made) == 4 and not any({r.src for r in e.collect()} & commerce for e in made)
    edges = graphs.commerce(spark, sf_dir).persist()
    assert abs(got["commerce", "clustering", "exact"] - clustering.exact(edges).first().value) < 1e-9
    assert abs(got["commerce", "clustering", "m=0.1"] - clustering.estimate(clustering.walk(edges, 0.1), edges).first().value) < 1e-9
    edges.unpersist()


def test_encoder_remembers_the_pieces_of_a_large_table():
    """Beyond 300,000 pieces the later ones were forgotten and encoded anew, and all but 60,000 after each task."""
    import public_tokenizers

    from approxdq.llm import bpe

    enc = bpe.ByteEncoder(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
    text = " ".join(map(str, range(100_000, 410_000)))
    first = enc.encode(text)
    enc.trim()
    calls = []
    enc.cache.encode = lambda piece: calls.append(piece) or enc.encode_piece(piece)
    assert enc.encode(text) == first and not calls
    assert enc.decode(first) == text.encode()


def test_many_ranges_of_a_stream(spark):
    """A thousand ranges and more were one nested expression, and the driver ran out of stack; settings are read together, also one
    that forgets nothing in the stream, and first bits that are wrong are put right within a task and across tasks."""
    inst = stream(spark, 200_000, 900).where("seq is not null")
    settings = [(2, 4), (3, 300), (4, 8000)]
    want = [tuple(bloom.flag_balanced(inst, bits, k=k).agg(F.count_if(~F.col("is_dup")), F.count(F.lit(1))).first()) for k, bits in settings]
    assert bloom.count_settings(inst, settings, held=60_000) == want
    few = inst.where("seq < 4000")
    want = [tuple(bloom.flag_balanced(few, bits, k=k).agg(F.count_if(~F.col("is_dup")), F.count(F.lit(1))).first()) for k, bits in settings[1:]]
    assert bloom.count_settings(few, settings[1:], forgets=1, held=3000) == want


def test_policies_of_a_stream_in_pieces(spark):
    inst = stream(spark, 12_000, 900).where("seq is not null")
    for policy in ("balanced", "biased", "biased_single", "reservoir", "none"):
        for form in ("murmur128", "md5"):
            want = bloom.flag_balanced(inst, 100, k=4, policy=policy, form=form).agg(F.count_if(~F.col("is_dup")), F.count(F.lit(1))).first()
            assert bloom.count_settings(inst, [(4, 100)], policy=policy, form=form, held=5000) == [tuple(want)]


def test_walk_over_numbered_edges_is_the_walk_by_name(spark, sf_dir, tmp_path, monkeypatch):
    """Above 20 million directed edges each step of the walkers was a Spark job, and the graph by name was written first."""
    edges = graphs.commerce(spark, sf_dir).persist()
    monkeypatch.setattr(clustering, "PACKED", 5000)
    numbered = graphs.commerce_numbered(spark, sf_dir)
    for kw in ({"walkers": 5, "start": "degree", "steps": 60}, {"m": 0.2}):
        want = sorted(clustering.walk(edges, seed=1, **kw).collect())
        assert sorted(clustering.walk(numbered, seed=1, kinds=graphs.KINDS, **kw).collect()) == want
    monkeypatch.setattr(queries, "cut", None)
    monkeypatch.setattr(clustering, "Lists", None)
    assert queries.QUERIES["clustering_walk_long"](spark, sf_dir).first().steps > 1000
    edges.unpersist()


def test_numbered_vertices_are_ordered_by_name():
    rng = np.random.default_rng(1)
    key = np.concatenate([[0, -1, 1, 10, 100, 12, -10, -12, (1 << 59) - 1, -(1 << 59)], rng.integers(-2000, 2000, 500), rng.integers(-(1 << 59), 1 << 59, 500)])
    v = key * 8 + rng.integers(0, 6, len(key))
    name = lambda x: f"{graphs.KINDS[x & 7]}{x >> 3}"
    assert [name(x) for x in v[np.lexsort(clustering._by_name(v, graphs.KINDS))].tolist()] == sorted(map(name, v.tolist()))


def test_look_for_a_declaration_makes_no_subjects(spark, sf_dir, monkeypatch):
    """Items declare nothing, yet a digest of eleven columns was made for each before their triples were sifted."""
    asked = []
    monkeypatch.setattr(links, "from_declaration", lambda t, f=links.from_declaration: asked.append(t) or f(t))
    for _, metric, _, _, _, make in _ladder_links(spark, "items", *(mappings.triples(spark, sf_dir, "lineitem", kind="uri", early=early) for early in (True, False))):
        assert metric == "external_links" and make().first().denom > 0
    plan = asked[0].where("p = 'type'").select("s")._jdf.queryExecution().optimizedPlan().toString()
    assert len(asked) == 1 and "md5" not in plan[plan.index("Filter") :].split("Relation")[0]
