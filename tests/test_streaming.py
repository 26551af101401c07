"""Streams against their batch twins: samples, filters, windows, late rows, joins, restart."""

from pyspark.sql import functions as F

from approxdq.operators import bloom, reservoir
from approxdq.streaming import streams


def parts(spark, sf_dir, tmp_path, n=3):
    path = str(tmp_path / "events")
    whole = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    most = whole.agg(F.max("event_id")).first()[0] + 1
    for i in range(n):  # files in order of time
        whole.where(F.floor(F.col("event_id") * n / most) == i).coalesce(1).write.mode("append").parquet(path)
    df = spark.read.parquet(path)
    return df, streams.file_stream(spark, path, df.schema)


def run(df, name, tmp_path, mode="append"):
    streams.start(df, name, str(tmp_path / f"cp_{name}"), mode).awaitTermination(180)
    return df.sparkSession.table(name)


def test_reservoir_with_state(spark, sf_dir, tmp_path):
    batch, stream = parts(spark, sf_dir, tmp_path)
    out = []
    streams.start(streams.reservoir(stream, "event_type", "event_id", 5, seed=3), lambda df, i: out.extend(df.collect()), str(tmp_path / "cp_res"), "update").awaitTermination(180)
    got = spark.createDataFrame(out)
    top = got.groupBy("grp").agg(F.max("n_seen").alias("n_seen"))
    last = {(r.grp, r.item) for r in got.join(top, ["grp", "n_seen"]).collect()}
    keyed = batch.select(F.col("event_type").alias("grp"), F.col("event_id").cast("string").alias("item"))
    assert last == {(r.grp, r.item) for r in reservoir.bottom_k_by(keyed, "grp", ["item"], 5, 3).collect()}


def test_filter_with_state_is_the_batch_filter(spark, sf_dir, tmp_path):
    batch, stream = parts(spark, sf_dir, tmp_path)
    sig = lambda d: d.select("event_id", F.md5(F.concat_ws("|", "user_id", "event_type")).alias("sig"))
    got = {r.seq: r.is_dup for r in run(streams.flag_balanced(sig(stream), "sig", "event_id", 4000, 4, shards=2), "flags", tmp_path).collect()}
    want = {r.seq: r.is_dup for r in bloom.flag_balanced(sig(batch).withColumnRenamed("event_id", "seq"), 4000, k=4, shards=2).collect()}
    assert got == want and any(got.values())


def test_windows_watermarks_and_repeats(spark, sf_dir, tmp_path):
    batch, stream = parts(spark, sf_dir, tmp_path)
    got = {(r.start, r.event_type): r.n for r in run(streams.tumbling(stream, delay="1 hour"), "tumbling", tmp_path, "complete").collect()}
    assert got == {(r.start, r.event_type): r.n for r in streams.tumbling(batch).collect()}
    assert run(streams.sliding(stream, delay="1 hour"), "sliding", tmp_path, "complete").count() == streams.sliding(batch).count()
    once = run(streams.drop_repeats(stream, "user_id", "ts", "5000 days"), "once", tmp_path)
    assert once.count() == batch.select("user_id").distinct().count()
    assert 0 < run(streams.sessions(stream, delay="1 hour"), "sess", tmp_path).count() <= streams.sessions(batch).count()


def test_stream_joins_and_restart(spark, sf_dir, tmp_path):
    batch, stream = parts(spark, sf_dir, tmp_path)
    users = spark.createDataFrame([(i, f"u{i}") for i in range(50)], "user_id long, name string")
    assert run(stream.join(users, "user_id"), "static_join", tmp_path).count() == batch.join(users, "user_id").count()
    side = lambda d: d.select("user_id", "ts", "event_id")
    a, b = side(stream).withWatermark("ts", "4000 days"), side(stream).withWatermark("ts", "4000 days")
    assert run(streams.within(a, b, "user_id", 10), "near", tmp_path).count() == streams.within(side(batch), side(batch), "user_id", 10).count()
    seen = []
    for _ in range(2):  # the second start finds nothing new
        streams.start(stream, lambda df, i: seen.append(df.count()), str(tmp_path / "cp_each")).awaitTermination(120)
    assert sum(seen) == batch.count()
