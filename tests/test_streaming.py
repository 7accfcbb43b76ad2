from pyspark.sql import functions as F

from cfengine.streaming import streams


def _files(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts")
    path = str(tmp_path / "events")
    e.repartitionByRange(3, "ts").write.parquet(path)
    return e, spark.read.parquet(path).schema, path


def _run(spark, df, name, mode, tmp_path):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def test_replay_equals_batch(spark, sf, tmp_path):
    e, schema, path = _files(spark, sf, tmp_path)
    got = _run(spark, streams.popularity(streams.read_events(spark, path, schema)), "pop", "complete", tmp_path)
    assert sorted(got.collect()) == sorted(streams.popularity(e).collect())


def test_repeats_are_dropped(spark, sf, tmp_path):
    e, schema, path = _files(spark, sf, tmp_path)
    e.limit(50).write.mode("append").parquet(path)
    got = _run(spark, streams.ingest(streams.read_events(spark, path, schema, 10)), "ing", "append", tmp_path)
    assert got.count() == e.count()


def test_history_stream_keeps_the_latest(spark, sf, tmp_path):
    e, schema, path = _files(spark, sf, tmp_path)
    rows = streams.replay(streams.rolling_history(streams.read_events(spark, path, schema), 10, idle="30 days"), str(tmp_path / "hist"), "update")
    assert rows.agg(F.max(F.size("hist"))).first()[0] == 10
    last = {r.user_id: r.hist for r in rows.groupBy("user_id").agg(F.max_by("hist", "batch").alias("hist")).collect()}
    assert last == {r.user_id: r.hist for r in streams.latest_items(e, 10).collect()}


def test_late_rows_are_dropped_and_append_waits(spark, sf, tmp_path):
    """Windows come out in append mode once the watermark passes them; a row behind it changes nothing."""
    at = str(tmp_path / "in")
    write = lambda rows: spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.mode("append").parquet(at)
    import datetime as dt

    day = lambda d, h=0: dt.datetime(2024, 1, d, h)
    props = '{"k": 7}'
    write([(1, day(1, 1), 1, "view", 0.0, props), (2, day(1, 2), 1, "view", 0.0, props)])
    write([(3, day(5), 1, "view", 0.0, props)])
    write([(6, day(6), 1, "view", 0.0, props)])  # a watermark holds from the batch after the next on
    write([(4, day(1, 3), 1, "view", 0.0, props), (5, day(9), 1, "view", 0.0, props)])
    schema = spark.read.parquet(at).schema
    got = streams.replay(streams.popularity(streams.read_events(spark, at, schema)), str(tmp_path / "late"))
    assert {(str(r.start)[:10], r.n) for r in got.collect()} == {("2024-01-01", 2), ("2024-01-05", 1), ("2024-01-06", 1)}


def test_stream_scores_and_joins_equal_the_batch(spark, sf, tmp_path):
    from cfengine.functions import vectors as V

    e, schema, path = _files(spark, sf, tmp_path)
    rows = spark.range(0, 200).withColumn("vec", V.init_vector(1, "id", 4)).cache()
    got = streams.replay(streams.score_stream(streams.read_events(spark, path, schema), rows, rows), str(tmp_path / "s")).drop("batch")
    assert sorted(got.collect()) == sorted(streams.score_stream(e, rows, rows).collect())
    two = streams.views_to_purchases(streams.read_events(spark, path, schema, 10), streams.read_events(spark, path, schema, 10))
    assert sorted(streams.replay(two, str(tmp_path / "v")).drop("batch").collect()) == sorted(streams.views_to_purchases(streams.timed(e), streams.timed(e)).collect())


def test_rate_stream_gives_pairs(spark):
    from cfengine.sources.tables import rate_pairs

    q = rate_pairs(spark, 50, 10, 5).writeStream.format("memory").queryName("rate").start()
    try:
        q.awaitTermination(6)
        assert spark.table("rate").where("user_id >= 10 or item_id >= 5").isEmpty()
    finally:
        q.stop()


def test_refresh_versions(spark, sf, tmp_path):
    from cfengine.operators.blocks import TrainConfig

    e, schema, path = _files(spark, sf, tmp_path)
    start = spark.createDataFrame([], "side string, id long, vec array<double>")
    q = streams.refresh_factors(streams.read_events(spark, path, schema), TrainConfig(dim=4, negatives=2, plan="block"), start, str(tmp_path / "f"), str(tmp_path / "c"))
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "f" / "v2")).where("side = 'user'").count() == e.where("event_type in ('view', 'click', 'purchase')").select("user_id").distinct().count()
