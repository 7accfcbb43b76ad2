"""Event streams: ingest, popularity, sessions, histories, refresh and scoring.

Each function takes a batch or a streaming frame of events, so a replay equals the batch result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DELAY = "1 hour"


def timed(events: DataFrame) -> DataFrame:
    """ts as a timestamp with zone, as watermarks need it."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def read_events(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return timed(spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path))


def ingest(events: DataFrame, delay: str = DELAY) -> DataFrame:
    """Events without repeats of an id inside the delay; later ones are dropped."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def popularity(events: DataFrame, width: str = "1 day", slide: str | None = None, delay: str = DELAY) -> DataFrame:
    """start, item_id, n per tumbling or sliding window."""
    e = timed(events).withColumn("item_id", F.get_json_object("props", "$.k").cast("long")).where("item_id is not null")
    if events.isStreaming:
        e = e.withWatermark("ts", delay)
    return e.groupBy(F.window("ts", width, slide), "item_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "item_id", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = DELAY) -> DataFrame:
    """user_id, start, n: runs of a user's events with gaps shorter than gap."""
    e = timed(events)
    if events.isStreaming:
        e = e.withWatermark("ts", delay)
    return e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def score_stream(events: DataFrame, users: DataFrame, items: DataFrame) -> DataFrame:
    """Stream-static: the model's score of each event's user and item."""
    from ..operators.predict import score_pairs

    pairs = events.select("user_id", F.get_json_object("props", "$.k").cast("long").alias("item_id")).where("item_id is not null")
    return score_pairs(pairs, users, items)


def views_to_purchases(events_a: DataFrame, events_b: DataFrame, delay: str = DELAY) -> DataFrame:
    """Purchases within an hour after a view of the same user: two watermarks and a time condition."""
    v = events_a.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("vu"), F.col("ts").alias("vts"))
    p = events_b.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts")
    if events_a.isStreaming:
        v, p = v.withWatermark("vts", delay), p.withWatermark("ts", delay)
    return v.join(p, (F.col("vu") == F.col("user_id")) & (F.col("ts") >= F.col("vts")) & (F.col("ts") <= F.col("vts") + F.expr("interval 1 hour"))).select("view_id", "purchase_id")


def rolling_history(events: DataFrame, max_len: int = 100, idle: str | None = None, delay: str = DELAY) -> DataFrame:
    """user_id, hist: the latest items of each user as a batch grows; state is one bounded list a user. idle: a user
    whose latest event the watermark has left so far behind ('30 days') is forgotten."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    e = timed(events).withColumn("item_id", F.get_json_object("props", "$.k").cast("long")).where("item_id is not null")
    if idle is not None:
        e = e.withWatermark("ts", delay)
    e = e.select("user_id", "ts", F.unix_micros("ts").alias("at"), "event_id", "item_id")
    keep_ms = None if idle is None else int(pd.Timedelta(idle).total_seconds() * 1000)

    def update(key, frames, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        old = list(zip(*state.get, strict=True)) if state.exists else []
        for pdf in frames:
            old += list(zip(pdf["at"], pdf["event_id"], pdf["item_id"], strict=True))
        old = sorted(old, key=lambda x: (x[0], x[1]), reverse=True)[:max_len]
        state.update(tuple([int(x[k]) for x in old] for k in range(3)))
        if keep_ms is not None:
            state.setTimeoutTimestamp(max(int(old[0][0]) // 1000 + keep_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"user_id": [key[0]], "hist": [[int(x[2]) for x in old]]})

    timeout = GroupStateTimeout.NoTimeout if idle is None else GroupStateTimeout.EventTimeTimeout
    return e.groupBy("user_id").applyInPandasWithState(update, "user_id long, hist array<long>", "ats array<long>, ids array<long>, items array<long>", "update", timeout)


def latest_items(events: DataFrame, max_len: int = 100) -> DataFrame:
    """user_id, hist: what rolling_history holds in the end, from a batch."""
    from pyspark.sql import Window as W

    e = timed(events).withColumn("item_id", F.get_json_object("props", "$.k").cast("long")).where("item_id is not null")
    n = F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id")))
    cut = e.withColumn("_n", n).where(F.col("_n") <= max_len)
    return cut.groupBy("user_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("_n", "item_id"))), lambda x: x["item_id"]).alias("hist"))


def replay(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what its source holds now, batch by batch, and gives back every row it put out, with the
    number of its batch. Rows and progress lie under path, in the folder that executors share."""
    spark = stream.sparkSession

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/rows/part={number}")

    q = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/progress").trigger(availableNow=True).start()
    q.awaitTermination()
    schema = stream.schema.add("batch", "integer")
    return spark.read.schema(schema).parquet(f"{path}/rows/part=*")


def refresh_factors(events: DataFrame, cfg, start: DataFrame, path: str, checkpoint: str):
    """Each micro-batch trains from the latest snapshot and writes the next version under path."""
    from ..operators.trainer import fit
    from ..sources.feedback import from_events

    def on_batch(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        warm = start if number == 0 else spark.read.parquet(f"{path}/v{number - 1}")
        pairs = from_events(batch).select("user_id", "item_id")
        out = warm if pairs.isEmpty() else fit(pairs, cfg, warm).factors
        out.select("side", "id", "vec").write.mode("overwrite").parquet(f"{path}/v{number}")

    return events.writeStream.foreachBatch(on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
