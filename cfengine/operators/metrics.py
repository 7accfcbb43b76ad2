"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def recall_at_k(recs: DataFrame, heldout: DataFrame, k: int = 20, average: str = "user") -> DataFrame:
    """recs: user_id, rank, item_id. Users without a held-out item do not count; found users without a list count 0."""
    hits = recs.where(F.col("rank") <= k).join(heldout.select("user_id", "item_id"), ["user_id", "item_id"]).groupBy("user_id").agg(F.count(F.lit(1)).alias("tp"))
    base = heldout.groupBy("user_id").agg(F.count(F.lit(1)).alias("n")).join(hits, "user_id", "left").withColumn("tp", F.coalesce("tp", F.lit(0)))
    value = F.avg(F.col("tp") / F.col("n")) if average == "user" else F.sum("tp") / F.sum("n")
    return base.agg(F.round(value, 6).alias("recall"))


def ndcg_at_k(recs: DataFrame, heldout: DataFrame, k: int = 20) -> DataFrame:
    hits = recs.where(F.col("rank") <= k).join(heldout.select("user_id", "item_id"), ["user_id", "item_id"]).groupBy("user_id").agg(F.sum(1 / F.log2(F.col("rank") + 1)).alias("dcg"))
    ideal = F.aggregate(F.sequence(F.lit(1), F.least(F.col("n"), F.lit(k)).cast("int")), F.lit(0.0), lambda a, r: a + 1 / F.log2(r + 1))
    base = heldout.groupBy("user_id").agg(F.count(F.lit(1)).alias("n")).join(hits, "user_id", "left")
    return base.agg(F.round(F.avg(F.coalesce("dcg", F.lit(0.0)) / ideal), 6).alias("ndcg"))


def metric_gap(a: float, b: float) -> float:
    return abs(a - b)


def memory_model(users: float, items: float, dim: int, capacity: float, overhead: float) -> float | None:
    """Share of capacity that a model takes, or None if it does not fit."""
    share = (users + items) * dim * 4 * overhead / capacity
    return share if share <= 1 else None


def rows_that_fit(capacity: float, dim: int, overhead: float = 1.0) -> int:
    return int(capacity // (dim * 4 * overhead))


def training_cost(epoch_seconds: float, epochs: int, price: float, instances: int = 1) -> float:
    return epoch_seconds * epochs / 3600 * price * instances


def scaling_table(spark: SparkSession, times: dict[int, float]) -> DataFrame:
    """cores, seconds, speedup, efficiency against the smallest number of cores."""
    p0 = min(times)
    rows = [(p, t, times[p0] * p0 / t, times[p0] * p0 / t / p) for p, t in sorted(times.items())]
    return spark.createDataFrame(rows, "cores int, seconds double, speedup double, efficiency double")


def copy_bytes(batch: int, n: int, dim: int) -> int:
    return batch * (1 + n) * dim * 4


def weight_writes(iterations: int, workers: int, m: int) -> int:
    """Updates of the shared layer: each worker writes once every m of its iterations, and once for a rest."""
    per = -(-iterations // workers)
    return workers * -(-per // m)


def reuse_savings(n: int, dim: int, sides: int = 2) -> int:
    """Multiplications an example saves by keeping the three sums."""
    return 3 * sides * (n + 1) * dim


def phase_share(seconds: dict[str, float]) -> dict[str, float]:
    total = sum(seconds.values()) or 1.0
    return {k: 100 * v / total for k, v in seconds.items()}


def speedups(times: DataFrame, base: str) -> DataFrame:
    """workload, method, speedup of every method against base on the same workload, and the mean over workloads
    under workload 'mean'. times: workload, method, seconds."""
    own = times.where(F.col("method") == base).select("workload", F.col("seconds").alias("_base"))
    rows = times.join(own, "workload").where(F.col("method") != base).select("workload", "method", (F.col("_base") / F.col("seconds")).alias("speedup"))
    return rows.unionByName(rows.groupBy("method").agg(F.avg("speedup").alias("speedup")).select(F.lit("mean").alias("workload"), "method", "speedup"))


def cost_frame(runs: DataFrame, epochs: int) -> DataFrame:
    """runs with hours, dollars and ratio: how many times the cheapest run of its workload it costs.
    runs: workload, platform, seconds (an epoch), price (an hour), instances."""
    hours = F.col("seconds") * epochs / 3600
    priced = runs.withColumn("hours", hours).withColumn("dollars", F.col("hours") * F.col("price") * F.col("instances"))
    least = priced.groupBy("workload").agg(F.min("dollars").alias("_least"))
    return priced.join(least, "workload").withColumn("ratio", F.col("dollars") / F.col("_least")).drop("_least")


def memory_frame(sizes: DataFrame, dim: int) -> DataFrame:
    """sizes with bytes of the model and share of each platform's memory, null where it does not fit.
    sizes: workload, users, items, platform, capacity, overhead."""
    held = (F.col("users") + F.col("items")) * dim * 4 * F.col("overhead")
    share = held / F.col("capacity")
    return sizes.withColumn("bytes", held).withColumn("share", F.when(share <= 1, share)).withColumn("rows_that_fit", F.floor(F.col("capacity") / (dim * 4 * F.col("overhead"))).cast("long"))


def copy_frame(sizes: DataFrame, batch: int, negatives: int, dim: int) -> DataFrame:
    """workload, batches, copied, norms: bytes that batching copies in an epoch, and those of the norm tensor,
    written once and read once. sizes: workload, pairs."""
    rows = F.col("pairs") * (1 + negatives)
    return sizes.select("workload", F.ceil(F.col("pairs") / batch).cast("long").alias("batches"), (rows * dim * 4).alias("copied"), (2 * rows * 4).alias("norms"))


def reuse_frame(sizes: DataFrame, negatives: int, dim: int) -> DataFrame:
    """workload, kept, again: passes over vectors of an epoch that keeps the three sums and of one that computes
    them again for both sides' gradients, in multiplications. sizes: workload, pairs."""
    once = F.col("pairs") * (1 + negatives) * dim
    return sizes.select("workload", (3 * once).alias("kept"), (9 * once).alias("again"))


def stage_metrics(spark: SparkSession, action) -> dict[str, float]:
    """What the stages of action() took: stages, tasks, seconds of tasks, bytes read and written by shuffles, bytes
    spilled, and bytes read from tables."""
    store = spark.sparkContext._jsc.sc().statusStore()
    bus = spark.sparkContext._jsc.sc().listenerBus()

    def stages() -> dict:
        bus.waitUntilEmpty()
        rows = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
        return {(rows.apply(k).stageId(), rows.apply(k).attemptId()): rows.apply(k) for k in range(rows.size())}

    before = set(stages())
    action()
    new = [s for k, s in stages().items() if k not in before]
    return {
        "stages": len(new), "tasks": sum(s.numCompleteTasks() for s in new), "task_seconds": sum(s.executorRunTime() for s in new) / 1000,
        "shuffle_read": sum(s.shuffleReadBytes() for s in new), "shuffle_written": sum(s.shuffleWriteBytes() for s in new),
        "spilled": sum(s.diskBytesSpilled() for s in new), "input_bytes": sum(s.inputBytes() for s in new),
    }
