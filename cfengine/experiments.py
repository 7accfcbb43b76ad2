"""The paper's experiments on the given tables: workload, method, setting, metric, value.

Hardware-bound figures keep the structure (phases, ratios, curves), not the numbers. Every run trains on all
pairs of its workload, in as many blocks as the sizes ask for; dimensions are small by default. Seconds are those of
the kernels, and wall_seconds those of a whole fit. Runs that are only scored, not timed, share the session.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import metrics, tuning
from .operators.baselines import als_baseline, popularity_recs
from .operators.blocks import PHASES, PRESETS, TrainConfig, with_options
from .operators.predict import aggregated_users, recommend
from .operators.trainer import Model, fit
from .plans.cuts import Cuts
from .shipping import ship
from .sources.feedback import planted, split_holdout, user_history, workload

SCHEMA = "workload string, method string, setting string, metric string, value double"
SMALL = TrainConfig(dim=32, negatives=16, epochs=1, batch=64, lr=0.05, mu=4.0, theta=0.3)
#: The dimensions of the paper's sampler experiments.
FULL = TrainConfig(dim=128, negatives=64, epochs=1, batch=64, lr=0.05, mu=4.0, theta=0.3, precision="float32")
#: Workloads with a structure that can be learned, and those where recall is chance whatever the model.
SIGNAL, FLOOR = ("docterms", "planted"), ("orders", "suppliers", "events")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Distinct pairs of a workload, with the latest time of each where it has one."""
    ship(spark)
    pairs = planted(spark) if name == "planted" else workload(spark, sf_dir, name)
    when = [F.max("ts").alias("ts")] if "ts" in pairs.columns else [F.lit(None).cast("timestamp").alias("ts")]
    return Cuts(spark).cut(pairs.groupBy("user_id", "item_id").agg(*when))


def train(pairs: DataFrame, cfg: TrainConfig) -> tuple[Model, dict]:
    """The model, and what its kernels counted an epoch; seconds are task time, without Spark's own."""
    began = time.perf_counter()
    model = fit(pairs, cfg)
    total: dict = {"wall_seconds": (time.perf_counter() - began)}
    for h in model.history:
        for k, v in h.items():
            total[k] = total.get(k, 0) + (v or 0)
    total = {k: v / cfg.epochs for k, v in total.items() if k != "epoch"}
    total["seconds"] = sum(total[f"s_{p}"] for p in PHASES)
    return model, total


def counted(pairs: DataFrame, cfg: TrainConfig) -> dict:
    """What the kernels counted, of a model that nothing reads: its tables are deleted before the next run makes its own."""
    model, total = train(pairs, cfg)
    model.drop()
    return total


def many(jobs: list[Callable[[], list[tuple]]], at_once: int = 4) -> list[tuple]:
    """Rows of jobs that do not measure time, several in the session at once."""
    with ThreadPoolExecutor(at_once) as pool:
        return [r for rows in pool.map(lambda j: j(), jobs) for r in rows]


def shares(total: dict, parts=PHASES) -> dict[str, float]:
    return metrics.phase_share({p: total[f"s_{p}"] for p in parts})


def accuracy_of(model: Model, train_pairs: DataFrame, test: DataFrame) -> dict[str, float]:
    """Recall and NDCG at 20 over all users with a held-out pair."""
    cuts, users = Cuts(test.sparkSession), model.user_factors
    if model.weights is not None:
        users = cuts.cut(aggregated_users(users, model.item_factors, user_history(train_pairs, model.cfg.history), model.weights, model.cfg))
    recs = cuts.cut(recommend(users, model.item_factors, train_pairs, 20, model.cfg.similarity))
    return {"recall20": metrics.recall_at_k(recs, test).first()[0] or 0.0, "ndcg20": metrics.ndcg_at_k(recs, test).first()[0] or 0.0}


def _frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(a, b, str(c), d, float(v)) for a, b, c, d, v in rows], SCHEMA)


SETS = ("orders", "suppliers", "events")
FORWARD = ("read_user", "read_item", "user_norm", "item_norm", "copy", "similarity", "loss")


def dense_vs_sparse(spark, d):
    """Rows written by the dense update, the frameworks' sparse one and the fused one, and shares of forward and backward."""
    rows = []
    for w in SETS:
        pairs = load(spark, d, w)
        for engine in ("dense", "sparse", "fused"):
            t = counted(pairs, with_options(SMALL, engine=engine, batch=256))
            p = shares(t)
            fwd = sum(p[k] for k in (*FORWARD, "aggregate"))
            rows += [(w, engine, "", "epoch_seconds", t["seconds"]), (w, engine, "", "wall_seconds", t["wall_seconds"]), (w, engine, "", "forward_share", fwd), (w, engine, "", "backward_share", p["backward"] + p["update"]), (w, engine, "", "rows_written", t["rows_written"])]
    return _frame(spark, rows)


def forward_parts(engine: str):
    def run(spark, d):
        """The seven parts of the forward pass at the paper's dimension and negatives, and bytes copied."""
        cfg = with_options(PRESETS["profile"], engine=engine, batch=1024 if engine == "dense" else 64, precision="float32")
        rows = []
        for w in SETS:
            t = counted(load(spark, d, w), cfg)
            rows += [(w, engine, f"K=128 n=64 B={cfg.batch}", k, v) for k, v in shares(t, FORWARD).items()] + [(w, engine, "", "copied_bytes", t["copied_bytes"])]
        return _frame(spark, rows)

    return run


def memory(spark, d):
    """Share of either platform's memory for the published sizes and the measured ones of all five workloads
    (absent where a model does not fit), and rows that fit in 80 GB."""
    sizes = [("goodreads", 810_000, 1_560_000), ("google", 4_570_000, 3_120_000), ("amazon", 20_980_000, 9_350_000)]
    for w in (*SETS, "docterms", "talkterms"):
        r = load(spark, d, w).agg(F.countDistinct("user_id").alias("u"), F.countDistinct("item_id").alias("i")).first()
        sizes.append((w, r.u, r.i))
    platforms = spark.createDataFrame([("cpu", 256e9, 7.35), ("gpu", 32e9, 6.52)], "platform string, capacity double, overhead double")
    held = metrics.memory_frame(spark.createDataFrame(sizes, "workload string, users long, items long").crossJoin(platforms), 128)
    rows = [(r.workload, r.platform, "dim 128", "share", r.share) for r in held.collect() if r.share is not None]
    return _frame(spark, rows + [("any", "gpu", "80 GB", "rows", metrics.rows_that_fit(80e9, 128, 8.0))])


def epoch_times(spark, d):
    """E5: epoch time of the dense, the jagged and the fused engine, with and without aggregation, and speedups of the fused one
    on every set and their mean."""
    times = []
    for w in SETS:
        pairs = load(spark, d, w)
        for kind, agg in (("", None), ("+agg", "average")):
            for e in ("dense", "jagged", "fused"):
                t = counted(pairs, with_options(SMALL, engine=e, batch=256, aggregator=agg))
                times.append((w, e, kind, t["seconds"], t["wall_seconds"]))
    rows = [(w, e + k, "", m, v) for w, e, k, s, wall in times for m, v in (("epoch_seconds", s), ("wall_seconds", wall))]
    for kind in ("", "+agg"):
        frame = spark.createDataFrame([(w, e, s) for w, e, k, s, _ in times if k == kind], "workload string, method string, seconds double")
        for e in ("dense", "jagged"):
            rows += [(r.workload, "fused" + kind, e + kind, "speedup", r.speedup) for r in metrics.speedups(frame, e).where("method = 'fused'").collect()]
    return _frame(spark, rows)


def pointwise(spark, d):
    """One negative, dot, squared error; pair by pair without dependences; the other pointwise and pairwise losses; and
    alternating least squares, in wall seconds of three rounds."""
    rows = []
    for w in SETS:
        pairs = load(spark, d, w)
        began = time.perf_counter()
        als_baseline(pairs).itemFactors.count()
        rows.append((w, "als", "", "fit_wall_seconds", time.perf_counter() - began))
        for method in ("fused", "jagged", "dense"):
            t = counted(pairs, with_options(SMALL, negatives=1, loss="mse", similarity="dot", batch=256, engine=method))
            rows += [(w, method, "n=1", "epoch_seconds", t["seconds"]), (w, method, "n=1", "loss", t["loss_sum"] / max(1, t["examples"]))]
    pairs = load(spark, d, "events")
    for name in ("pair_sgd", "bpr", "bce", "metric"):
        t = counted(pairs, with_options(PRESETS[name], dim=32))
        rows += [("events", name, "n=1", "epoch_seconds", t["seconds"]), ("events", name, "n=1", "loss", t["loss_sum"] / max(1, t["examples"]))]
    return _frame(spark, rows)


def phases(spark, d):
    """Shares of an epoch."""
    pairs = load(spark, d, "orders")
    rows = []
    for method, agg in (("plain", None), ("aggregated", "average")):
        rows += [("orders", method, "", k, v) for k, v in shares(counted(pairs, with_options(SMALL, aggregator=agg))).items()]
    return _frame(spark, rows)


def cost(spark, d):
    """Dollars of 100 measured epochs of the fused engine on one instance of the cheap platform and of the dense
    one on two of the dear one, their ratio, and the projected one-time training."""
    rows = [("projection", "gpu", "297.7 h x 100", "dollars", metrics.training_cost(297.7 * 3600, 1, 3.06, 100))]
    runs = []
    for w in ("docterms", "talkterms"):
        pairs = load(spark, d, w)
        runs += [(w, "cpu", counted(pairs, with_options(SMALL, batch=256))["seconds"], tuning.EPYC.price, 1), (w, "gpu", counted(pairs, with_options(SMALL, batch=256, engine="dense"))["seconds"], 3.06, 2)]
    priced = metrics.cost_frame(spark.createDataFrame(runs, "workload string, platform string, seconds double, price double, instances int"), 100)
    for r in priced.collect():
        rows += [(r.workload, r.platform, "100 epochs", "dollars", r.dollars), (r.workload, r.platform, "100 epochs", "ratio", r.ratio)]
    return _frame(spark, rows)


def _held_out(spark, d, name):
    cuts = Cuts(spark)
    own, test = split_holdout(load(spark, d, name))
    return cuts.cut(own), cuts.cut(test)


def accuracy(spark, d, sets: tuple[str, ...] = (*SIGNAL, *FLOOR), seeds: tuple[int, ...] = (1,), epochs: int = 2):
    """Recall and NDCG of the dense base method and of the fused one with random and tuned tiled
    sampling, each with and without aggregation; popularity is the floor. Workloads without a signal train one epoch."""
    jobs = []
    for w in sets:
        own, test = _held_out(spark, d, w)
        items = own.select("item_id").distinct().count()
        plan = tuning.plan_tiles(items, own.count(), SMALL.dim, tuning.EPYC)
        size = min(plan.n1, max(16, items // 4))

        def floor(w=w, own=own, test=test):
            return [(w, "popularity", "", "recall20", metrics.recall_at_k(Cuts(spark).cut(popularity_recs(own, 20)), test).first()[0] or 0.0)]

        jobs.append(floor)
        for name, engine, tile in (("base", "dense", 0), ("random", "fused", 0), ("tiled", "fused", size)):
            for agg in (None, "average"):
                for seed in seeds:

                    def one(w=w, own=own, test=test, name=name, engine=engine, tile=tile, agg=agg, seed=seed, refresh=plan.n2, epochs=epochs if w in SIGNAL else 1):
                        model, t = train(own, with_options(SMALL, epochs=epochs, tile=tile, refresh=refresh, aggregator=agg, engine=engine, seed=seed))
                        method = name + ("+agg" if agg else "")
                        setting = f"seed {seed}" + (f" tile {tile} interval {refresh}" if tile else "")
                        return [(w, method, setting, m, v) for m, v in (accuracy_of(model, own, test) | {"loss": t["loss_sum"] / max(1, t["examples"])}).items()]

                    jobs.append(one)
    return _frame(spark, many(jobs))


def _sweep(spark, d, plain, aggregated, name, cfg: TrainConfig = FULL):
    """Every setting against the random sampler at the paper's dimension and negatives, timed one by one, without and with
    aggregation."""
    own, test = _held_out(spark, d, "docterms")
    rows = []
    for agg, settings in ((None, plain), ("average", aggregated)):
        if not settings:
            continue
        method = "tiled" + ("+agg" if agg else "")
        model, base = train(own, with_options(cfg, aggregator=agg))
        rows += [("docterms", method.replace("tiled", "random"), "", m, v) for m, v in (accuracy_of(model, own, test) | {"epoch_seconds": base["seconds"]}).items()]
        for tile, refresh in settings:
            model, t = train(own, with_options(cfg, tile=tile, refresh=refresh, aggregator=agg))
            values = accuracy_of(model, own, test) | {
                "epoch_seconds": t["seconds"], "measured_speedup": base["seconds"] / max(1e-9, t["seconds"]), "predicted_speedup": tuning.neg_speedup(tile, refresh, 4, 100),
                "space": -(-t["examples"] // refresh) * tile, "hit_share": t["tile_hits"] / max(1, t["reads"]), "rows_loaded": t["tile_loads"]}
            rows += [("docterms", method, {"tile": tile, "refresh": refresh}[name], m, v) for m, v in values.items()]
    return _frame(spark, rows)


def tile_sweep(spark, d):
    """Tile size at a fixed interval."""
    return _sweep(spark, d, [(n, 4096) for n in (16, 64, 256, 1024)], [(n, 4096) for n in (64, 1024)], "tile")


def interval_sweep(spark, d):
    """Interval at a fixed tile, from a redraw at every example on."""
    return _sweep(spark, d, [(64, n) for n in (1, 64, 512, 4096)], [], "refresh")


def accumulation(spark, d, seeds: tuple[int, ...] = (1,)):
    """Weight gradients applied every 32 iterations, every iteration (the shared copy), or through a server with stale replicas."""
    rows = []
    for w in ("docterms", *FLOOR):
        own, test = _held_out(spark, d, w)
        for mode in ("local", "shared", "server"):
            for seed in seeds:
                model, t = train(own, with_options(SMALL, aggregator="average", sync_mode=mode, seed=seed))
                rows += [(w, mode, f"seed {seed}", k, v) for k, v in (accuracy_of(model, own, test) | {"epoch_seconds": t["seconds"], "weight_writes": t["weight_writes"]}).items()]
    return _frame(spark, rows)


def scaling(spark, d):
    """The same pairs on 1 to 4 workers, random and tiled; wall seconds of an epoch and parallel efficiency."""
    pairs, rows = load(spark, d, "orders"), []
    for method, opts in (("random", {}), ("tiled", {"tile": 256, "refresh": 2048})):
        times = {}
        for p in (1, 2, 4):
            began = time.perf_counter()
            fit(pairs, with_options(SMALL, plan="merge", blocks=p, **opts)).factors.count()
            times[p] = time.perf_counter() - began
        rows += [("orders", method, r.cores, m, v) for r in metrics.scaling_table(spark, times).collect() for m, v in (("wall_seconds", r.seconds), ("efficiency", r.efficiency))]
    return _frame(spark, rows)


def two_machines(spark, d):
    """The latency model on both published processors, for the items and pairs of the orders; a tile holds no
    more rows than there are items, and lasts no longer than there are pairs."""
    r = workload(spark, d, "orders").agg(F.countDistinct("item_id").alias("items"), F.count("user_id").alias("pairs")).first()
    rows = []
    for name, m in (("epyc", tuning.EPYC), ("a64fx", tuning.A64FX)):
        for tile in sorted({min(n, r["items"]) for n in (64, 128, 512, 1024)}):
            t, level = tuning.read_latency(tile * 128 * 4 * m.workers, m)
            rows.append((name, level, tile, "neg_speedup", tuning.neg_speedup(tile, min(4096, r["pairs"]), t, m.t_mem)))
    return _frame(spark, rows)


EXPERIMENTS = {
    "E1_dense_vs_sparse": dense_vs_sparse, "E2_forward_dense": forward_parts("dense"), "E3_E18_memory": memory, "E4_forward_fused": forward_parts("fused"),
    "E5_epoch_times": epoch_times, "E6_pointwise": pointwise, "E7_phases": phases, "E8_E17_cost": cost, "E9_E12_accuracy": accuracy, "E10_tile_sweep": tile_sweep,
    "E11_interval_sweep": interval_sweep, "E13_accumulation": accumulation, "E14_scaling": scaling, "E15_E16_machines": two_machines,
}
