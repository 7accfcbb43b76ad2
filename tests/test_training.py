import numpy as np
import pytest
from pyspark.sql import functions as F

from cfengine.functions import vectors as V
from cfengine.operators import metrics, predict, relational, sampling
from cfengine.operators.blocks import TrainConfig, _mix_np, block_epoch, init_rows, with_options
from cfengine.operators.trainer import block_of, fit, rotation
from cfengine.plans import plancheck
from cfengine.plans.planner import explain_plan
from cfengine.sources.feedback import index_ids, kcore, planted, split_holdout, user_history, workload


@pytest.fixture(scope="module")
def pairs(spark, sf):
    return workload(spark, sf, "orders").cache()


def test_feedback_edges(spark):
    raw = spark.createDataFrame([(1, 2), (1, 2), (None, 3), (4, None)], "a long, b long")
    from cfengine.sources.feedback import implicit_pairs

    assert implicit_pairs(raw, "a", "b").collect() == [(1, 2)]
    assert implicit_pairs(raw.limit(0), "a", "b").count() == 0


def test_index_is_dense_and_ordered(pairs):
    rows = index_ids(pairs, "item_id").orderBy("id").collect()
    assert [r.idx for r in rows] == list(range(len(rows)))


def test_split_is_a_partition(pairs):
    train, test = split_holdout(pairs)
    assert train.count() + test.count() == pairs.count() and train.join(test, ["user_id", "item_id"]).count() == 0


def test_history_is_bounded(pairs):
    assert user_history(pairs, 5).agg(F.max(F.size("hist"))).first()[0] == 5


def test_kcore_leaves_frequent(pairs):
    out = kcore(pairs.select("user_id", "item_id"), 10, 10, 2)
    assert out.groupBy("item_id").count().agg(F.min("count")).first()[0] >= 10


def test_rotation_covers_once_and_shares_nothing(pairs):
    cfg = TrainConfig(blocks=4)
    dealt = rotation(pairs, cfg).withColumn("iblk", block_of("item", "item_id", cfg))
    assert dealt.count() == pairs.count()
    assert dealt.groupBy("turn", "iblk").agg(F.countDistinct("cell").alias("c")).where("c > 1").isEmpty()


def test_tiled_draws_stay_in_their_tile(spark, pairs):
    items = index_ids(pairs, "item_id")
    drawn = sampling.sample_tiled(pairs, items, 3, 16, 100, 2)
    tiles = sampling.tile_rows(items, 2, 40, 16)
    hit = sampling.hit_ratio(drawn.select("worker", "refresh", "item_id"), tiles).first()[0]
    assert hit == 1.0
    assert sorted(drawn.collect()) == sorted(sampling.sample_tiled(pairs.repartition(7), items, 3, 16, 100, 2).collect())


def test_uniform_draws_are_uniform(spark):
    h = _mix_np(7, np.arange(200_000), np.int64(3)) % 97
    c = np.bincount(h, minlength=97)
    assert ((c - c.mean()) ** 2 / c.mean()).sum() < 140


def test_relational_step_equals_kernel(spark, pairs):
    """One synchronous step over the same draws: the plan of joins and the fused kernel agree."""
    some = pairs.select("user_id", "item_id")
    cfg = TrainConfig(dim=6, negatives=3, batch=10**9, seed=1)
    p = some.toPandas()
    u_ids, u = np.unique(p["user_id"], return_inverse=True)
    i_ids, i = np.unique(p["item_id"], return_inverse=True)
    users, items = init_rows(u_ids, 0, cfg), init_rows(i_ids, 1, cfg)
    block_epoch(users, items, u, i, p["user_id"].to_numpy(), p["item_id"].to_numpy(), cfg)
    idx = index_ids(some, "item_id")
    negs = sampling.sample_uniform(some, idx, 3, seed=1 + 13)
    ids = some.select(F.lit("user").alias("side"), F.col("user_id").alias("id")).union(some.select(F.lit("item"), "item_id")).distinct()
    f = ids.withColumn("vec", F.when(F.col("side") == "user", V.init_vector(1, "id", 6)).otherwise(V.init_vector(2, "id", 6))).cache()
    got = relational.step(some, negs, f, relational.StepConfig(6, 3)).collect()
    for r in got:
        own, at = (users, u_ids) if r.side == "user" else (items, i_ids)
        assert np.allclose(r.vec, own[np.searchsorted(at, r.id)], atol=1e-9)


def test_reuse_keeps_one_set_of_sums(spark, pairs):
    cfg = relational.StepConfig()
    rows = relational.examples(pairs, sampling.sample_uniform(pairs, index_ids(pairs, "item_id"), 2))
    f = spark.range(400).select("id", F.array(F.lit(1.0), F.lit(2.0)).alias("vec"))
    f = f.cache()
    scored = relational.forward(rows, f, f, cfg)
    assert plancheck.occurrences(relational.gradients(scored, cfg), "aggregate(zip_with") == 3
    assert plancheck.occurrences(relational.gradients(scored, relational.StepConfig(reuse=False)), "aggregate(zip_with") == 6


def test_planted_communities_are_learned(spark):
    data = planted(spark, 300, 150, 5).cache()
    train, test = split_holdout(data)
    base = {"dim": 16, "negatives": 8, "epochs": 6, "lr": 0.05, "blocks": 3}
    values = {}
    for name, opts in {"block": {"plan": "block"}, "rotate": {"plan": "rotate"}, "merge": {"plan": "merge"}, "tiled": {"plan": "rotate", "tile": 32, "refresh": 128}, "agg": {"plan": "rotate", "aggregator": "average"}}.items():
        m = fit(train, TrainConfig(**base, **opts))
        recs = predict.recommend(m.user_factors, m.item_factors, train, 20)
        values[name] = metrics.recall_at_k(recs, test).first()[0]
    assert min(values.values()) > 0.3, values  # chance is 20 of 150


def test_metrics_by_hand(spark):
    recs = spark.createDataFrame([(1, 1, 10), (1, 2, 11), (1, 3, 12)], "user_id long, rank int, item_id long")
    held = spark.createDataFrame([(1, 10), (1, 12), (1, 99), (2, 5)], "user_id long, item_id long")
    assert metrics.recall_at_k(recs, held.where("user_id = 1"), 3).first()[0] == pytest.approx(2 / 3, abs=1e-6)
    assert metrics.ndcg_at_k(recs, held.where("user_id = 1"), 3).first()[0] == pytest.approx(0.703918, abs=1e-6)
    assert metrics.recall_at_k(recs, held, 3).first()[0] == pytest.approx(1 / 3, abs=1e-6)


def test_user_who_has_seen_all_gets_nothing(spark):
    f = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 1.0])], "id long, vec array<double>")
    seen = spark.createDataFrame([(1, 1), (1, 2)], "user_id long, item_id long")
    assert {r.user_id for r in predict.recommend(f, f, seen, 5).collect()} == {2}


def test_blocks_follow_the_sizes_alone(pairs):
    from cfengine.operators.blocks import blocks_for
    from cfengine.plans.planner import CELL_BYTES, CELL_PAIRS, settle

    cfg = TrainConfig()
    assert "plan=rotate blocks=1" in explain_plan(pairs, cfg) and settle(pairs, TrainConfig(plan="merge", blocks=3)).blocks == 3
    last = 0
    for n in (1, 10**5, 10**6, 10**8, 10**11):
        q = blocks_for(n, n // 50, n // 500, cfg, CELL_PAIRS, CELL_BYTES)
        assert q >= last and n <= q * q * CELL_PAIRS and 2 * (n // 50 + n // 500) * cfg.dim * 8 <= q * CELL_BYTES
        last = q
    tuned = settle(pairs, TrainConfig(tile=-1, dim=64))
    assert 0 < tuned.tile * 64 * 4 <= 1 << 20 and tuned.refresh >= 1


def test_a_sub_epoch_reads_its_own_pairs(spark, pairs):
    from cfengine.plans.cuts import Cuts

    cfg = TrainConfig(blocks=3)
    dealt = Cuts(spark).cut(rotation(pairs.select("user_id", "item_id"), cfg).repartition("turn", "cell"), "turn")
    one = dealt.where("turn = 1")
    assert "PartitionFilters: [isnotnull(turn" in plancheck.plan_text(one)
    assert one.count() == rotation(pairs, cfg).where("turn = 1").count()


def test_scan_is_pruned_and_filtered(spark, sf):
    plan = workload(spark, sf, "events")
    pushed = " ".join(plancheck.pushed_filters(plan))
    assert "In(event_type" in pushed.replace(" ", "")
    assert "value" not in plancheck.plan_text(plan).split("ReadSchema:")[1].split("\n")[0]


def test_training_goes_on_after_its_last_snapshot(pairs, tmp_path):
    base = TrainConfig(dim=4, negatives=2, blocks=2, plan="rotate", aggregator="average", history=5)
    whole = fit(pairs, with_options(base, epochs=3))
    at = str(tmp_path / "snaps")
    fit(pairs, with_options(base, epochs=2), snapshots=at)
    rest = fit(pairs, with_options(base, epochs=3), snapshots=at)
    assert [h["epoch"] for h in rest.history] == [2, 2]
    a, b = ({(r.side, r.id): r.vec for r in m.factors.collect()} for m in (whole, rest))
    assert a.keys() == b.keys() and all(np.allclose(a[k], b[k]) for k in a)
    assert np.allclose(whole.weights, rest.weights)


def test_training_stops_when_the_loss_does_not_fall(pairs):
    flat = fit(pairs, TrainConfig(dim=4, negatives=2, blocks=1, plan="rotate", epochs=6, lr=0.0, patience=2))
    assert len(flat.history) == 3


def test_losses_of_kernel_and_plan_agree(spark, pairs):
    """One synchronous step of every loss, by joins and by the kernel."""
    some = pairs.select("user_id", "item_id").where("user_id < 40")
    for loss in ("mse", "bce", "bpr", "metric"):
        base = TrainConfig(dim=4, negatives=3, batch=10**9, blocks=1, loss=loss, similarity="dot", l2=0.01)
        a, b = ({(r.side, r.id): r.vec for r in fit(some, with_options(base, plan=p)).factors.collect()} for p in ("block", "relational"))
        assert a.keys() == b.keys() and all(np.allclose(a[k], b[k], atol=1e-9) for k in a), loss


def test_adagrad_and_float32(pairs):
    for opts in ({"optimizer": "adagrad"}, {"precision": "float32"}, {"optimizer": "adagrad", "tile": 16, "refresh": 64}):
        m = fit(pairs, TrainConfig(dim=8, negatives=4, epochs=3, blocks=2, plan="rotate", **opts))
        loss = {}
        for h in m.history:
            loss[h["epoch"]] = loss.get(h["epoch"], 0) + h["loss_sum"]
        assert loss[2] < loss[0], opts


def test_core_is_a_fixpoint(pairs):
    out = kcore(pairs.select("user_id", "item_id"), 34, 26)
    if out.count():
        for side, least in (("user_id", 34), ("item_id", 26)):
            assert out.groupBy(side).count().agg(F.min("count")).first()[0] >= least


def test_hot_keys_are_dealt(spark):
    """A value that half of all rows hold: its pairs are met in parts, and none is lost."""
    from cfengine.plans.cuts import Cuts
    from cfengine.plans.skew import meetings, split_join

    rows = [(u, 1) for u in range(60)] + [(u, 2 + u % 20) for u in range(60)]
    df = spark.createDataFrame(rows, "user_id long, item_id long")
    want = sorted((a, b) for i in {i for _, i in rows} for a in {u for u, j in rows if j == i} for b in {u for u, j in rows if j == i} if a < b)
    assert sorted(map(tuple, meetings(df, "user_id", "item_id", Cuts(spark), 8).collect())) == want
    names = spark.createDataFrame([(1, "x"), (1, "y"), (3, "z")], "item_id long, name string")
    got = split_join(df, names, "item_id", "user_id", Cuts(spark), 8).select("user_id", "item_id", "name").collect()
    assert sorted(map(tuple, got)) == sorted((u, i, n) for u, i in rows for j, n in ((1, "x"), (1, "y"), (3, "z")) if i == j)


def test_truncated_factors_equal_the_best_product(spark):
    from cfengine.operators.baselines import truncated_factors

    df = planted(spark, 60, 40, 4).cache()
    users, items, values = truncated_factors(df, 4, 20)
    p = df.toPandas()
    m = np.zeros((60, 40))
    m[p["user_id"], p["item_id"]] = 1
    best = np.linalg.svd(m)
    assert np.allclose(values, best[1][:4], rtol=1e-3)
    u, t = np.zeros((60, 4)), np.zeros((40, 4))
    for r in users.collect():
        u[r.id] = r.vec
    for r in items.collect():
        t[r.id] = r.vec
    assert np.allclose(u @ t.T, (best[0][:, :4] * best[1][:4]) @ best[2][:4], atol=0.05)


def test_stage_metrics_count_a_shuffle(spark):
    def work():
        spark.range(10_000, numPartitions=4).groupBy((F.col("id") % 100).alias("k")).count().collect()

    m = metrics.stage_metrics(spark, work)
    assert m["stages"] >= 2 and m["tasks"] >= 5 and m["shuffle_written"] > 0 and m["spilled"] == 0
