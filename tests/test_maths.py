import numpy as np
import pytest
from pyspark.sql import functions as F

from cfengine.functions import vectors as V
from cfengine.functions.mix import mix, mix_py
from cfengine.operators import metrics, tuning
from cfengine.operators.blocks import Layer, TrainConfig, _mix_np, block_epoch, scatter_add, with_options


def one(spark, **cols):
    return spark.range(1).select(*[c.alias(k) for k, c in cols.items()]).first()


def vec(*v):
    return F.array(*[F.lit(float(x)) for x in v])


def test_cosine_and_gradient_of_the_worked_example(spark):
    s, t = vec(3, 4), vec(4, 3)
    r = one(spark, x=V.cosine(s, t), st=V.dot(s, t), ss=V.sq_norm(s), g=V.grad_cosine(s, t, V.cosine(s, t), V.sq_norm(s), V.sq_norm(s), V.sq_norm(t)))
    assert (r.x, r.st, r.ss) == (0.96, 24.0, 25.0)
    assert r.g == pytest.approx([0.0448, -0.0336])


def test_zero_vector_has_no_similarity_and_no_gradient(spark):
    s, t = vec(0, 0), vec(4, 3)
    r = one(spark, x=V.cosine(s, t), g=V.grad_cosine(s, t, V.cosine(s, t), V.sq_norm(s), V.sq_norm(s), V.sq_norm(t)))
    assert r.x == 0 and r.g == [0, 0]


def test_contrastive_loss_example(spark):
    assert one(spark, v=V.ccl(F.lit(0.9), vec(0.5, 0.1, -0.2, 0.8), 2, 0.4)).v == pytest.approx(0.35)


def test_draws_agree_in_column_numpy_and_python(spark):
    keys = [(1, 2), (0, 0), (2**33, 5), (77, 10**12)]
    got = [r.m for r in spark.createDataFrame(keys, "a long, b long").select(mix(3, "a", "b").alias("m")).collect()]
    assert sorted(got) == sorted(mix_py(3, *k) for k in keys) == sorted(_mix_np(3, np.array([k[0] for k in keys]), np.array([k[1] for k in keys])).tolist())


@pytest.mark.parametrize("loss,similarity", [("ccl", "cosine"), ("mse", "dot"), ("bce", "dot"), ("bpr", "cosine"), ("metric", "dot")])
def test_kernel_gradient_against_differences(loss, similarity):
    rng = np.random.default_rng(1)
    users, items = rng.normal(size=(3, 4)), rng.normal(size=(6, 4))
    cfg = TrainConfig(dim=4, negatives=3, lr=1e-6, batch=8, loss=loss, similarity=similarity, theta=-1.0 if loss == "ccl" else 0.0)
    u, i = np.array([0, 1, 2]), np.array([1, 3, 5])

    def total(a, b):
        return block_epoch(a.copy(), b.copy(), u, i, u, i, with_options(cfg, lr=0.0)).loss

    a, b = users.copy(), items.copy()
    block_epoch(a, b, u, i, u, i, cfg)
    for m, new, side in ((users, a, 0), (items, b, 1)):
        for r in range(len(m)):
            for k in range(4):
                up, down = [users.copy(), items.copy()], [users.copy(), items.copy()]
                up[side][r, k] += 1e-5
                down[side][r, k] -= 1e-5
                assert (m[r, k] - new[r, k]) / 1e-6 == pytest.approx((total(*up) - total(*down)) / 2e-5, abs=2e-4)


def test_engines_give_the_same_rows_and_sparse_leaves_others_alone():
    rng = np.random.default_rng(2)
    users, items = rng.normal(size=(5, 4)), rng.normal(size=(9, 4))
    out = {}
    for engine in ("fused", "dense"):
        a, b = users.copy(), items.copy()
        block_epoch(a, b, np.array([0, 2]), np.array([1, 3]), np.array([0, 2]), np.array([1, 3]), TrainConfig(dim=4, negatives=2, engine=engine))
        out[engine] = (a, b)
    assert np.allclose(out["fused"][0], out["dense"][0]) and np.allclose(out["fused"][1], out["dense"][1])
    assert (out["fused"][0][[1, 3, 4]] == users[[1, 3, 4]]).all()


def test_scatter_add_with_repeats():
    x = np.zeros((3, 2))
    assert scatter_add(x, np.array([2, 0, 2]), np.ones((3, 2))) == 2
    assert x.tolist() == [[1, 1], [0, 0], [2, 2]]


@pytest.mark.parametrize("flush,writes", [(True, 3), (False, 2)])
def test_accumulation_of_70_gradients(flush, writes):
    layer = Layer(np.zeros((2, 2)), 32, 1.0, flush)
    layer.add(np.ones((70, 2)), np.ones((70, 2)))
    layer.finish()
    assert layer.writes == writes and np.allclose(layer.w, -writes)


def test_tuner_fixtures():
    assert tuning.tile_from_capacity(tuning.EPYC, 128) == 1024
    assert tuning.tile_from_capacity(tuning.Machine(32 << 20, 0, 128), 128) == 512
    assert tuning.neg_speedup(1024, 4096, 4, 100) == pytest.approx(3.571429, abs=1e-6)
    assert tuning.neg_speedup(1024, 4096, 4, 100, "printed") == pytest.approx(3.478261, abs=1e-6)
    assert tuning.neg_speedup(1024, 4096, 4, 100, "approx") == 4
    assert tuning.pos_speedup(0.5, 4, 100) == pytest.approx(1.923077, abs=1e-6)
    assert tuning.refresh_candidates(91_599, 1e6, 1024, 4, 1.0) == (pytest.approx(11179.2, abs=0.1), 4096)
    assert tuning.refresh_candidates(91_599, 1e6, 1024, 4, 1.0, "printed")[1] == 256
    ratio = tuning.neg_time_random(1e6, 64, 100) / tuning.neg_time_tiled(1e6, 64, 1024, 4096, 4, 100)
    assert ratio == pytest.approx(tuning.neg_speedup(1024, 4096, 4, 100))


def test_published_costs():
    assert metrics.training_cost(297.7 * 3600, 1, 3.06, 100) == pytest.approx(91_096.2)
    assert 64 * 0.637 == pytest.approx(40.8, abs=0.05)
    shares = [metrics.memory_model(u, i, 128, 256e9, o) for u, i, o in ((0.81e6, 1.56e6, 8.86), (4.57e6, 3.12e6, 7.35), (20.98e6, 9.35e6, 6.33))]
    assert shares == pytest.approx([0.042, 0.113, 0.384], abs=1e-3)
    assert metrics.memory_model(20.98e6, 9.35e6, 128, 10e9, 8) is None


def test_bad_settings_are_refused():
    for bad in ({"negatives": 0}, {"theta": 2.0}, {"mu": -1.0}, {"dim": 0}):
        with pytest.raises(ValueError):
            TrainConfig(**bad)
