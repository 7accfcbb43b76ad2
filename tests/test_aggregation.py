import numpy as np
import pytest
from pyspark.sql import functions as F

from cfengine.operators import aggregate, predict, trainer
from cfengine.operators.blocks import Histories, TrainConfig, block_epoch, with_options
from cfengine.operators.trainer import Model, fit
from cfengine.sources.feedback import user_history, workload

HIST = [np.array([0, 2, 5]), np.array([], np.int64), np.array([4]), np.array([1, 1, 3])]


def pooled(hist, items, kind, users, params, away=None):
    rows, lens = np.concatenate(hist).astype(np.int64), np.array([len(h) for h in hist])
    return aggregate.pool(items[rows], rows, lens, kind, users, params, away)


def histories(hist):
    return Histories(np.concatenate(hist), np.concatenate(([0], np.cumsum([len(h) for h in hist]))))


def _numeric(f, x, step=1e-6):
    out = np.zeros_like(x)
    for at in np.ndindex(*x.shape):
        a, b = x.copy(), x.copy()
        a[at] += step
        b[at] -= step
        out[at] = (f(a) - f(b)) / (2 * step)
    return out


@pytest.mark.parametrize("kind", aggregate.KINDS)
def test_gradients_equal_central_differences(kind):
    rng = np.random.default_rng(3)
    items, users, g = rng.normal(size=(6, 3)), rng.normal(size=(4, 3)), rng.normal(size=(4, 3))
    params = aggregate.first_params(kind, 3, 1)
    params = params + rng.normal(0, 0.3, params.shape)
    value = lambda i, u, p: float((g * pooled(HIST, i, kind, u, p).vec).sum())
    g_hist, g_user, g_att = aggregate.backward(pooled(HIST, items, kind, users, params), kind, g, params)
    g_items = np.zeros_like(items)
    np.add.at(g_items, np.concatenate(HIST).astype(int), g_hist)
    assert np.allclose(g_items, _numeric(lambda x: value(x, users, params), items), atol=1e-6)
    if kind == "user_attention":
        assert np.allclose(g_user, _numeric(lambda x: value(items, x, params), users), atol=1e-6)
    if g_att is not None:
        expected = _numeric(lambda x: value(items, users, x), params)[3:]
        assert np.allclose(g_att(0, 4), expected, atol=1e-6)
        assert np.allclose(g_att(0, 2) + g_att(2, 4), expected, atol=1e-6)


def _sums_away(rest, items, kind, users, params):
    """num, den, off by hand for histories that are elsewhere."""
    dim = items.shape[1]
    out = np.zeros((len(rest), dim + 2))
    for n, h in enumerate(rest):
        q = {"average": np.zeros(dim), "self_attention": params[-1], "user_attention": users[n]}[kind]
        out[n, dim + 1] = np.abs(q).sum()
        for t in items[h]:
            w = 1.0 if kind == "average" else np.exp(q @ np.tanh(params[dim : 2 * dim] @ t + params[2 * dim]) - out[n, dim + 1])
            out[n, :dim] += w * t
            out[n, dim] += w
    return out


@pytest.mark.parametrize("kind", aggregate.KINDS)
def test_histories_split_over_blocks_pool_like_whole_ones(kind):
    rng = np.random.default_rng(5)
    items, users, g = rng.normal(size=(6, 3)), rng.normal(size=(4, 3)) * 3, rng.normal(size=(4, 3))
    params = aggregate.first_params(kind, 3, 1)
    params = params + rng.normal(0, 0.8, params.shape)
    here, rest = [h[:k] for h, k in zip(HIST, (1, 0, 1, 0), strict=True)], [h[k:] for h, k in zip(HIST, (1, 0, 1, 0), strict=True)]
    away = _sums_away(rest, items, kind, users, params)
    whole = pooled(HIST, items, kind, users, params)
    split = pooled(here, items, kind, users, params, away)
    assert np.allclose(split.vec, whole.vec)
    g_hist, g_user, g_att = aggregate.backward(split, kind, g, params)
    value = lambda i, u, p: float((g * pooled(here, i, kind, u, p, away).vec).sum())
    g_items = np.zeros_like(items)
    np.add.at(g_items, np.concatenate(here).astype(int), g_hist)
    assert np.allclose(g_items, _numeric(lambda x: value(x, users, params), items), atol=1e-6)
    if kind == "user_attention":
        assert np.allclose(g_user, _numeric(lambda x: value(items, x, params), users), atol=1e-6)
    if g_att is not None:
        assert np.allclose(g_att(0, 4), _numeric(lambda x: value(items, users, x), params)[3:], atol=1e-6)


@pytest.mark.parametrize("kind", ["average", "user_attention"])
def test_cells_get_the_history_they_do_not_hold(spark, sf, kind):
    cfg = TrainConfig(dim=3, aggregator=kind, history=7, blocks=3)
    pairs = trainer.mark_recent(workload(spark, sf, "orders").select("user_id", "item_id").distinct().withColumn("at", F.col("item_id") % 5), 7)
    dealt = trainer.rotation(pairs, cfg).cache()
    factors = trainer.init_factors(pairs, cfg).cache()
    params = aggregate.first_params(kind, 3, 1)
    got = {(r.id, r.turn): r.vec for r in trainer.away_sums(dealt, factors, params, cfg).collect()}
    vec = {(r.side, r.id): np.array(r.vec) for r in factors.collect()}
    rows = dealt.toPandas()
    assert (rows[rows.recent].groupby("user_id").size() <= 7).all()
    newest = rows.sort_values(["user_id", "at", "item_id"], ascending=[True, False, False]).groupby("user_id").head(7)
    assert set(zip(newest.user_id, newest.item_id, strict=True)) == set(zip(*(rows[rows.recent][c] for c in ("user_id", "item_id")), strict=True))
    ids = sorted({i for s, i in vec if s == "item"})
    items = np.stack([vec["item", i] for i in ids])
    for (user, turn), have in got.items():
        rest = newest[(newest.user_id == user) & (newest.turn != turn)].item_id
        expected = _sums_away([np.searchsorted(ids, rest)], items, kind, np.stack([vec["user", user]]), params)[0]
        assert np.allclose(have, expected)
    assert set(got) == set(zip(rows.user_id, rows.turn, strict=True))


def test_empty_histories_pool_to_zero():
    for kind in aggregate.KINDS:
        p = pooled([np.array([], np.int64)] * 2, np.ones((3, 4)), kind, np.ones((2, 4)), aggregate.first_params(kind, 4, 1))
        assert (p.vec == 0).all() and p.vec.shape == (2, 4)


@pytest.mark.parametrize("kind", [None, *aggregate.KINDS])
def test_engines_compute_the_same(kind):
    rng = np.random.default_rng(2)
    users, items = rng.normal(size=(4, 4)), rng.normal(size=(6, 4))
    u, i = np.array([0, 0, 2, 3, 3]), np.array([1, 3, 5, 0, 2])
    base = TrainConfig(dim=4, negatives=3, batch=3, aggregator=kind, sync=2)
    out = []
    for engine in ("fused", "dense", "sparse", "jagged"):
        a, b, layer = users.copy(), items.copy(), None
        if kind:
            layer = aggregate.Layer(aggregate.first_params(kind, 4, 1), 2, base.lr)
        c = block_epoch(a, b, u, i, u + 10, i + 20, with_options(base, engine=engine), 0, layer, histories(HIST))
        assert (c.copied_bytes > 0) == (engine != "fused")
        out.append((a, b) if layer is None else (a, b, layer.w))
    for other in out[1:]:
        assert all(np.allclose(x, y) for x, y in zip(out[0], other, strict=True))


@pytest.mark.parametrize("kind", [None, "average", "user_attention"])
@pytest.mark.parametrize("loss", ["ccl", "mse", "bpr", "metric"])
def test_a_buffered_tile_computes_what_the_matrix_does(kind, loss):
    """Tiles of all items: the buffer, its products and its write-back against plain gathers of the same draws."""
    rng = np.random.default_rng(2)
    users, items = rng.normal(size=(9, 4)), rng.normal(size=(12, 4))
    u, i = rng.integers(0, 4, 40), rng.integers(0, 12, 40)
    base = TrainConfig(dim=4, negatives=3, batch=5, aggregator=kind, sync=2, loss=loss, similarity="cosine" if loss == "ccl" else "dot", tile=12, refresh=10)
    out = []
    for opts in ({}, {"writeback": "step"}, {"engine": "sparse"}, {"tile": 7}, {"tile": 7, "engine": "sparse"}, {"tile": 7, "tile_replace": True}, {"tile": 7, "tile_replace": True, "engine": "sparse"}):
        cfg = with_options(base, **opts)
        a, b, layer = users.copy(), items.copy(), None
        if kind:
            layer = aggregate.Layer(aggregate.first_params(kind, 4, 1), 2, base.lr)
        c = block_epoch(a, b, u, i, u + 10, i + 20, cfg, 0, layer, histories([*HIST, *HIST, np.array([3])]))
        out.append((a, b))
        if cfg.engine == "fused":
            assert c.tile_hits > 0 and c.tile_loads == 4 * cfg.tile
    assert np.allclose(out[0][1], out[1][1]) and np.allclose(out[0][1], out[2][1]) and np.allclose(out[3][1], out[4][1])
    assert np.isfinite(out[5][1]).all() and not np.allclose(out[5][1], items)


def test_server_replicas_lag_and_arrive():
    rng = np.random.default_rng(1)
    x, g = rng.normal(size=(20, 3)), rng.normal(size=(20, 3))
    local, server = aggregate.Layer(np.zeros((3, 3)), 4, 0.1), aggregate.ServerLayer(np.zeros((3, 3)), 4, 0.1, age=2)
    local.add(x, g)
    server.add(x, g)
    assert not np.allclose(local.w, server.w) and server.writes == 3
    server.finish()
    assert np.allclose(local.w, server.w) and server.writes == local.writes == 5


def test_parameters_survive_cells_epochs_and_files(spark, sf, tmp_path):
    pairs = workload(spark, sf, "orders")
    base = TrainConfig(dim=4, negatives=2, blocks=2, plan="rotate", aggregator="self_attention", history=5)
    one, two = (fit(pairs, with_options(base, epochs=n)) for n in (1, 2))
    start = aggregate.first_params("self_attention", 4, base.seed)
    assert one.weights.shape == start.shape and not np.allclose(one.weights, start)
    assert not np.allclose(one.weights, two.weights)
    assert set(r.side for r in one.factors.select("side").distinct().collect()) == {"user", "item"}
    one.save(str(tmp_path / "m"))
    back = Model.load(spark, str(tmp_path / "m"), base)
    assert np.allclose(back.weights, one.weights) and back.factors.count() == one.factors.count()
    again = fit(pairs.repartition(5), base)
    assert np.allclose(again.weights, one.weights)


@pytest.mark.parametrize("kind", aggregate.KINDS)
def test_aggregated_users_equal_the_kernels_rows(spark, sf, kind):
    pairs = workload(spark, sf, "orders")
    cfg = TrainConfig(dim=4, aggregator=kind, history=7)
    params = aggregate.first_params(kind, 4, 1)
    vec = lambda seed: F.transform(F.array(*[F.lit(k) for k in range(4)]), lambda k: F.sin(F.col("id") * 3 + k + seed))
    users = pairs.select(F.col("user_id").alias("id")).distinct().union(spark.range(10**6, 10**6 + 1)).withColumn("vec", vec(0.5))
    items = pairs.select(F.col("item_id").alias("id")).distinct().withColumn("vec", vec(1.5))
    hist = user_history(pairs, 7)
    got = {r.id: r.vec for r in predict.aggregated_users(users, items, hist, params, cfg).collect()}
    u, t, h = users.toPandas(), items.toPandas(), {r.user_id: r.hist for r in hist.collect()}
    at = {k: n for n, k in enumerate(t["id"])}
    s = np.stack(u["vec"])
    p = pooled([np.array([at[x] for x in h.get(k, [])], np.int64) for k in u["id"]], np.stack(t["vec"]), kind, s, params)
    expected = cfg.gate * s + (1 - cfg.gate) * (p.vec @ params[:4])
    assert len(got) == len(u) and np.allclose([got[k] for k in u["id"]], expected)


@pytest.mark.parametrize("kind", aggregate.KINDS)
def test_sums_elsewhere_come_by_turns_as_they_do_at_once(spark, sf, monkeypatch, kind):
    """All users' sums for all blocks lay on disk together, and the shuffle of a row a pair before them."""
    from cfengine.operators import trainer
    from cfengine.plans.cuts import Cuts
    from cfengine.sources.feedback import workload

    cfg = TrainConfig(dim=3, aggregator=kind, history=7, blocks=3)
    pairs = workload(spark, sf, "orders").where("user_id < 40").selectExpr("user_id", "item_id", "unix_micros(cast(ts as timestamp)) as at")
    dealt = Cuts(spark).cut(trainer.rotation(trainer.mark_recent(pairs, 7), cfg))
    factors = Cuts(spark).cut(trainer.init_factors(pairs, cfg))
    params = aggregate.first_params(kind, 3, 1)
    want = {(r.id, r.turn): r.vec for r in trainer.away_sums(dealt, factors, params, cfg).collect()}
    monkeypatch.setattr(trainer, "AWAY_BYTES", 20_000)
    away = trainer.Away(dealt, factors, params, cfg, Cuts(spark))
    got = [r for turn in range(3) for r in away.turn(turn).collect()]
    assert len(away.made) > 1 and len(got) == len(want)
    assert all(np.allclose(r.vec, want[r.id, r.turn], atol=1e-12) for r in got)


def test_a_run_keeps_no_tables_that_nothing_reads(spark, sf):
    """An experiment's runs left their pairs, twice, and their factors on disk beside those of the next run."""
    from cfengine.operators.trainer import fit
    from cfengine.plans.files import exists, listed
    from cfengine.sources.feedback import workload

    m = fit(workload(spark, sf, "orders").where("user_id < 40"), TrainConfig(dim=3, negatives=2, aggregator="average", history=7, blocks=2, plan="rotate"))
    assert m.factors.count() and len(listed(spark, m.cuts.base)) <= 4  # dealt pairs, first factors, the last two turns
    m.drop()
    assert not exists(spark, m.cuts.base)
