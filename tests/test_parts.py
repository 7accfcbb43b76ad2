import numpy as np
import pyarrow as pa
import pytest

from cfengine import queries
from cfengine.operators import blocks, trainer
from cfengine.operators.blocks import TrainConfig


def _rows(df):
    return {tuple(r)[:-1]: r[-1] for r in df.collect()}


#: Queries whose epoch is one step over a whole cell.
ONE_STEP = [
    "fused_step",
    "jagged_engine_step",
    "merged_epoch",
    "agg_step",
    "agg_accumulated_m32",
    "agg_every_iteration",
    "agg_parameter_server",
    "agg_weight_grad",
    "step_bpr",
    "step_metric",
]


@pytest.mark.parametrize("name", ONE_STEP)
def test_a_step_in_parts_equals_the_whole_one(spark, sf, monkeypatch, name):
    whole = _rows(queries.QUERIES[name](spark, sf))
    sizes = []
    monkeypatch.setattr(trainer, "PART_PAIRS", 700)
    monkeypatch.setattr(trainer, "ROUND_PARTS", 3)
    monkeypatch.setattr(trainer, "parts_of", lambda n, cfg, f=trainer.parts_of: sizes.append(f(n, cfg)) or sizes[-1])
    parts = _rows(queries.QUERIES[name](spark, sf))
    assert max(sizes) > 3
    assert parts.keys() == whole.keys() and all(abs(v - whole[k]) < 2e-6 for k, v in parts.items())


def test_a_part_hashes_no_more_than_a_piece_at_a_time(monkeypatch):
    """A sum over a part's pairs needs no seeded order, whose arrays grow with the part."""
    n, sizes = 300_000, []
    cfg = TrainConfig(dim=2, negatives=4, batch=10**9)
    at = np.arange(n)
    monkeypatch.setattr(blocks, "_mix_np", lambda seed, *keys, f=blocks._mix_np: sizes.append(max(len(k) for k in keys)) or f(seed, *keys))
    rows, moves = [np.random.default_rng(k).normal(size=(7_000, 2)) for k in range(2)], []
    c = blocks.block_epoch(*rows, at % 7_000, at * 11 % 7_000, at % 7_000, at * 11 % 7_000, cfg, moves=moves)
    assert c.examples == n and len(moves) == 2
    assert max(sizes) <= blocks.PIECE_BYTES // (8 * 4)


def test_a_part_comes_and_goes_in_batches():
    """A part's rows stood in an Arrow table beside the kernel's arrays, and went back as one batch."""
    n, cfg = 3 * trainer.GIVEN_ROWS, TrainConfig(dim=2, negatives=1, batch=10**9)
    vec = np.random.default_rng(1).normal(size=(n, 2))
    rows = pa.table({"side": ["item"] * n + ["user", "pair"], "id": [*range(n)][::-1] + [7, 7], "other": [None] * (n + 1) + [5], "vec": [*vec.tolist(), [0.5, 0.5], None], "state": pa.array([None] * (n + 2), pa.float64())})
    got = trainer._Stream(iter(rows.to_batches(max_chunksize=1000)), 2)
    assert got.pairs["user_id"].tolist() == [7] and got.pairs["item_id"].tolist() == [5]
    ids, held, _ = got.side("item", 2)
    assert ids.tolist() == [*range(n)] and np.array_equal(held, vec[::-1]) and not got.piles.get("item")
    out = [*trainer._part(cfg, 0, None, None, True)(iter(rows.to_batches(max_chunksize=1000)))]
    assert max(b.num_rows for b in out) <= trainer.GIVEN_ROWS and {s for b in out for s in b["side"].to_pylist()} >= {"user", "item", "stats"}


@pytest.mark.parametrize("engine", ["fused", "jagged", "dense"])
def test_a_worker_holds_one_stretch_of_pairs(monkeypatch, engine):
    """Pairs come in their seeded order and are trained as they come: a worker held all of them, their order and a copy of its rows."""
    n, cfg = 3000, TrainConfig(dim=4, negatives=3, batch=64, tile=16, refresh=100, engine=engine)
    rng = np.random.default_rng(1)
    at = np.unique(rng.integers(0, 90 * 70, n))
    u, i = at // 70, at % 70
    users, items = (np.concatenate((rng.normal(size=(m, 4)), np.full((1, 4), 7.0))) for m in (90, 70))  # the last rows have no pair
    order = np.lexsort((i, u, blocks._mix_np(cfg.seed, u, i)))
    rows = pa.table({
        "key": [trainer.USER_KEY] * 91 + [trainer.ITEM_KEY] * 71 + [0] * len(at),
        "id": [*range(91), *range(71), *u[order]],
        "other": [None] * 162 + i[order].tolist(),
        "vec": [*users.tolist(), *items.tolist()] + [None] * len(at),
        "state": pa.array([None] * (162 + len(at)), pa.float64()),
    })
    sizes = []
    monkeypatch.setattr(trainer, "STRETCH_PAIRS", 150)
    monkeypatch.setattr(blocks.Pass, "go", lambda self, a, *rest, f=blocks.Pass.go: sizes.append(len(a)) or f(self, a, *rest))
    out = pa.Table.from_batches(trainer._in_order(iter(rows.to_batches(max_chunksize=130)), cfg, 0)).to_pydict()
    assert len(sizes) > 5 and max(sizes) == 200 and sum(sizes) == len(at)
    blocks.block_epoch(users, items, u, i, u, i, cfg)
    for side, own in (("user", users), ("item", items)):
        here = [k for k, s in enumerate(out["side"]) if s == side]
        assert [out["id"][k] for k in here] == [*range(len(own))]
        assert np.array_equal([out["vec"][k] for k in here], own)


@pytest.mark.parametrize("opts", [{}, {"tile": 16, "refresh": 50}, {"optimizer": "adagrad", "l2": 0.01}, {"batch": 1100, "tile": 16, "refresh": 1500}], ids=["plain", "tiled", "adagrad_l2", "pieces"])
@pytest.mark.parametrize("helped", [False, True])
def test_dense_batches_are_worked_off_near_their_rows(monkeypatch, opts, helped):
    """Every dense batch went through the whole tables; the rows, losses and counts are those of that to the last bit."""
    cfg, sizes, got = TrainConfig(**({"dim": 4, "negatives": 3, "batch": 20, "engine": "dense"} | opts)), [], []
    rng = np.random.default_rng(1)
    u, i = rng.integers(0, 5000, 4000), rng.integers(0, 3000, 4000)
    first = [rng.normal(size=(n, 4)) for n in (5000, 3000)]
    monkeypatch.setattr(blocks._Copying, "train", lambda self, tables, *rest, f=blocks._Copying.train: sizes.append(sum(len(v) for v, _ in tables)) or f(self, tables, *rest))
    monkeypatch.setattr(blocks, "PIECE_BYTES", 1 << 10)  # a piece has 1,024 examples
    for runs, near in (((1,), 1 << 30), (blocks.RUNS, 1 << 12)):
        sizes.clear()
        monkeypatch.setattr(blocks, "RUNS", runs)
        monkeypatch.setattr(blocks, "NEAR_BYTES", near)
        rows, states = [v.copy() for v in first], tuple(np.zeros(len(v)) for v in first)
        run = blocks.Pass(*rows, cfg, 0, states=states, helped=helped)
        run.go(u, i, u, i)
        c = run.finish()
        got.append((*rows, *states, c.loss, c.rows_written, c.examples))
        assert max(sizes) == 8000 if runs == (1,) or cfg.batch > 1000 else max(sizes) < 1500
    assert all(np.array_equal(a, b) for a, b in zip(*got, strict=True))
    assert got[1][5] == 8000 * (200 if cfg.batch == 20 and not cfg.tile else 240 if cfg.batch == 20 else 5)


def test_a_cell_is_sorted_by_its_key_first(spark):
    """Rows that agree in the first column are compared as a whole; the first was the cell, which is the same for all of them."""
    pairs = spark.range(50).selectExpr("cast(0 as int) cell", "id % 7 user_id", "id item_id")
    rows = spark.createDataFrame([(0, s, k, [0.1, 0.2], None) for s, n in (("user", 7), ("item", 50)) for k in range(n)], "cell int, side string, id long, vec array<double>, state double")
    out = trainer._ordered_cells(pairs, rows, 1, TrainConfig(dim=2, negatives=1), 0)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Sort [key" in plan and "Sort [cell" not in plan
    assert out.where("side = 'user'").count() == 7 and out.where("side = 'item'").count() == 50
