from math import sqrt

import pytest

from cfengine import queries
from cfengine.operators import baselines
from cfengine.plans.files import listed
from cfengine.sources.feedback import workload


@pytest.mark.parametrize("own", ["user_id", "item_id"])
@pytest.mark.parametrize("sim", ["cosine", "jaccard"])
def test_neighbours_in_blocks_equal_brute_force(spark, sf, monkeypatch, own, sim):
    """Small blocks, lists sent in turns, and lists dealt into parts."""
    monkeypatch.setattr(baselines, "BLOCK_MEETINGS", 3000)
    monkeypatch.setattr(baselines, "SENT", 20_000)
    monkeypatch.setattr(baselines, "SHARE", 5)
    pairs = workload(spark, sf, "orders").select("user_id", "item_id").where("item_id < 60")
    other = "item_id" if own == "user_id" else "user_id"
    has: dict = {}
    for r in pairs.collect():
        has.setdefault(r[own], set()).add(r[other])
    expected = set()
    for a, x in has.items():
        near = []
        for b, y in has.items():
            c = len(x & y)
            if a != b and c:
                near.append((-round(c / sqrt(len(x) * len(y)) if sim == "cosine" else c / (len(x) + len(y) - c), 9), b))
        expected |= {(a, b, -s, n) for n, (s, b) in enumerate(sorted(near)[:4], 1)}
    f = baselines.user_knn if own == "user_id" else baselines.item_knn
    assert {tuple(r) for r in f(pairs, 4, sim).select("a", "b", "sim", "rank").collect()} == expected


def test_no_neighbours_of_no_pairs(spark, sf):
    pairs = workload(spark, sf, "orders").select("user_id", "item_id").limit(0)
    assert baselines.user_knn(pairs).count() == 0


@pytest.mark.parametrize("name", ["user_knn_votes", "item_knn_votes"])
def test_votes_do_not_depend_on_blocks(spark, sf, monkeypatch, name):
    whole = sorted(map(tuple, queries.QUERIES[name](spark, sf).collect()))
    monkeypatch.setattr(baselines, "BLOCK_MEETINGS", 20_000)
    monkeypatch.setattr(baselines, "SENT", 100_000)
    assert sorted(map(tuple, queries.QUERIES[name](spark, sf).collect())) == whole


def test_content_lists_meet_few_items(spark, monkeypatch):
    """Two attributes, ties between their shares, few items left over; no user meets all items of an attribute."""
    attrs = spark.createDataFrame([(i, "ab"[i % 2]) for i in range(400)] + [(400, "c"), (401, None)], "item_id long, attr string")
    pairs = spark.createDataFrame([(1, 0), (1, 1), (1, 3), (2, 0), (2, 1), (3, 400), (3, 7), (4, 401)], "user_id long, item_id long")
    monkeypatch.setattr(baselines, "split_join", None)
    got = sorted((r.user_id, r["rank"], r.item_id, r.score) for r in baselines.content_recs(pairs, attrs, 3).collect())
    expected = [(1, 1, 5, 0.666667), (1, 2, 7, 0.666667), (1, 3, 9, 0.666667), (2, 1, 2, 0.5), (2, 2, 3, 0.5), (2, 3, 4, 0.5), (3, 1, 1, 0.5), (3, 2, 3, 0.5), (3, 3, 5, 0.5)]
    assert got == expected


def test_content_scores_of_items_with_two_attributes_add_up(spark):
    attrs = spark.createDataFrame([(0, "a"), (0, "b"), (1, "a"), (2, "a"), (2, "b")], "item_id long, attr string")
    pairs = spark.createDataFrame([(1, 0)], "user_id long, item_id long")
    assert [(r.item_id, r.score) for r in baselines.content_recs(pairs, attrs, 3).orderBy("rank").collect()] == [(2, 2.0), (1, 1.0)]


@pytest.mark.parametrize("name", ["user_knn_votes", "item_knn_votes"])
def test_votes_in_turns_equal_those_at_once(spark, sf, monkeypatch, name):
    """All votes of all users were shuffled at once."""
    rows = lambda: {tuple(r) for r in queries.QUERIES[name](spark, sf).collect()}
    whole, cuts = rows(), []
    monkeypatch.setattr(baselines, "VOTES", 20_000)
    monkeypatch.setattr(baselines.Cuts, "cut", lambda self, df, by=None, f=baselines.Cuts.cut: cuts.append(set(df.columns)) or f(self, df, by))
    assert rows() == whole and len(whole) > 500
    assert cuts.count({"user_id", "item_id", "score", "rank"}) > 2


def test_neighbours_leave_no_table_that_nothing_reads(spark, sf, monkeypatch):
    """Every table stayed on disk, and lists were copied to blocks as structs."""
    made, kinds = [], []
    monkeypatch.setattr(baselines.Cuts, "__init__", lambda self, s, f=baselines.Cuts.__init__: made.append(self) or f(self, s))
    monkeypatch.setattr(baselines.Cuts, "cut", lambda self, df, by=None, f=baselines.Cuts.cut: kinds.append(df.dtypes) or f(self, df, by))
    found = baselines.item_knn(workload(spark, sf, "orders"))
    left = [n for c in made for n in listed(spark, c.base)]
    assert len(left) == 1 and len(kinds) > 5  # what one turn found
    assert not [d for d in kinds if any("struct" in t for _, t in d)]
    assert found.count() > 500
