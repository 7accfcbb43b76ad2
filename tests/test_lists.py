import numpy as np
import pytest
from pyspark.sql import functions as F

from cfengine import queries
from cfengine.functions import vectors as V
from cfengine.operators import metrics, predict


def _brute(s, t, ids, seen, k, cosine):
    if cosine:
        s, t = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300) for v in (s, t))
    score = s @ t.T
    score[seen] = -np.inf
    tops = [np.lexsort((ids, -np.round(r, 12)))[:k] for r in score]
    return [top[np.isfinite(r[top])] for top, r in zip(tops, score, strict=True)]


@pytest.mark.parametrize("dim, items, cosine", [(8, 6000, True), (8, 6000, False), (3, 3000, True), (4, 900, True), (4, 900, False), (40, 1500, True), (2, 7, True)])
def test_lists_of_leaves_are_those_of_all_items(dim, items, cosine):
    rng = np.random.default_rng(dim)
    s, t = rng.normal(size=(150, dim)), rng.normal(size=(items, dim)) * rng.lognormal(size=(items, 1))
    if dim == 4:  # rows of length 0, and equal ones
        t[::5], t[1::7], s[3] = 0, t[1], 0
    ids = np.sort(rng.choice(10 * items, items, replace=False))
    seen = np.divmod(np.unique(rng.integers(0, 150 * items, 4000)), items)
    if dim == 3:  # the nearest items are all seen
        first = _brute(s, t, ids, ([], []), 40, cosine)
        seen = (np.repeat(np.arange(150), 40), np.concatenate(first))
    lists = predict._Lists(s, t, ids, seen, 20, cosine)
    user, rank, item, _ = lists.run()
    for u, top in enumerate(_brute(s, t, ids, seen, 20, cosine)):
        assert item[user == u].tolist() == top.tolist() and rank[user == u].tolist() == list(range(1, len(top) + 1))


def test_rows_are_copied_for_few_cells(spark):
    """Cells of 4,096 users by 4,096 items copied every user for each 4,096 items."""
    rows = lambda n, k: spark.range(n).select("id", V.init_vector(k, "id", 8).alias("vec"))
    out = []
    found = predict.recommend(rows(30_000, 1), rows(9_000, 2), None, 20)
    spent = metrics.stage_metrics(spark, lambda: out.extend(found.agg(F.count(F.lit(1)), F.countDistinct("user_id"), F.max("rank")).first()))
    assert out == [600_000, 30_000, 20]
    assert spent["shuffle_written"] < 9e6


@pytest.mark.parametrize("name", ["recall20", "recall20_pooled", "ndcg20"])
def test_lists_are_written_before_they_are_measured(spark, sf, name):
    """Cells of users and items, and the pairs' own shuffles, were still on disk while lists met held-out pairs."""
    measured = queries.QUERIES[name](spark, sf)
    plan = measured._jdf.queryExecution().executedPlan().toString()
    assert "CoGroup" not in plan and "lineitem" not in plan
    assert measured.count() == 1
