from collections import Counter

from pyspark.sql import functions as F

from cfengine.operators import baselines
from cfengine.sources.feedback import dense_index, workload


def test_dense_index_follows_any_total_order(spark):
    rows = spark.range(5000).select("id", (F.col("id") * 37 % 101).alias("w")).repartition(7)
    got = {r.idx: (r.w, r.id) for r in dense_index(rows, F.desc("w"), F.col("id")).collect()}
    expected = sorted(((r * 37 % 101, r) for r in range(5000)), key=lambda x: (-x[0], x[1]))
    assert [got[k] for k in range(5000)] == expected
    assert dense_index(rows.limit(0), "id").count() == 0


def test_popular_unseen_items_by_hand(spark, sf):
    pairs = workload(spark, sf, "orders").select("user_id", "item_id").where("user_id < 20")
    rows = [tuple(r) for r in pairs.collect()]
    order = [i for i, _ in sorted(Counter(i for _, i in rows).items(), key=lambda x: (-x[1], x[0]))]
    expected = set()
    for u in {u for u, _ in rows}:
        seen = {i for v, i in rows if v == u}
        expected |= {(u, n, i) for n, i in enumerate([i for i in order if i not in seen][:5], 1)}
    assert {tuple(r) for r in baselines.popularity_recs(pairs, 5).collect()} == expected


def test_sql_functions_agree_with_the_plans(spark, sf):
    from cfengine.functions import sql
    from cfengine.operators import sampling
    from cfengine.sources.feedback import index_ids

    sql.register(spark)
    r = spark.sql("SELECT dot_vec(array(3D, 4D), array(4D, 3D)) AS d, cosine_vec(array(3D, 4D), array(4D, 3D)) AS c, cosine_vec(array(0D, 0D), array(1D, 2D)) AS z, ccl_loss(0.9D, array(0.5D, 0.1D, -0.2D, 0.8D), 2D, 0.4D) AS l").first()
    assert (r.d, r.z) == (24, 0) and abs(r.c - 0.96) < 1e-12 and abs(r.l - 0.35) < 1e-12
    pairs = workload(spark, sf, "orders").select("user_id", "item_id").where("user_id < 20")
    items = index_ids(pairs, "item_id")
    pairs.createOrReplaceTempView("some_pairs")
    got = spark.sql(f"SELECT p.user_id, p.item_id AS pos_id, d.j, d.idx FROM some_pairs p, LATERAL negative_draws(7, p.user_id, p.item_id, 3, {items.count()}) d").join(items, "idx")
    expected = sampling.sample_uniform(pairs, items, 3)
    assert sorted(map(tuple, got.select("user_id", "pos_id", "j", "id").collect())) == sorted(map(tuple, expected.collect()))
    tile = {(t.slot, t.item_id) for t in sampling.tile_rows(items, 1, 2, 8).where("refresh = 1").collect()}
    own = spark.sql(f"SELECT * FROM tile_slots(9, 0, 1, 8, {items.count()})").join(items, "idx")
    assert {(t.slot, t.id) for t in own.collect()} == tile
    assert spark.sql("SELECT * FROM negative_draws(7, cast(null AS int), 1, 3, 5)").count() == 0


def test_files_round_trip(spark, tmp_path):
    import pytest

    from cfengine.sources.tables import read_pairs, write_lists

    raw = spark.createDataFrame([(1, 2, "2020-01-01 00:00:00"), (1, 2, "2020-01-02 00:00:00"), (None, 3, None), (5, 6, None)], "u long, i long, at string")
    for fmt in ("parquet", "orc", "json", "csv"):
        w = raw.write.format(fmt)
        (w.option("header", True) if fmt == "csv" else w).save(str(tmp_path / fmt))
        rows = {(r.user_id, r.item_id, str(r.ts)) for r in read_pairs(spark, str(tmp_path / fmt), "u", "i", "at", fmt).collect()}
        assert rows == {(1, 2, "2020-01-02 00:00:00"), (5, 6, "None")}, fmt
    with pytest.raises(ValueError):
        read_pairs(spark, "x", "u", "i", fmt="xml")
    recs = spark.createDataFrame([(1, 1, 9, 0.5)], "user_id long, rank int, item_id long, score double")
    write_lists(recs, str(tmp_path / "lists"), "csv")
    assert spark.read.option("header", True).csv(str(tmp_path / "lists")).count() == 1


def test_bucketed_factors_join_without_exchange(spark):
    from cfengine.plans import plancheck
    from cfengine.sources.tables import bucket_factors

    f = spark.range(100).selectExpr("'user' AS side", "id", "array(1D) AS vec")
    a, b = bucket_factors(f, "factors_a", 4), bucket_factors(f, "factors_b", 4)
    try:
        joined = a.join(b.hint("merge"), "id")
        assert joined.count() == 100 and plancheck.exchanges(joined) == 0
    finally:
        spark.sql("DROP TABLE factors_a")
        spark.sql("DROP TABLE factors_b")


def test_text_lines_and_planted_source(spark, tmp_path):
    from cfengine.functions import sql
    from cfengine.sources.feedback import planted
    from cfengine.sources.tables import read_text_pairs

    (tmp_path / "pairs.txt").write_text("1\t2\n1\t2\n x\t3\n4\n 5 \t 6\n")
    assert sorted(map(tuple, read_text_pairs(spark, str(tmp_path / "pairs.txt")).collect())) == [(1, 2), (5, 6)]
    sql.register(spark)
    got = spark.read.format("planted").options(users="60", items="40", blocks="4", partitions="3").load()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, planted(spark, 60, 40, 4).collect()))


def test_shared_folder_is_required_beyond_a_local_master():
    import types

    import pytest

    from cfengine.plans.files import shared_dir

    sc = types.SimpleNamespace(master="spark://host:7077", getConf=lambda: {}, getCheckpointDir=lambda: None)
    with pytest.raises(ValueError):
        shared_dir(types.SimpleNamespace(sparkContext=sc))


def test_cuts_delete_what_they_replace(spark):
    from cfengine.plans.cuts import Cuts
    from cfengine.plans.files import exists, listed

    cuts = Cuts(spark)
    for k in range(3):
        made = cuts.cut(spark.range(k + 1))
        cuts.follow(made, made)
    assert listed(spark, cuts.base) == ["3"] and made.count() == 3
    cuts.close()
    assert not exists(spark, cuts.base)
