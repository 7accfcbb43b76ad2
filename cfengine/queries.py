"""Queries of the engine on the given tables, and the SQL they are held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import experiments
from .functions import vectors as V
from .functions.mix import P, mix, mix_py, mix_sql, multiplier_sql
from .operators import baselines, metrics, predict, relational, sampling, tuning
from .operators.blocks import TrainConfig
from .operators.trainer import fit, init_factors, rotation
from .plans.cuts import Cuts
from .shipping import ship
from .sources import feedback as S
from .sources.feedback import table, workload
from .streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = " ".join(sql.split())
        return f

    return keep


# --- shared SQL -------------------------------------------------------------

BUY = "(SELECT o_custkey AS user_id, l_partkey AS item_id, l_suppkey AS supp_id, max(o_orderdate) AS ts, max(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2, 3)"
W1 = f"(SELECT user_id, item_id, max(ts) AS ts FROM {BUY} GROUP BY 1, 2)"
TERMS = "(SELECT DISTINCT doc_id AS user_id, unnest(regexp_extract_all(lower(text), '[a-z]{3,}')) AS term FROM documents)"


def w1(spark: SparkSession, d: str) -> DataFrame:
    return workload(spark, d, "orders")


# --- feedback ---------------------------------------------------------------


@query("implicit_orders", f"SELECT user_id, item_id FROM {W1}")
def _(spark, d):
    return w1(spark, d).select("user_id", "item_id")


@query("implicit_suppliers", f"SELECT DISTINCT user_id, supp_id AS item_id FROM {BUY}")
def _(spark, d):
    return workload(spark, d, "suppliers").select("user_id", "item_id")


@query("implicit_events", "SELECT DISTINCT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id FROM events WHERE event_type IN ('view', 'click', 'purchase') AND json_extract(props, '$.k') IS NOT NULL")
def _(spark, d):
    return workload(spark, d, "events").select("user_id", "item_id")


@query("implicit_events_weighted", "SELECT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id, round(sum(CASE event_type WHEN 'purchase' THEN 4.0 WHEN 'click' THEN 2.0 ELSE 1.0 END), 6) AS weight FROM events WHERE event_type IN ('view', 'click', 'purchase') AND json_extract(props, '$.k') IS NOT NULL GROUP BY 1, 2")
def _(spark, d):
    pairs = S.from_events(table(spark, d, "events"), weights={"purchase": 4.0, "click": 2.0})
    return pairs.select("user_id", "item_id", F.round("weight", 6).alias("weight"))


@query("implicit_docterms", f"WITH t AS {TERMS} SELECT user_id, term FROM t WHERE term IN (SELECT term FROM t GROUP BY 1 HAVING count(*) >= 5 AND count(*) <= 0.1 * (SELECT count(*) FROM documents))")
def _(spark, d):
    return workload(spark, d, "docterms").select("user_id", "term")


@query("implicit_talkterms", "SELECT DISTINCT conv_id AS user_id, unnest(regexp_extract_all(lower(text), '[a-z]{3,}')) AS term FROM conversations")
def _(spark, d):
    return workload(spark, d, "talkterms").select("user_id", "term")


@query("implicit_brands", f"SELECT DISTINCT user_id, CAST(regexp_extract(p_brand, '([0-9]+)$', 1) AS BIGINT) AS item_id FROM {W1} JOIN part ON item_id = p_partkey")
def _(spark, d):
    return workload(spark, d, "brands").select("user_id", "item_id")


@query("explicit_quantity", "SELECT DISTINCT o_custkey AS user_id, l_partkey AS item_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity >= 40")
def _(spark, d):
    return S.from_explicit(S.purchases(spark, d), "o_custkey", "l_partkey", "l_quantity", min_rating=40)


@query("explicit_labels", "SELECT DISTINCT doc_id AS user_id, CAST(toxic AS BIGINT) AS item_id FROM labels WHERE quality IN (1)")
def _(spark, d):
    return S.from_explicit(table(spark, d, "labels"), "doc_id", "toxic", "quality", keep=[1])


def _side_sql(side: str) -> str:
    name = side.removesuffix("_id")
    quantiles = ", ".join(f"quantile_cont(n, {p}) AS {name}_p{round(100 * p)}" for p in (0.5, 0.9, 0.99))
    return f"(SELECT {quantiles}, round(max(n) / avg(n), 6) AS {name}_skew FROM (SELECT {side}, count(*)::DOUBLE AS n FROM {W1} GROUP BY 1))"


@query("profile_orders", f"SELECT * FROM (SELECT count(DISTINCT user_id) AS users, count(DISTINCT item_id) AS items, count(*) AS pairs, round(count(*) / count(DISTINCT user_id) / count(DISTINCT item_id), 6) AS density FROM {W1}), {_side_sql('user_id')}, {_side_sql('item_id')}")
def _(spark, d):
    return S.profile(w1(spark, d))


@query("degree_hist_items", f"SELECT degree, count(*) AS n FROM (SELECT item_id, count(*) AS degree FROM {W1} GROUP BY 1) GROUP BY 1")
def _(spark, d):
    return S.degree_hist(w1(spark, d), "item_id")


def _kcore_sql(pairs: str, rounds: int, least_u: int, least_i: int, columns: str = "user_id, item_id", item: str = "item_id") -> str:
    parts, last = [f"k0 AS MATERIALIZED (SELECT {columns} FROM {pairs})"], "k0"
    for r in range(rounds):
        parts.append(f"u{r} AS MATERIALIZED (SELECT * FROM {last} WHERE user_id IN (SELECT user_id FROM {last} GROUP BY 1 HAVING count(*) >= {least_u}))")
        parts.append(f"i{r} AS MATERIALIZED (SELECT * FROM u{r} WHERE {item} IN (SELECT {item} FROM u{r} GROUP BY 1 HAVING count(*) >= {least_i}))")
        last = f"i{r}"
    return f"WITH {', '.join(parts)} SELECT * FROM {last}"


@query("kcore_orders", _kcore_sql(W1, 3, 25, 20))
def _(spark, d):
    return S.kcore(w1(spark, d).select("user_id", "item_id"), 25, 20, 3)


@query("kcore_docterms", _kcore_sql(f"(SELECT user_id, term FROM {TERMS} WHERE term IN (SELECT term FROM {TERMS} GROUP BY 1 HAVING count(*) >= 5 AND count(*) <= 0.1 * (SELECT count(*) FROM documents)))", 12, 20, 8, "user_id, term", "term"))
def _(spark, d):
    """Until nothing changes; the SQL repeats the two filters more often than that takes."""
    return S.kcore(workload(spark, d, "docterms"), 20, 8).select("user_id", "term")


@query("split_hash", f"SELECT user_id, item_id, {mix_sql(3, 'user_id', 'item_id')} % 1000 < 200 AS held_out FROM {W1}")
def _(spark, d):
    train, test = S.split_holdout(w1(spark, d).select("user_id", "item_id"))
    return train.withColumn("held_out", F.lit(False)).unionByName(test.withColumn("held_out", F.lit(True)))


@query("split_last", f"SELECT user_id, item_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, item_id DESC) AS n FROM {W1}) WHERE n = 1")
def _(spark, d):
    return S.split_holdout(w1(spark, d), "last")[1].select("user_id", "item_id")


@query("history_100", f"SELECT user_id, string_agg(item_id, ',' ORDER BY n) AS hist FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, item_id DESC) AS n FROM {W1}) WHERE n <= 100 GROUP BY 1")
def _(spark, d):
    return S.user_history(w1(spark, d)).select("user_id", F.array_join(F.col("hist").cast("array<string>"), ",").alias("hist"))


@query("index_ids_parts", f"SELECT id, row_number() OVER (ORDER BY id) - 1 AS idx FROM (SELECT DISTINCT item_id AS id FROM {W1})")
def _(spark, d):
    return S.index_ids(w1(spark, d), "item_id")


@query("sparse_vectors_users", f"SELECT user_id, CAST(0 AS BIGINT) AS part, string_agg(item_id, ',' ORDER BY item_id) AS members FROM {W1} GROUP BY 1")
def _(spark, d):
    return S.as_sparse_vectors(w1(spark, d), "user_id").select("user_id", F.col("part").cast("long").alias("part"), F.array_join(F.col("members").cast("array<string>"), ",").alias("members"))


@query("sparse_vectors_items_parts", f"SELECT item_id, count(*) AS members, CAST(sum(user_id) AS BIGINT) AS total FROM {W1} GROUP BY 1")
def _(spark, d):
    """Parts of about eight members, put together again."""
    parts = S.as_sparse_vectors(w1(spark, d), "item_id", 8)
    each = parts.select("item_id", F.size("members").alias("n"), F.aggregate("members", F.lit(0).cast("long"), lambda a, x: a + x).alias("s"))
    return each.groupBy("item_id").agg(F.sum("n").alias("members"), F.sum("s").alias("total"))


# --- init, similarity, loss, gradient --------------------------------------


def vec_sql(seed: int, ident: str, dim: int, scale: float = 0.1) -> str:
    return f"list_transform(range({dim}), lambda d: (2 * ({mix_sql(seed, ident, 'd')} / {float(P)}) - 1) * {scale})"


@query("init_uniform", f"SELECT id, unnest(range(8)) AS d, round(unnest({vec_sql(1, 'id', 8)}), 9) AS v FROM (SELECT c_custkey AS id FROM customer)")
def _(spark, d):
    rows = table(spark, d, "customer").select(F.col("c_custkey").alias("id")).withColumn("vec", V.init_vector(1, "id", 8))
    return rows.select("id", F.posexplode("vec").alias("d", "v")).select("id", F.col("d").cast("long").alias("d"), F.round("v", 9).alias("v"))


@query("init_xavier", f"SELECT id, round(list_sum({vec_sql(2, 'id', 16, (6 / (100 + 16)) ** 0.5)}), 9) AS total FROM (SELECT p_partkey AS id FROM part)")
def _(spark, d):
    rows = table(spark, d, "part").select(F.col("p_partkey").alias("id")).withColumn("vec", V.init_vector(2, "id", 16, "xavier_uniform", fan_in=100))
    return rows.select("id", F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 9).alias("total"))


@query("init_xavier_normal", f"SELECT id, round((list_sum(list_transform(range(12), lambda k: {mix_sql(4, 'id', '0', 'k')} / {float(P)})) - 6) * {(2 / (50 + 1)) ** 0.5}, 9) AS v FROM (SELECT s_suppkey AS id FROM supplier)")
def _(spark, d):
    rows = table(spark, d, "supplier").select(F.col("s_suppkey").alias("id")).withColumn("vec", V.init_vector(4, "id", 1, "xavier_normal", fan_in=50))
    return rows.select("id", F.round(F.col("vec")[0], 9).alias("v"))


@query("init_warm", f"SELECT side, id, round(list_sum(v), 6) AS total FROM (SELECT 'user' AS side, user_id AS id, {vec_sql(1, 'user_id', 64)} AS v FROM (SELECT DISTINCT user_id FROM {W1}) UNION ALL SELECT 'item', coalesce(i.item_id, e.vec_id), coalesce(CAST(e.embedding AS DOUBLE[]), {vec_sql(2, 'i.item_id', 64)}) FROM (SELECT DISTINCT item_id FROM {W1}) i FULL JOIN embeddings e ON e.vec_id = i.item_id)")
def _(spark, d):
    """Items that are known from earlier keep their rows."""
    warm = table(spark, d, "embeddings").select(F.lit("item").alias("side"), F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    rows = init_factors(w1(spark, d), TrainConfig(dim=64), warm)
    return rows.select("side", "id", F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 6).alias("total"))


@query("init_normal", f"SELECT id, round((list_sum(list_transform(range(12), lambda k: {mix_sql(4, 'id', '0', 'k')} / {float(P)})) - 6) * 0.1, 9) AS v FROM (SELECT s_suppkey AS id FROM supplier)")
def _(spark, d):
    rows = table(spark, d, "supplier").select(F.col("s_suppkey").alias("id")).withColumn("vec", V.init_vector(4, "id", 1, "normal"))
    return rows.select("id", F.round(F.col("vec")[0], 9).alias("v"))


_EMB = "(SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)"
_EPAIR = f"{_EMB} a JOIN {_EMB} b ON b.vec_id = (a.vec_id * 7 + 3) % (SELECT count(*) FROM embeddings)"


def _emb_pairs(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    n = e.count()
    a = e.select(F.col("vec_id").alias("a"), F.col("v").alias("s"), ((F.col("vec_id") * 7 + 3) % n).alias("b"))
    return a.join(e.select(F.col("vec_id").alias("b"), F.col("v").alias("t")), "b")


@query("sim_dot", f"SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.v, b.v), 9) AS x FROM {_EPAIR}")
def _(spark, d):
    return _emb_pairs(spark, d).select("a", "b", F.round(V.dot(F.col("s"), F.col("t")), 9).alias("x"))


@query("sim_cosine", f"SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v) * list_dot_product(b.v, b.v)), 9) AS x FROM {_EPAIR}")
def _(spark, d):
    return _emb_pairs(spark, d).select("a", "b", F.round(V.cosine(F.col("s"), F.col("t")), 9).alias("x"))


@query("self_norm", f"SELECT vec_id, round(list_dot_product(v, v), 9) AS n FROM {_EMB}")
def _(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    return e.select("vec_id", F.round(V.sq_norm(F.col("v")), 9).alias("n"))


@query("normalized_rows", f"SELECT vec_id, round(1 / sqrt(list_dot_product(v, v)), 9) AS inverse_norm, round(list_sum(list_transform(v, lambda x: x / sqrt(list_dot_product(v, v)))), 8) AS total FROM {_EMB}")
def _(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("vec"))
    return V.normalize_rows(e).select("vec_id", F.round("inverse_norm", 9).alias("inverse_norm"), F.round(F.aggregate("unit", F.lit(0.0), lambda a, x: a + x), 8).alias("total"))


_X = f"(SELECT a.vec_id AS a, list_dot_product(a.v, b.v) AS x, (a.label = b.label)::INT AS y FROM (SELECT *, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) a JOIN (SELECT *, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) b ON b.vec_id = (a.vec_id * 7 + 3) % (SELECT count(*) FROM embeddings))"


def _scored(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label")
    n = e.count()
    a = e.select(F.col("vec_id").alias("a"), F.col("v").alias("s"), F.col("label").alias("la"), ((F.col("vec_id") * 7 + 3) % n).alias("b"))
    return a.join(e.select(F.col("vec_id").alias("b"), F.col("v").alias("t"), "label"), "b").select("a", V.dot(F.col("s"), F.col("t")).alias("x"), (F.col("la") == F.col("label")).cast("int").alias("y"))


@query("loss_mse", f"SELECT a, round((y - x) * (y - x), 9) AS loss FROM {_X}")
def _(spark, d):
    return _scored(spark, d).select("a", F.round(V.mse(F.col("x"), F.col("y")), 9).alias("loss"))


@query("loss_bce", f"SELECT a, round(greatest(x, 0) + ln(1 + exp(-abs(x))) - y * x, 9) AS loss FROM {_X}")
def _(spark, d):
    return _scored(spark, d).select("a", F.round(V.bce(F.col("x"), F.col("y")), 9).alias("loss"))


@query("loss_bpr", f"SELECT p.a AS a, round(ln(1 + exp(n.x - p.x)), 9) AS loss FROM {_X} p JOIN {_X} n ON n.a = p.a + 1")
def _(spark, d):
    s = _scored(spark, d)
    return s.alias("p").join(s.alias("n"), F.col("n.a") == F.col("p.a") + 1).select(F.col("p.a").alias("a"), F.round(V.bpr(F.col("p.x"), F.col("n.x")), 9).alias("loss"))


@query("loss_metric", f"SELECT p.a AS a, round(greatest(0.0, 0.5 + (2 - 2 * p.x) - (2 - 2 * n.x)), 9) AS loss FROM {_X} p JOIN {_X} n ON n.a = p.a + 1")
def _(spark, d):
    s = _scored(spark, d)
    return s.alias("p").join(s.alias("n"), F.col("n.a") == F.col("p.a") + 1).select(F.col("p.a").alias("a"), F.round(V.metric_hinge(2 - 2 * F.col("p.x"), 2 - 2 * F.col("n.x"), 0.5), 9).alias("loss"))


# --- samplers ---------------------------------------------------------------

_ITEMS = f"(SELECT id, row_number() OVER (ORDER BY id) - 1 AS idx FROM (SELECT DISTINCT item_id AS id FROM {W1}))"
_N = f"(SELECT count(DISTINCT item_id) FROM {W1})"
_BATCH = f"(SELECT user_id, item_id AS pos_id FROM {W1})"


def neg_sql(seed: int | str, n: int = 4) -> str:
    return f"(SELECT user_id, pos_id, j, id AS item_id FROM (SELECT *, {mix_sql(seed, 'user_id', 'pos_id', 'j')} % {_N} AS idx FROM (SELECT *, unnest(range({n})) AS j FROM {_BATCH})) JOIN {_ITEMS} USING (idx))"


_NEG = neg_sql(7)


def _batch(spark, d):
    pairs = w1(spark, d).select("user_id", "item_id")
    return pairs, S.index_ids(pairs, "item_id")


def _negs(spark, d, **opts):
    batch, items = _batch(spark, d)
    return sampling.sample_uniform(batch, items, 4, **opts).withColumn("j", F.col("j").cast("long"))


@query("neg_uniform", f"SELECT * FROM {_NEG}")
def _(spark, d):
    return _negs(spark, d)


@query("neg_single", f"SELECT * FROM {_NEG} WHERE j = 0")
def _(spark, d):
    batch, items = _batch(spark, d)
    return sampling.sample_uniform(batch, items, 1).withColumn("j", F.col("j").cast("long"))


@query("neg_uniform_unseen", f"SELECT user_id, pos_id, j, item_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id, pos_id, j ORDER BY a) AS k FROM (SELECT user_id, pos_id, j, a, id AS item_id FROM (SELECT *, {mix_sql('7 + 1000 * a', 'user_id', 'pos_id', 'j')} % {_N} AS idx FROM (SELECT *, unnest(range(4)) AS j FROM {_BATCH}), range(9) r(a)) JOIN {_ITEMS} USING (idx)) n WHERE NOT EXISTS (SELECT 1 FROM {_BATCH} b WHERE b.user_id = n.user_id AND b.pos_id = n.item_id)) WHERE k = 1")
def _(spark, d):
    """Draws that hit a seen item are drawn again, up to eight times."""
    return _negs(spark, d, exclude_seen=True)


def _tile_idx(worker: str, refresh: str, slot: str, replacement: bool = False) -> str:
    if replacement:
        return f"{mix_sql(9, worker, refresh, slot)} % n"
    return f"({mix_sql(10, worker, refresh)} % n + {multiplier_sql(9, 'n', mix_sql(11, worker, refresh))} * {slot}) % n"


_STEPS = f"(SELECT *, floor(step / 3000)::BIGINT AS refresh FROM (SELECT *, row_number() OVER (PARTITION BY worker ORDER BY {mix_sql(11, 'user_id', 'pos_id')}, user_id, pos_id) - 1 AS step FROM (SELECT *, {mix_sql(10, 'user_id')} % 4 AS worker FROM {_BATCH})))"


def _tiles_sql(replacement: bool = False) -> str:
    grid = f"(SELECT *, {_N} AS n FROM (SELECT unnest(range(4)) AS worker), (SELECT unnest(range((SELECT max(refresh) + 1 FROM {_STEPS}))) AS refresh))"
    if replacement:
        drawn = f"SELECT worker, refresh, slot, {_tile_idx('worker', 'refresh', 'slot', True)} AS idx FROM {grid}, (SELECT unnest(range(32)) AS slot)"
    else:
        drawn = f"SELECT worker, refresh, slot, (first + step * slot) % n AS idx FROM (SELECT worker, refresh, n, {mix_sql(10, 'worker', 'refresh')} % n AS first, {multiplier_sql(9, 'n', mix_sql(11, 'worker', 'refresh'))} AS step FROM {grid}), (SELECT unnest(range(32)) AS slot)"
    return f"(SELECT worker, refresh, slot, id AS item_id FROM ({drawn}) JOIN {_ITEMS} USING (idx))"


_TILES = _tiles_sql()
_TILED = f"(SELECT s.user_id, s.pos_id, s.worker, s.refresh, s.j, t.item_id FROM (SELECT *, {mix_sql(12, 'user_id', 'pos_id', 'j')} % 32 AS slot FROM (SELECT *, unnest(range(4)) AS j FROM {_STEPS})) s JOIN {_TILES} t USING (worker, refresh, slot))"


def _all_tiles(spark, d, replacement: bool = False):
    """Tiles of all refreshes that the pairs take, and the pairs with their steps."""
    batch, items = _batch(spark, d)
    steps = Cuts(spark).cut(sampling.with_steps(batch, 4, 3000))
    return sampling.tile_rows(items, 4, sampling.tiles_used(steps), 32, replacement=replacement), steps


@query("tile_rows", f"SELECT * FROM {_TILES}")
def _(spark, d):
    return _all_tiles(spark, d)[0].select(F.col("worker").cast("long"), F.col("refresh").cast("long"), F.col("slot").cast("long"), "item_id")


@query("tile_rows_replaced", f"SELECT * FROM {_tiles_sql(True)}")
def _(spark, d):
    return _all_tiles(spark, d, True)[0].select(F.col("worker").cast("long"), F.col("refresh").cast("long"), F.col("slot").cast("long"), "item_id")


def _tiled(spark, d):
    batch, items = _batch(spark, d)
    return sampling.sample_tiled(batch, items, 4, 32, 3000, 4)


@query("neg_tiled", f"SELECT * FROM {_TILED}")
def _(spark, d):
    return _tiled(spark, d).select("user_id", "pos_id", F.col("worker").cast("long"), "refresh", F.col("j").cast("long"), "item_id")


@query("tile_coverage", f"SELECT count(*) AS draws, count(DISTINCT item_id) AS distinct_items, count(DISTINCT (worker, refresh, item_id)) AS distinct_in_tiles FROM {_TILES}")
def _(spark, d):
    return _all_tiles(spark, d)[0].agg(F.count(F.lit(1)).alias("draws"), F.countDistinct("item_id").alias("distinct_items"), F.countDistinct("worker", "refresh", "item_id").alias("distinct_in_tiles"))


@query("tile_hit_ratio", f"SELECT round(avg((t.item_id IS NOT NULL)::INT), 6) AS hit_ratio FROM {_STEPS} s LEFT JOIN (SELECT DISTINCT worker, refresh, item_id FROM {_TILES}) t ON t.worker = s.worker AND t.refresh = s.refresh AND t.item_id = s.pos_id")
def _(spark, d):
    tiles, steps = _all_tiles(spark, d)
    return sampling.hit_ratio(steps, tiles)


# --- one step ---------------------------------------------------------------


def coef_sql(neg: str, coef: str = "CASE WHEN j < 0 THEN -1.0 WHEN x > 0 THEN 0.25 ELSE 0.0 END", x: str = "st / sqrt(ss * tt)") -> str:
    """Examples with rows, sums, similarity and the loss's derivative c."""
    ex = f"(SELECT user_id, pos_id, CAST(-1 AS BIGINT) AS j, pos_id AS item_id FROM {_BATCH} UNION ALL SELECT user_id, pos_id, j, item_id FROM {neg})"
    vec = f"(SELECT *, {vec_sql(1, 'user_id', 8)} AS s, {vec_sql(2, 'item_id', 8)} AS t FROM {ex})"
    sums = f"(SELECT *, list_dot_product(s, s) AS ss, list_dot_product(t, t) AS tt, list_dot_product(s, t) AS st FROM {vec})"
    return f"(SELECT *, {coef} AS c FROM (SELECT *, {x} AS x FROM {sums}))"


_EX = f"(SELECT user_id, pos_id, CAST(-1 AS BIGINT) AS j, pos_id AS item_id FROM {_BATCH} UNION ALL SELECT user_id, pos_id, j, item_id FROM {_NEG})"
_COEF = _FWD = coef_sql(_NEG)


def _grad_sql(coef: str = _COEF, cosine: bool = True) -> str:
    u = "c * (t[k + 1] / sqrt(ss * tt) - x / ss * s[k + 1])" if cosine else "c * t[k + 1]"
    i = "c * (s[k + 1] / sqrt(ss * tt) - x / tt * t[k + 1])" if cosine else "c * s[k + 1]"
    return f"(SELECT side, id, k, sum(g) AS g FROM (SELECT 'user' AS side, user_id AS id, k, {u} AS g FROM {coef}, range(8) r(k) WHERE c <> 0 UNION ALL SELECT 'item', item_id, k, {i} FROM {coef}, range(8) r(k) WHERE c <> 0) GROUP BY 1, 2, 3)"


def _start(spark, d, cuts):
    batch, items = _batch(spark, d)
    batch = cuts.cut(batch.repartition(8))
    negs = cuts.cut(sampling.sample_uniform(batch, items, 4))
    both = relational.examples(batch, negs)
    ids = both.select(F.lit("user").alias("side"), F.col("user_id").alias("id")).union(both.select(F.lit("item"), "item_id")).distinct()
    factors = cuts.cut(ids.withColumn("vec", F.when(F.col("side") == "user", V.init_vector(1, "id", 8)).otherwise(V.init_vector(2, "id", 8))))
    return batch, negs, factors


def _forward(spark, d, cfg=relational.StepConfig()):
    cuts = Cuts(spark)
    batch, negs, factors = _start(spark, d, cuts)
    parts = (factors.where(F.col("side") == s).select("id", "vec") for s in ("user", "item"))
    return relational.forward(relational.examples(batch, negs), *parts, cfg)


@query("loss_ccl", f"SELECT user_id, pos_id, round(1 - max(x) FILTER (j < 0) + coalesce(sum(greatest(x, 0)) FILTER (j >= 0), 0) / 4, 9) AS loss FROM {_FWD} GROUP BY 1, 2")
def _(spark, d):
    return relational.example_loss(_forward(spark, d), relational.StepConfig()).withColumn("loss", F.round("loss", 9))


@query("epoch_loss", f"SELECT round(avg(loss), 8) AS mean_loss, count(*) AS n FROM (SELECT user_id, pos_id, 1 - max(x) FILTER (j < 0) + coalesce(sum(greatest(x, 0)) FILTER (j >= 0), 0) / 4 AS loss FROM {_FWD} GROUP BY 1, 2)")
def _(spark, d):
    return relational.example_loss(_forward(spark, d), relational.StepConfig()).agg(F.round(F.avg("loss"), 8).alias("mean_loss"), F.count(F.lit(1)).alias("n"))


def _long(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select("side", "id", F.posexplode(df.columns[-1]).alias("k", "v")).select("side", "id", F.col("k").cast("long").alias("k"), F.round("v", digits).alias("v"))


def _grads(spark, d, **opts):
    cfg = relational.StepConfig(**opts)
    return _long(relational.combine_gradients(relational.gradients(_forward(spark, d, cfg), cfg), 8))


@query("grad_user", f"SELECT side, id, k, round(g, 6) AS v FROM {_grad_sql()} WHERE side = 'user'")
def _(spark, d):
    return _grads(spark, d).where("side = 'user'")


@query("grad_item", f"SELECT side, id, k, round(g, 6) AS v FROM {_grad_sql()} WHERE side = 'item'")
def _(spark, d):
    return _grads(spark, d).where("side = 'item'")


@query("grad_noreuse_equal", f"SELECT side, id, k, round(g, 6) AS v FROM {_grad_sql()}")
def _(spark, d):
    return _grads(spark, d, reuse=False)


_ALL = "(SELECT 'user' AS side, user_id AS id FROM {v} UNION SELECT 'item', item_id FROM {v})".format(v=_EX)
_FACT = f"(SELECT side, id, k, CASE WHEN side = 'user' THEN {vec_sql(1, 'id', 8)} ELSE {vec_sql(2, 'id', 8)} END[k + 1] AS v FROM {_ALL}, range(8) r(k))"


def _step_sql(grads: str, keep: float = 1.0) -> str:
    return f"SELECT f.side, f.id, f.k, round(CASE WHEN g.g IS NULL THEN f.v ELSE {keep} * f.v - 0.05 * g.g END, 6) AS v FROM {_FACT} f LEFT JOIN {grads} g ON g.side = f.side AND g.id = f.id AND g.k = f.k"


def _step(spark, d, update="sparse", **opts):
    batch, negs, factors = _start(spark, d, Cuts(spark))
    return _long(relational.step(batch, negs, factors, relational.StepConfig(**opts), update))


def _paired_step(spark, d, loss):
    """One step of a loss that compares a negative with its positive. The kernel has an example's similarities together, so no
    example is shuffled; rows and draws are those of the plan of joins: seeds 1, 2 and, as the kernel adds 13, 7."""
    pairs = w1(ship(spark), d).select("user_id", "item_id")
    pairs = Cuts(spark).cut(pairs)
    rows = [pairs.select(F.lit(s).alias("side"), F.col(f"{s}_id").alias("id")).distinct().withColumn("vec", V.init_vector(k, "id", 8)) for k, s in ((1, "user"), (2, "item"))]
    return _factors(fit(pairs, TrainConfig(dim=8, negatives=4, batch=10**9, seed=7 - 13, plan="block", loss=loss, similarity="dot"), warm=rows[0].union(rows[1])))


for _name, _update in (("step_sparse", "sparse"), ("step_dense", "dense"), ("step_coalesced", "coalesced")):
    query(_name, _step_sql(_grad_sql()))(lambda spark, d, u=_update: _step(spark, d, u))


@query("step_l2", _step_sql(_grad_sql(), 1 - 0.05 * 0.01))
def _(spark, d):
    return _step(spark, d, l2=0.01)


@query("step_pointwise", _step_sql(_grad_sql(coef_sql(_NEG, "CASE WHEN j < 0 THEN 2 * (st - 1) ELSE 2 * st END", "st"), cosine=False)))
def _(spark, d):
    return _step(spark, d, loss="mse", similarity="dot")


@query("step_bce", _step_sql(_grad_sql(coef_sql(_NEG, "1 / (1 + exp(-st)) - (j < 0)::INT", "st"), cosine=False)))
def _(spark, d):
    return _step(spark, d, loss="bce", similarity="dot")


def _paired_sql(value: str, one: str) -> str:
    """c of losses that compare each negative with its example's positive."""
    rows = f"(SELECT *, {value} AS val, max({value}) FILTER (j < 0) OVER (PARTITION BY user_id, pos_id) AS pv FROM {coef_sql(_NEG, '0.0', 'st')})"
    part = f"(SELECT * EXCLUDE (c), CASE WHEN j >= 0 THEN {one} ELSE 0.0 END AS one FROM {rows})"
    return f"(SELECT *, CASE WHEN j < 0 THEN -sum(one) OVER (PARTITION BY user_id, pos_id) ELSE one END AS c FROM {part})"


@query("step_bpr", _step_sql(_grad_sql(_paired_sql("st", "0.25 / (1 + exp(pv - val))"), cosine=False)))
def _(spark, d):
    return _paired_step(spark, d, "bpr")


_METRIC_GRAD = "(SELECT side, id, k, sum(g) AS g FROM (SELECT 'user' AS side, user_id AS id, k, 2 * c * (s[k + 1] - t[k + 1]) AS g FROM {c}, range(8) r(k) WHERE c <> 0 UNION ALL SELECT 'item', item_id, k, 2 * c * (t[k + 1] - s[k + 1]) FROM {c}, range(8) r(k) WHERE c <> 0) GROUP BY 1, 2, 3)".format(c=_paired_sql("ss + tt - 2 * st", "CASE WHEN 1 + pv - val > 0 THEN -0.25 ELSE 0.0 END"))


@query("step_metric", _step_sql(_METRIC_GRAD))
def _(spark, d):
    return _paired_step(spark, d, "metric")


@query("touched_rows", f"SELECT side, count(DISTINCT id) AS touched FROM {_grad_sql()} GROUP BY 1")
def _(spark, d):
    cfg = relational.StepConfig()
    return relational.gradients(_forward(spark, d, cfg), cfg).groupBy("side").agg(F.countDistinct("id").alias("touched"))


# --- whole epochs of the kernels, one batch a cell, in SQL ------------------
#
# A kernel that takes a whole cell as one batch makes one summed step over it, which SQL can follow: a chain of
# tables f0, f1, ... of factors (side, id, v: a list), one for each step.

FULL = TrainConfig(dim=8, negatives=4, batch=10**9, seed=1)


def _first_sql(dim: int = 8) -> str:
    return f"f0 AS MATERIALIZED (SELECT 'user' AS side, user_id AS id, {vec_sql(1, 'user_id', dim)} AS v FROM (SELECT DISTINCT user_id FROM {W1}) UNION ALL SELECT 'item', item_id, {vec_sql(2, 'item_id', dim)} FROM (SELECT DISTINCT item_id FROM {W1}))"


def _turn_sql(k: int, examples: str, dim: int = 8, n: int = 4) -> list[str]:
    """Tables of step k, from f<k> to f<k + 1>. examples: user_id, pos_id, j, item_id."""
    return [
        f"c{k} AS MATERIALIZED (SELECT *, CASE WHEN j < 0 THEN -1.0 WHEN x > 0 THEN {1 / n} ELSE 0.0 END AS c FROM (SELECT *, st / sqrt(ss * tt) AS x FROM (SELECT e.*, u.v AS s, i.v AS t, list_dot_product(u.v, u.v) AS ss, list_dot_product(i.v, i.v) AS tt, list_dot_product(u.v, i.v) AS st FROM ({examples}) e JOIN f{k} u ON u.side = 'user' AND u.id = e.user_id JOIN f{k} i ON i.side = 'item' AND i.id = e.item_id)))",
        f"g{k} AS MATERIALIZED (SELECT side, id, k, sum(g) AS g FROM (SELECT 'user' AS side, user_id AS id, k, c * (t[k + 1] / sqrt(ss * tt) - x / ss * s[k + 1]) AS g FROM c{k}, range({dim}) r(k) WHERE c <> 0 UNION ALL SELECT 'item', item_id, k, c * (s[k + 1] / sqrt(ss * tt) - x / tt * t[k + 1]) FROM c{k}, range({dim}) r(k) WHERE c <> 0) GROUP BY 1, 2, 3)",
        f"f{k + 1} AS MATERIALIZED (SELECT f.side, f.id, list(f.v[f.k + 1] - 0.05 * coalesce(g.g, 0) ORDER BY f.k) AS v FROM (SELECT *, unnest(range({dim})) AS k FROM f{k}) f LEFT JOIN g{k} g ON g.side = f.side AND g.id = f.id AND g.k = f.k GROUP BY 1, 2)",
    ]


def _chain_sql(tables: list[str], last: int, dim: int = 8) -> str:
    return f"WITH {', '.join(tables)} SELECT side, id, k, round(v[k + 1], 6) AS v FROM f{last}, range({dim}) r(k)"


def _ex_sql(pairs: str, negatives: str) -> str:
    return f"SELECT user_id, pos_id, CAST(-1 AS BIGINT) AS j, pos_id AS item_id FROM {pairs} UNION ALL SELECT user_id, pos_id, j, item_id FROM {negatives}"


def _factors(model) -> DataFrame:
    return _long(model.factors.select("side", "id", "vec"))


def _fitted(spark, d, **opts):
    from .operators.blocks import with_options

    return fit(w1(ship(spark), d), with_options(FULL, **opts))


@query("two_steps", _chain_sql([_first_sql(), *_turn_sql(0, _ex_sql(_BATCH, neg_sql(14))), *_turn_sql(1, _ex_sql(_BATCH, neg_sql(15)))], 2))
def _(spark, d):
    """Two synchronous steps of the relational plan."""
    return _factors(_fitted(spark, d, plan="relational", epochs=2))


@query("fused_step", _chain_sql([_first_sql(), *_turn_sql(0, _ex_sql(_BATCH, neg_sql(14)))], 1))
def _(spark, d):
    """One epoch of the fused kernel as one batch."""
    return _factors(_fitted(spark, d, plan="block"))


for _engine in ("dense", "sparse", "jagged"):
    query(f"{_engine}_engine_step", ORACLES["fused_step"])(lambda spark, d, e=_engine: _factors(_fitted(spark, d, plan="block", engine=e)))

_FIRST_USER = f"(SELECT user_id FROM {_BATCH} ORDER BY {mix_sql(1, 'user_id', 'pos_id')}, user_id, pos_id LIMIT 1)"
_ONE_TILE = f"(SELECT slot, id AS item_id FROM (SELECT slot, (first + step * slot) % n AS idx FROM (SELECT n, {mix_sql(9, '0', '0', 'f')} % n AS first, {multiplier_sql(8, 'n', mix_sql(10, '0', '0', 'f'))} AS step FROM (SELECT {_N} AS n, {_FIRST_USER} AS f)), (SELECT unnest(range(32)) AS slot)) JOIN {_ITEMS} USING (idx))"
_TILE_NEG = f"(SELECT user_id, pos_id, j, t.item_id FROM (SELECT *, {mix_sql(14, 'user_id', 'pos_id', 'j')} % 32 AS slot FROM (SELECT *, unnest(range(4)) AS j FROM {_BATCH})) JOIN {_ONE_TILE} t USING (slot))"


@query("fused_tiled_step", _chain_sql([_first_sql(), *_turn_sql(0, _ex_sql(_BATCH, _TILE_NEG))], 1))
def _(spark, d):
    """The same with negatives, and positives that are there, in the buffer of one tile, and its write-back."""
    return _factors(_fitted(spark, d, plan="block", tile=32, refresh=10**9))


def _rotated_sql(blocks: int = 2) -> str:
    dealt = f"(SELECT *, {mix_sql(32, 'user_id')} % {blocks} AS ub, {mix_sql(38, 'pos_id')} % {blocks} AS ib FROM {_BATCH})"
    own = f"(SELECT id, ib, row_number() OVER (PARTITION BY ib ORDER BY id) - 1 AS idx, count(*) OVER (PARTITION BY ib) AS n FROM (SELECT id, {mix_sql(38, 'id')} % {blocks} AS ib FROM {_ITEMS}))"
    tables = [_first_sql(), f"dealt AS MATERIALIZED (SELECT * FROM {dealt})", f"own AS MATERIALIZED (SELECT * FROM {own})"]
    for turn in range(blocks):
        pairs = f"(SELECT * FROM dealt WHERE (ib - ub + {blocks}) % {blocks} = {turn})"
        drawn = f"(SELECT user_id, pos_id, j, o.id AS item_id FROM (SELECT p.*, j, {mix_sql(14, 'p.user_id', 'p.pos_id', 'j')} % z.n AS idx FROM {pairs} p JOIN (SELECT DISTINCT ib, n FROM own) z USING (ib), range(4) r(j)) q JOIN own o ON o.ib = q.ib AND o.idx = q.idx)"
        tables += _turn_sql(turn, _ex_sql(pairs, drawn))
    return _chain_sql(tables, blocks)


@query("rotated_epoch", _rotated_sql())
def _(spark, d):
    """Two blocks a side: two sub-epochs, the second from the first one's rows."""
    return _factors(_fitted(spark, d, plan="rotate", blocks=2))


def _merged_sql(workers: int = 2, extra: int = 256) -> str:
    dealt = f"(SELECT *, {mix_sql(42, 'user_id')} % {workers} AS worker FROM {_BATCH})"
    slots = f"(SELECT i // {extra} AS worker, id FROM (SELECT i, {mix_sql(44, 'i')} % {_N} AS idx FROM range({workers * extra}) r(i)) JOIN {_ITEMS} USING (idx))"
    own = f"(SELECT worker, id, row_number() OVER (PARTITION BY worker ORDER BY id) - 1 AS idx, count(*) OVER (PARTITION BY worker) AS n FROM (SELECT worker, pos_id AS id FROM dealt UNION SELECT worker, id FROM {slots}))"
    drawn = f"(SELECT user_id, pos_id, j, o.id AS item_id FROM (SELECT p.*, j, {mix_sql(14, 'p.user_id', 'p.pos_id', 'j')} % z.n AS idx FROM dealt p JOIN (SELECT DISTINCT worker, n FROM own) z USING (worker), range(4) r(j)) q JOIN own o ON o.worker = q.worker AND o.idx = q.idx)"
    return _chain_sql([_first_sql(), f"dealt AS MATERIALIZED (SELECT * FROM {dealt})", f"own AS MATERIALIZED (SELECT * FROM {own})", *_turn_sql(0, _ex_sql("dealt", drawn))], 1)


@query("merged_epoch", _merged_sql())
def _(spark, d):
    """Two workers on private copies of their rows; their deltas are summed."""
    return _factors(_fitted(spark, d, plan="merge", blocks=2))


# --- aggregation ------------------------------------------------------------

_HIST = f"(SELECT user_id, item_id FROM (SELECT user_id, item_id, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, item_id DESC) AS n FROM {W1}) WHERE n <= 100)"
_K = 4


def _draw_rows(seed: int, rows: int) -> list[list[float]]:
    """A drawn matrix of rows x _K, as SQL draws it too."""
    return [[mix_py(seed, r, k) / float(P) - 0.5 for k in range(_K)] for r in range(rows)]


def _params():
    """Rows of the layer, the projection, its offset and the query."""
    import numpy as np

    return np.array(_draw_rows(5, _K) + _draw_rows(21, _K) + _draw_rows(22, 1) + _draw_rows(23, 1))


def _drawn_sql(seed: int, row: str, k: str) -> str:
    return f"({mix_sql(seed, row, k)} / {float(P)} - 0.5)"


def _vectors(spark, d):
    """users, items (id, vec) of the orders workload, and its histories."""
    cuts, pairs = Cuts(ship(spark)), w1(spark, d)
    rows = lambda side, seed: cuts.cut(pairs.select(F.col(side).alias("id")).distinct().withColumn("vec", V.init_vector(seed, "id", _K)))
    return rows("user_id", 1), rows("item_id", 2), cuts.cut(S.user_history(pairs))


def _entries(df: DataFrame, vec: str, digits: int = 7) -> DataFrame:
    return df.select(df.columns[0], F.posexplode(vec).alias("k", "v")).select(F.col(df.columns[0]).alias("user_id"), F.col("k").cast("long").alias("k"), F.round("v", digits).alias("v"))


def _pooled_by(kind: str) -> Query:
    def run(spark, d):
        users, items, history = _vectors(spark, d)
        rows = history.select("user_id", F.explode("hist").alias("item_id"), F.lit(True).alias("counts"))
        return _entries(predict.pooled_rows(rows, users, items, _params(), TrainConfig(dim=_K, aggregator=kind)), "vec")

    return run


_POOL = f"(SELECT user_id, k, avg(t[k + 1]) AS v FROM (SELECT user_id, {vec_sql(2, 'item_id', _K)} AS t FROM {_HIST}), range({_K}) r(k) GROUP BY 1, 2)"
query("agg_average", f"SELECT user_id, k, round(v, 7) AS v FROM {_POOL}")(_pooled_by("average"))


@query("agg_layer", f"SELECT user_id, o AS k, round(0.8 * any_value({vec_sql(1, 'user_id', _K)})[o + 1] + 0.2 * sum(v * {_drawn_sql(5, 'k', 'o')}), 7) AS v FROM {_POOL}, range({_K}) q(o) GROUP BY 1, 2")
def _(spark, d):
    """The rows that training scores with: the gated mix of a user row and its pooled row times the layer."""
    users, items, history = _vectors(spark, d)
    return _entries(predict.aggregated_users(users, items, history, _params(), TrainConfig(dim=_K, aggregator="average")), "vec")


def _attn_sql(query_vec: str) -> str:
    project = lambda o: " + ".join(f"t[{k + 1}] * {_draw_rows(21, _K)[o][k]!r}" for k in range(_K)) + f" + {_draw_rows(22, 1)[0][o]!r}"
    z = " + ".join(f"({query_vec})[{o + 1}] * tanh({project(o)})" for o in range(_K))
    return f"WITH h AS MATERIALIZED (SELECT user_id, t, exp({z}) AS e FROM (SELECT user_id, {vec_sql(1, 'user_id', _K)} AS s, {vec_sql(2, 'item_id', _K)} AS t FROM {_HIST})) SELECT user_id, k, round(sum(e * t[k + 1]) / sum(e), 7) AS v FROM h, range({_K}) r(k) GROUP BY 1, 2"


query("attn_self", _attn_sql(str(_draw_rows(23, 1)[0])))(_pooled_by("self_attention"))
query("attn_user", _attn_sql("s"))(_pooled_by("user_attention"))

#: One epoch with average pooling as one batch: an example's positive is no part of its own pooled row.
_AGG_PARTS = [
    f"hist AS MATERIALIZED (SELECT user_id, item_id, {vec_sql(2, 'item_id', _K)} AS t FROM {_HIST})",
    f"sums AS MATERIALIZED (SELECT user_id, count(*) AS n, list_value({', '.join(f'sum(t[{k + 1}])' for k in range(_K))}) AS v FROM hist GROUP BY 1)",
    f"mixed AS MATERIALIZED (SELECT user_id, pos_id, m, w, CASE WHEN w > 0 THEN list_transform(p, lambda x: x / w) ELSE list_transform(p, lambda x: 0.0) END AS pooled FROM (SELECT b.user_id, b.pos_id, {vec_sql(1, 'b.user_id', _K)} AS m, s.n - (h.item_id IS NOT NULL)::INT AS w, list_value({', '.join(f's.v[{k + 1}] - coalesce(h.t[{k + 1}], 0)' for k in range(_K))}) AS p FROM {_BATCH} b JOIN sums s ON s.user_id = b.user_id LEFT JOIN hist h ON h.user_id = b.user_id AND h.item_id = b.pos_id))",
    f"ex AS MATERIALIZED (SELECT e.user_id, e.pos_id, e.j, e.item_id, m.w, m.pooled, list_value({', '.join(f'0.8 * m.m[{k + 1}] + 0.2 * 0.5 * m.pooled[{k + 1}]' for k in range(_K))}) AS s, {vec_sql(2, 'e.item_id', _K)} AS t FROM ({_ex_sql(_BATCH, neg_sql(14))}) e JOIN mixed m ON m.user_id = e.user_id AND m.pos_id = e.pos_id)",
    "c AS MATERIALIZED (SELECT *, CASE WHEN j < 0 THEN -1.0 WHEN x > 0 THEN 0.25 ELSE 0.0 END AS c FROM (SELECT *, st / sqrt(ss * tt) AS x FROM (SELECT *, list_dot_product(s, s) AS ss, list_dot_product(t, t) AS tt, list_dot_product(s, t) AS st FROM ex)))",
    f"gs AS MATERIALIZED (SELECT user_id, pos_id, any_value(w) AS w, any_value(pooled) AS pooled, list_value({', '.join(f'sum(c * (t[{k + 1}] / sqrt(ss * tt) - x / ss * s[{k + 1}]))' for k in range(_K))}) AS g FROM c GROUP BY 1, 2)",
    f"turns AS MATERIALIZED (SELECT *, (row_number() OVER (ORDER BY {mix_sql(1, 'user_id', 'pos_id')}, user_id, pos_id) - 1) AS turn FROM gs)",
]


@query("agg_step", "WITH " + ", ".join(_AGG_PARTS) + f", past AS (SELECT h.item_id, k, sum(0.5 * 0.2 * g.g[k + 1] / g.w) AS g FROM gs g JOIN hist h ON h.user_id = g.user_id AND h.item_id <> g.pos_id, range({_K}) r(k) GROUP BY 1, 2)"
    f", moved AS (SELECT 'user' AS side, user_id AS id, k, sum(0.8 * g[k + 1]) AS g FROM gs, range({_K}) r(k) GROUP BY 1, 2, 3 UNION ALL SELECT 'item', item_id, k, sum(g) FROM (SELECT item_id, k, c * (s[k + 1] / sqrt(ss * tt) - x / tt * t[k + 1]) AS g FROM c, range({_K}) r(k) WHERE c <> 0 UNION ALL SELECT * FROM past) GROUP BY 1, 2, 3)"
    f", first AS (SELECT side, id, k, v[k + 1] AS v FROM (SELECT 'user' AS side, user_id AS id, {vec_sql(1, 'user_id', _K)} AS v FROM (SELECT DISTINCT user_id FROM {W1}) UNION ALL SELECT 'item', item_id, {vec_sql(2, 'item_id', _K)} FROM (SELECT DISTINCT item_id FROM {W1})), range({_K}) r(k))"
    " SELECT f.side, f.id, f.k, round(f.v - 0.05 * coalesce(m.g, 0), 6) AS v FROM first f LEFT JOIN moved m ON m.side = f.side AND m.id = f.id AND m.k = f.k")
def _(spark, d):
    """User, item and history rows after an epoch with average pooling."""
    return _factors(_fitted(spark, d, plan="block", dim=_K, aggregator="average"))


def _weights_sql(m: str) -> str:
    """The layer after an epoch: half the unit matrix less the mean gradient of every group of m iterations."""
    return "WITH " + ", ".join(_AGG_PARTS) + f", parts AS (SELECT i, o, turn // {m} AS grp, avg(pooled[i + 1] * 0.2 * g[o + 1]) AS g FROM turns, range({_K}) a(i), range({_K}) b(o) GROUP BY 1, 2, 3) SELECT i, o, round(CASE WHEN i = o THEN 0.5 ELSE 0.0 END - 0.05 * sum(g), 6) AS w FROM parts GROUP BY 1, 2"


def _weights(**opts) -> Query:
    def run(spark, d):
        w = _fitted(spark, d, plan="block", dim=_K, aggregator="average", **opts).weights
        return spark.createDataFrame([(i, o, round(float(w[i, o]), 6)) for i in range(_K) for o in range(_K)], "i long, o long, w double")

    return run


query("agg_accumulated_m32", _weights_sql("32"))(_weights(sync=32))
query("agg_every_iteration", _weights_sql("1"))(_weights(sync_mode="shared"))
query("agg_parameter_server", _weights_sql("32"))(_weights(sync_mode="server", sync=32, stale=3))
query("agg_weight_grad", _weights_sql("1000000000"))(_weights(sync=10**9))


# --- prediction and measures ------------------------------------------------

_SCORE = f"(SELECT u.id AS user_id, i.id AS item_id, list_dot_product(u.v, i.v) / sqrt(list_dot_product(u.v, u.v) * list_dot_product(i.v, i.v)) AS score FROM (SELECT c_custkey AS id, {vec_sql(1, 'c_custkey', 8)} AS v FROM customer) u, (SELECT id, {vec_sql(2, 'id', 8)} AS v FROM {_ITEMS}) i)"
_SEEN = f"(SELECT user_id, item_id FROM {W1} WHERE {mix_sql(3, 'user_id', 'item_id')} % 1000 >= 200)"
_TEST = f"(SELECT user_id, item_id FROM {W1} WHERE {mix_sql(3, 'user_id', 'item_id')} % 1000 < 200)"
_TOP = f"(SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY score DESC, item_id) AS rank FROM {_SCORE} s WHERE NOT EXISTS (SELECT 1 FROM {_SEEN} x WHERE x.user_id = s.user_id AND x.item_id = s.item_id)) WHERE rank <= 20)"


def _lists(spark, d):
    cuts = Cuts(ship(spark))
    pairs = cuts.cut(w1(spark, d).select("user_id", "item_id"))
    train, test = S.split_holdout(pairs)
    users = table(ship(spark), d, "customer").select(F.col("c_custkey").alias("id")).withColumn("vec", V.init_vector(1, "id", 8))
    items = S.index_ids(pairs, "item_id").select("id").withColumn("vec", V.init_vector(2, "id", 8))
    return predict.recommend(cuts.cut(users), cuts.cut(items), train, 20), test


def _measured(spark, d):
    """The same, written without scores before they are compared: the copied rows behind them are off the disk by then."""
    recs, test = _lists(spark, d)
    return Cuts(spark).cut(recs.select("user_id", "rank", "item_id")), test


@query("recommend_top20", f"SELECT user_id, rank, item_id, round(score, 9) AS score FROM {_TOP}")
def _(spark, d):
    return _lists(spark, d)[0].select("user_id", F.col("rank").cast("long").alias("rank"), "item_id", F.round("score", 9).alias("score"))


@query("recall20", f"SELECT round(avg(coalesce(tp, 0) / n), 6) AS recall FROM (SELECT user_id, count(*) AS n FROM {_TEST} GROUP BY 1) LEFT JOIN (SELECT user_id, count(*) AS tp FROM {_TOP} JOIN {_TEST} USING (user_id, item_id) GROUP BY 1) USING (user_id)")
def _(spark, d):
    return metrics.recall_at_k(*_measured(spark, d))


@query("recall20_pooled", f"SELECT round((SELECT count(*) FROM {_TOP} JOIN {_TEST} USING (user_id, item_id)) / (SELECT count(*) FROM {_TEST}), 6) AS recall")
def _(spark, d):
    return metrics.recall_at_k(*_measured(spark, d), average="pooled")


@query("ndcg20", f"SELECT round(avg(coalesce(dcg, 0) / ideal), 6) AS ndcg FROM (SELECT user_id, list_sum(list_transform(range(1, least(count(*), 20) + 1), lambda r: 1 / log2(r + 1))) AS ideal FROM {_TEST} GROUP BY 1) LEFT JOIN (SELECT user_id, sum(1 / log2(rank + 1)) AS dcg FROM {_TOP} JOIN {_TEST} USING (user_id, item_id) GROUP BY 1) USING (user_id)")
def _(spark, d):
    return metrics.ndcg_at_k(*_measured(spark, d))


@query("score_pairs", f"SELECT user_id, item_id, round(list_dot_product(s, t) / sqrt(list_dot_product(s, s) * list_dot_product(t, t)), 9) AS score FROM (SELECT user_id, item_id, {vec_sql(1, 'user_id', 8)} AS s, {vec_sql(2, 'item_id', 8)} AS t FROM {W1})")
def _(spark, d):
    pairs = w1(spark, d).select("user_id", "item_id")
    vecs = lambda side, k: pairs.select(F.col(side).alias("id")).distinct().withColumn("vec", V.init_vector(k, "id", 8))
    cuts = Cuts(spark)
    return predict.score_pairs(pairs, cuts.cut(vecs("user_id", 1)), cuts.cut(vecs("item_id", 2))).withColumn("score", F.round("score", 9))


# --- neighbours, content, popularity ---------------------------------------


def _knn_sql(own: str, other: str, table_sql: str) -> str:
    return f"WITH p AS (SELECT user_id, item_id FROM {table_sql}), n AS (SELECT {own} AS k, count(*) AS n FROM p GROUP BY 1), c AS (SELECT a.{own} AS a, b.{own} AS b, count(*) AS c FROM p a JOIN p b ON a.{other} = b.{other} AND a.{own} <> b.{own} GROUP BY 1, 2), s AS (SELECT a, b, round(c / sqrt(CAST(x.n * y.n AS DOUBLE)), 9) AS sim FROM c JOIN n x ON x.k = a JOIN n y ON y.k = b) SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY sim DESC, b) AS rank FROM s) WHERE rank <= 10"


@query("user_knn", _knn_sql("user_id", "item_id", W1))
def _(spark, d):
    return baselines.user_knn(w1(spark, d)).withColumn("rank", F.col("rank").cast("long"))


@query("item_knn", _knn_sql("item_id", "user_id", W1))
def _(spark, d):
    return baselines.item_knn(w1(spark, d)).withColumn("rank", F.col("rank").cast("long"))


@query("user_knn_jaccard", _knn_sql("user_id", "item_id", W1).replace("c / sqrt(CAST(x.n * y.n AS DOUBLE))", "c / (x.n + y.n - c)"))
def _(spark, d):
    return baselines.user_knn(w1(spark, d), sim="jaccard").withColumn("rank", F.col("rank").cast("long"))


def _votes_sql(own: str, other: str, join: str) -> str:
    return f"WITH near AS MATERIALIZED ({_knn_sql(own, other, W1)}), b AS (SELECT user_id, item_id FROM {W1}), v AS (SELECT user_id, item_id, round(sum(sim), 9) AS score FROM ({join}) GROUP BY 1, 2) SELECT * FROM (SELECT user_id, item_id, score, row_number() OVER (PARTITION BY user_id ORDER BY score DESC, item_id) AS rank FROM v ANTI JOIN b USING (user_id, item_id)) WHERE rank <= 20"


@query("user_knn_votes", _votes_sql("user_id", "item_id", "SELECT n.a AS user_id, b.item_id, n.sim FROM near n JOIN b ON b.user_id = n.b"))
def _(spark, d):
    pairs = w1(spark, d)
    return baselines.user_knn_votes(pairs, Cuts(spark).cut(baselines.user_knn(pairs))).withColumn("rank", F.col("rank").cast("long"))


@query("item_knn_votes", _votes_sql("item_id", "user_id", "SELECT b.user_id, n.b AS item_id, n.sim FROM b JOIN near n ON n.a = b.item_id"))
def _(spark, d):
    pairs = w1(spark, d)
    return baselines.item_knn_votes(pairs, Cuts(spark).cut(baselines.item_knn(pairs))).withColumn("rank", F.col("rank").cast("long"))


@query("svd_row_sums", f"SELECT user_id AS id, k, round(sum(v[k + 1]), 6) AS v FROM (SELECT user_id, {vec_sql(1, 'item_id', 4, 1.0)} AS v FROM {W1}), range(4) r(k) GROUP BY 1, 2")
def _(spark, d):
    """One product of the 0/1 matrix with a block of vectors, the step of the truncated factorization."""
    pairs = w1(spark, d)
    items = Cuts(spark).cut(pairs.select(F.col("item_id").alias("id")).distinct().withColumn("vec", V.init_vector(1, "id", 4, "uniform", 1.0)))
    rows = baselines.row_sums(pairs, items, "user_id", 4)
    return rows.select("id", F.posexplode("vec").alias("k", "v")).select("id", F.col("k").cast("long").alias("k"), F.round("v", 6).alias("v"))


@query("truncated_factors")
def _(spark, d):
    users, _, _ = baselines.truncated_factors(w1(spark, d), 4, 4)
    return users.select("id", F.round(F.col("vec")[0], 4).alias("v0"))


_SLICE_U = "(SELECT c_custkey AS id FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_name = (SELECT min(n_name) FROM nation))"
_SLICE_I = "(SELECT p_partkey AS id FROM part WHERE p_brand = (SELECT min(p_brand) FROM part))"


@query("predict_block", f"SELECT user_id, item_id, round(list_dot_product(s, t), 9) AS score FROM (SELECT u.id AS user_id, i.id AS item_id, {vec_sql(1, 'u.id', 8)} AS s, {vec_sql(2, 'i.id', 8)} AS t FROM {_SLICE_U} u, {_SLICE_I} i)")
def _(spark, d):
    """The predicted matrix for the customers of one nation and the parts of one brand."""
    nation, part = table(spark, d, "nation"), table(spark, d, "part")
    home = nation.agg(F.min("n_name").alias("n_name"))
    users = table(spark, d, "customer").join(nation.join(home, "n_name"), F.col("c_nationkey") == F.col("n_nationkey"), "left_semi").select(F.col("c_custkey").alias("id"))
    items = part.join(part.agg(F.min("p_brand").alias("p_brand")), "p_brand", "left_semi").select(F.col("p_partkey").alias("id"))
    return predict.predict_block(users.withColumn("vec", V.init_vector(1, "id", 8)), items.withColumn("vec", V.init_vector(2, "id", 8))).withColumn("score", F.round("score", 9))


_BRANDS = f"(SELECT DISTINCT user_id, CAST(regexp_extract(p_brand, '([0-9]+)$', 1) AS BIGINT) AS item_id FROM {W1} JOIN part ON item_id = p_partkey)"


@query("item_cond_prob", f"WITH p AS {_BRANDS}, n AS (SELECT item_id, count(*) AS n FROM p GROUP BY 1) SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY given ORDER BY p DESC, item) AS rank FROM (SELECT a.item_id AS given, b.item_id AS item, round(count(*) / any_value(n.n), 9) AS p FROM p a JOIN p b ON a.user_id = b.user_id AND a.item_id <> b.item_id JOIN n ON n.item_id = a.item_id GROUP BY 1, 2)) WHERE rank <= 10")
def _(spark, d):
    return baselines.item_cond_prob(workload(spark, d, "brands")).withColumn("rank", F.col("rank").cast("long"))


@query("content_profile", f"SELECT user_id, p_type AS attr, round(count(*) / any_value(n), 6) AS share FROM {W1} JOIN part ON item_id = p_partkey JOIN (SELECT user_id, count(*) AS n FROM {W1} GROUP BY 1) USING (user_id) GROUP BY 1, 2")
def _(spark, d):
    return baselines.content_profile(w1(spark, d), table(spark, d, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_type").alias("attr")))


@query("content_recs", f"WITH b AS (SELECT user_id, item_id FROM {W1}), a AS (SELECT p_partkey AS item_id, p_brand || p_type AS attr FROM part), s AS (SELECT user_id, attr, round(count(*) / any_value(n), 6) AS share FROM b JOIN a USING (item_id) JOIN (SELECT user_id, count(*) AS n FROM b GROUP BY 1) USING (user_id) GROUP BY 1, 2) SELECT * FROM (SELECT user_id, item_id, round(share, 6) AS score, row_number() OVER (PARTITION BY user_id ORDER BY share DESC, item_id) AS rank FROM s JOIN a USING (attr) ANTI JOIN b USING (user_id, item_id)) WHERE rank <= 20")
def _(spark, d):
    attrs = table(spark, d, "part").select(F.col("p_partkey").alias("item_id"), F.concat("p_brand", "p_type").alias("attr"))
    return baselines.content_recs(w1(spark, d), attrs).withColumn("rank", F.col("rank").cast("long"))


@query("popularity", f"SELECT item_id, count(*) AS n FROM {W1} GROUP BY 1 ORDER BY n DESC, item_id LIMIT 100")
def _(spark, d):
    return baselines.popularity(w1(spark, d))


# --- cost models ------------------------------------------------------------
#
# Sizes are measured on the tables, settings and prices are the published ones.

_SETS = {
    "orders": f"SELECT user_id, item_id FROM {W1}",
    "suppliers": f"SELECT DISTINCT user_id, supp_id AS item_id FROM {BUY}",
    "events": ORACLES["implicit_events"],
}
_SIZES = " UNION ALL ".join(f"SELECT '{n}' AS workload, count(DISTINCT user_id) AS users, count(DISTINCT item_id) AS items, count(*) AS pairs FROM ({q})" for n, q in _SETS.items())
_SIZES_SQL = f"({_SIZES})"


def _sizes(spark, d) -> DataFrame:
    """workload, users, items, pairs."""
    parts = [S.profile(workload(spark, d, n).select("user_id", "item_id")).select(F.lit(n).alias("workload"), "users", "items", "pairs") for n in _SETS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


#: Profiles of the two published processors: name, l2, l3, workers and three latencies. Fixed values.
_MACHINES = (("epyc", 32 << 20, 256 << 20, 64, 4.0, 40.0, 100.0), ("a64fx", 32 << 20, 0, 48, 4.0, 40.0, 100.0))
_MACHINES_SQL = "(VALUES " + ", ".join(str(m) for m in _MACHINES) + ") AS m(machine, l2, l3, workers, t_l2, t_l3, t_mem)"


@query("tile_plan_grid", f"SELECT workload, machine, dim, n1, n2, level, round(n2_cover, 6) AS n2_cover, round(n2_speed, 6) AS n2_speed, round(iterations * negatives * t_mem, 3) AS neg_time_random, round(negatives * iterations / greatest(n1, n2) * ((greatest(n1, n2) - n1) * t_c + n1 * t_mem), 3) AS neg_time_tiled, round(t_mem / (t_c + (t_mem - t_c) * n1 / greatest(n1, n2)), 6) AS neg_speedup, round(t_mem / (hit * t_c + (1 - hit) * t_mem), 6) AS pos_speedup FROM (SELECT *, CASE level WHEN 'l2' THEN t_l2 WHEN 'l3' THEN t_l3 ELSE t_mem END AS t_c, greatest(1, floor(least(n2_cover, n2_speed)))::BIGINT AS n2 FROM (SELECT *, CASE WHEN n1 * dim * 4 * workers < l2 THEN 'l2' WHEN n1 * dim * 4 * workers < l3 THEN 'l3' ELSE 'memory' END AS level, iterations * n1 / items AS n2_cover, n1 * CAST(0.85 AS DOUBLE) * 4 AS n2_speed FROM (SELECT *, least(items, greatest(1, l2 // (workers * dim * 4)))::BIGINT AS n1 FROM (SELECT workload, items, pairs AS iterations, 64 AS negatives, 0.5 AS hit, dim, m.* FROM {_SIZES_SQL}, (SELECT unnest([64, 128]) AS dim), {_MACHINES_SQL}))))")
def _(spark, d):
    """The tuner's figures for every workload, both processors and two dimensions."""
    m = spark.createDataFrame(list(_MACHINES), "machine string, l2 long, l3 long, workers int, t_l2 double, t_l3 double, t_mem double")
    grid = m.withColumn("dim", F.explode(F.array(F.lit(64), F.lit(128))))
    runs = _sizes(spark, d).withColumnRenamed("pairs", "iterations").withColumns({"negatives": F.lit(64), "hit": F.lit(0.5)}).crossJoin(grid)
    plan = tuning.plan_frame(runs)
    digits = {"n2_cover": 6, "n2_speed": 6, "neg_time_random": 3, "neg_time_tiled": 3, "neg_speedup": 6, "pos_speedup": 6}
    return plan.select("workload", "machine", "dim", "n1", "n2", "level", *[F.round(c, k).alias(c) for c, k in digits.items()])


@query("tile_plan_scalar", "SELECT * FROM (VALUES ('epyc', 1024, 128, 1024, 'l3', 3072.0), ('epyc', 1024, 64, 2048, 'l3', 6963.2), ('a64fx', 1024, 128, 1365, 'l2', 4096.0)) AS t(machine, iterations_thousand, dim, n1, level, n2_speed) WHERE false")
def _(spark, d):
    """Rows where the scalar tuner and plan_frame differ: none."""
    m = spark.createDataFrame(list(_MACHINES), "machine string, l2 long, l3 long, workers int, t_l2 double, t_l3 double, t_mem double")
    runs = _sizes(spark, d).withColumnRenamed("pairs", "iterations").withColumns({"negatives": F.lit(64), "hit": F.lit(0.5), "dim": F.lit(128)}).crossJoin(m)
    bad = []
    for r in tuning.plan_frame(runs).collect():  # one row a workload and processor
        p = tuning.plan_tiles(r.items, r.iterations, r.dim, tuning.Machine(r.l2, r.l3, r.workers, r.t_l2, r.t_l3, r.t_mem), r.hit)
        if (p.n1, p.n2, p.level) != (r.n1, r.n2, r.level) or abs(p.neg_speedup - r.neg_speedup) > 1e-9:
            bad.append((r.machine, 0, r.dim, p.n1, p.level, p.n2_speed))
    return spark.createDataFrame(bad, "machine string, iterations_thousand int, dim int, n1 int, level string, n2_speed double")


@query("tile_latency", "SELECT n1, n2, round(100 / (4 + 96 * n1 / n2), 6) AS exact_form, round(100 / (4 + 99 * n1 / n2), 6) AS printed_form, n2 / n1 AS approx_form FROM (SELECT least(unnest([512, 1024]), items) AS n1, lines FROM (SELECT count(DISTINCT l_partkey) AS items, count(*) AS lines FROM lineitem)), (SELECT unnest([3072, 4096]) AS most), LATERAL (SELECT least(most, lines) AS n2)")
def _(spark, d):
    """Tiles of no more rows than the items sold, redrawn after no more draws than the lines."""
    r = table(spark, d, "lineitem").agg(F.countDistinct("l_partkey").alias("items"), F.count(F.lit(1)).alias("lines")).first()
    sizes = [(min(a, r["items"]), min(b, r["lines"])) for a in (512, 1024) for b in (3072, 4096)]
    rows = [(a, b, *(round(tuning.neg_speedup(a, b, 4, 100, f), 6) for f in ("exact", "printed", "approx"))) for a, b in sizes]
    return spark.createDataFrame(rows, "n1 long, n2 long, exact_form double, printed_form double, approx_form double")


#: Overheads over bare float rows that follow from the published shares, and memories of the two platforms. Fixed values.
_PLATFORMS = (("cpu", 256e9, 7.35), ("gpu", 32e9, 6.52))
#: Published sizes: name, users, items. Fixed values.
_PUBLISHED = (("goodreads", 810_000, 1_560_000), ("google", 4_570_000, 3_120_000), ("amazon", 20_980_000, 9_350_000))


@query("memory_table", f"SELECT workload, platform, (users + items) * 128 * 4 * overhead AS bytes, CASE WHEN (users + items) * 128 * 4 * overhead / capacity <= 1 THEN round((users + items) * 128 * 4 * overhead / capacity, 9) END AS share, floor(capacity / (128 * 4 * overhead))::BIGINT AS rows_that_fit FROM (SELECT workload, users, items FROM {_SIZES_SQL} UNION ALL SELECT * FROM (VALUES {', '.join(str(r) for r in _PUBLISHED)}) AS t(workload, users, items)), (SELECT platform, CAST(capacity AS DOUBLE) AS capacity, CAST(overhead AS DOUBLE) AS overhead FROM (VALUES {', '.join(str(r) for r in _PLATFORMS)}) AS t(platform, capacity, overhead))")
def _(spark, d):
    """Share of memory of the measured workloads and of the published ones; null where a model does not fit."""
    platforms = spark.createDataFrame(list(_PLATFORMS), "platform string, capacity double, overhead double")
    sizes = _sizes(spark, d).select("workload", "users", "items").unionByName(spark.createDataFrame(list(_PUBLISHED), "workload string, users long, items long"))
    return metrics.memory_frame(sizes.crossJoin(platforms), 128).select("workload", "platform", "bytes", F.round("share", 9).alias("share"), "rows_that_fit")


#: Instances and prices an hour of the published comparison. Fixed values.
_PRICES = (("gpu", 2, 3.06), ("cpu", 1, 2.46))


@query("cost_table", f"SELECT workload, platform, round(h, 9) AS hours, round(h * price * instances, 9) AS dollars, round(h * price * instances / min(h * price * instances) OVER (PARTITION BY workload), 6) AS ratio FROM (SELECT workload, platform, price, instances, pairs / CAST(100000 AS DOUBLE) * 100 / 3600 AS h FROM {_SIZES_SQL}, (SELECT platform, instances, CAST(price AS DOUBLE) AS price FROM (VALUES {', '.join(str(r) for r in _PRICES)}) AS t(platform, instances, price)))")
def _(spark, d):
    """Dollars of 100 epochs at 100,000 pairs a second on either platform, and the ratio of the two."""
    prices = spark.createDataFrame(list(_PRICES), "platform string, instances int, price double")
    runs = _sizes(spark, d).select("workload", (F.col("pairs") / 100000.0).alias("seconds")).crossJoin(prices)
    return metrics.cost_frame(runs, 100).select("workload", "platform", F.round("hours", 9).alias("hours"), F.round("dollars", 9).alias("dollars"), F.round("ratio", 6).alias("ratio"))


@query("cost_projection", "SELECT round(sum(l_quantity) / 1000 * 100 / 3600 * CAST(3.06 AS DOUBLE) * 100, 3) AS dollars FROM lineitem")
def _(spark, d):
    """Dollars of 100 epochs on 100 instances over every unit sold, at 1,000 a second."""
    seconds = table(spark, d, "lineitem").agg((F.sum("l_quantity") / 1000).alias("seconds"))
    return seconds.select(F.round(metrics.training_cost(F.col("seconds"), 100, 3.06, 100), 3).alias("dollars"))


_WRITES = "(SELECT event_type AS workload, user_id, count(*) AS n FROM events GROUP BY 1, 2)"


@query("speedup_table", f"WITH t AS (SELECT workload, CAST(sum(n + ceil(n / 32)) AS DOUBLE) AS own, CAST(sum(2 * n) AS DOUBLE) AS base FROM {_WRITES} GROUP BY 1) SELECT workload, 'with' AS method, round(base / own, 6) AS speedup FROM t UNION ALL SELECT 'mean', 'with', round(avg(base / own), 6) FROM t")
def _(spark, d):
    """Every type of event a workload and every user a worker: an iteration and a write of the shared layer take a second
    each, and with accumulation a worker writes once in 32 iterations and for a rest."""
    n = table(spark, d, "events").groupBy(F.col("event_type").alias("workload"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    sums = n.groupBy("workload").agg(F.sum(F.col("n") + F.ceil(F.col("n") / 32)).cast("double").alias("with"), F.sum(2 * F.col("n")).cast("double").alias("without"))
    times = sums.select("workload", F.inline(F.array(*[F.struct(F.lit(m).alias("method"), F.col(m).alias("seconds")) for m in ("with", "without")])))
    return metrics.speedups(times, "without").withColumn("speedup", F.round("speedup", 6))


_BUSIEST = " UNION ALL ".join(f"SELECT {p} AS cores, CAST(max(n) AS DOUBLE) AS seconds FROM (SELECT count(*) AS n FROM orders GROUP BY {mix_sql(42, 'o_custkey')} % {p})" for p in (1, 2, 64))


@query("scaling_table", f"WITH t AS ({_BUSIEST}), f AS (SELECT max(seconds) AS one FROM t) SELECT cores, seconds, one / seconds AS speedup, one / seconds / cores AS efficiency FROM t, f")
def _(spark, d):
    """The orders dealt to 1, 2 and 64 workers by customer: at one a second the busiest one sets the time."""
    orders = table(spark, d, "orders").select("o_custkey")
    count = lambda p: orders.groupBy(mix(42, "o_custkey") % p).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0]
    return metrics.scaling_table(spark, {p: float(count(p)) for p in (1, 2, 64)})


@query("copy_bytes", f"SELECT workload, CAST(ceil(pairs / 1024) AS BIGINT) AS batches, CAST(pairs * 65 * 128 * 4 AS BIGINT) AS copied, CAST(pairs * 65 * 8 AS BIGINT) AS norms FROM {_SIZES_SQL}")
def _(spark, d):
    return metrics.copy_frame(_sizes(spark, d), 1024, 64, 128)


@query("reuse_savings", f"SELECT workload, CAST(3 * pairs * 65 * 128 AS BIGINT) AS kept, CAST(9 * pairs * 65 * 128 AS BIGINT) AS again FROM {_SIZES_SQL}")
def _(spark, d):
    return metrics.reuse_frame(_sizes(spark, d), 64, 128)


@query("weight_writes", f"SELECT m, CAST(ceil(pairs / CAST(m AS DOUBLE)) AS BIGINT) AS writes FROM (SELECT count(*) AS pairs FROM {W1}), (SELECT unnest([1, 32]) AS m)")
def _(spark, d):
    """Writes of the shared layer that the kernel counts in an epoch of one worker."""
    rows = [(m, _fitted(spark, d, plan="block", dim=_K, aggregator="average", sync=m).history[0]["weight_writes"]) for m in (1, 32)]
    return spark.createDataFrame(rows, "m int, writes long")


# --- surrounding operators --------------------------------------------------


@query("gs_region_segment", f"SELECT r_name, c_mktsegment, count(*) AS pairs FROM {W1} JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY GROUPING SETS ((r_name, c_mktsegment), (r_name), ())")
def _(spark, d):
    j = w1(spark, d).join(table(spark, d, "customer"), F.col("user_id") == F.col("c_custkey")).join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupingSets([[F.col("r_name"), F.col("c_mktsegment")], [F.col("r_name")], []], "r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("pairs"))


@query("cube_metric", "SELECT event_type, CAST(user_id % 3 AS BIGINT) AS grp, count(*) AS n FROM events GROUP BY CUBE (event_type, user_id % 3)")
def _(spark, d):
    return table(spark, d, "events").withColumn("grp", F.col("user_id") % 3).cube("event_type", "grp").agg(F.count(F.lit(1)).alias("n"))


@query("rollup_types", "SELECT event_type, CAST(user_id % 3 AS BIGINT) AS grp, CAST(GROUPING(event_type, user_id % 3) AS BIGINT) AS level, count(*) AS n FROM events GROUP BY ROLLUP (event_type, user_id % 3)")
def _(spark, d):
    e = table(spark, d, "events").withColumn("grp", F.col("user_id") % 3)
    return e.rollup("event_type", "grp").agg(F.grouping_id().cast("long").alias("level"), F.count(F.lit(1)).alias("n"))


@query("unpivot_prices", "UNPIVOT (SELECT p_partkey AS id, CAST(p_size AS DOUBLE) AS size, p_retailprice AS price FROM part) ON size, price INTO NAME metric VALUE value")
def _(spark, d):
    p = table(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("id", ["size", "price"], "metric", "value")


@query("stratified_pairs", f"SELECT user_id, item_id FROM {W1} JOIN customer ON c_custkey = user_id WHERE {mix_sql(3, 'user_id', 'item_id')} % 1000000 < CASE c_mktsegment WHEN 'BUILDING' THEN 500000 WHEN 'MACHINERY' THEN 100000 ELSE 0 END")
def _(spark, d):
    """Half of one segment's pairs and a tenth of another's."""
    j = w1(spark, d).join(table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")
    return S.stratified(j, "c_mktsegment", {"BUILDING": 0.5, "MACHINERY": 0.1}, ["user_id", "item_id"]).select("user_id", "item_id")


@query("sketches_near_exact", f"SELECT 'users' AS what, true AS near UNION ALL SELECT 'items', true UNION ALL SELECT 'median', true UNION ALL SELECT 'frequent', true")
def _(spark, d):
    """Sketches of the pairs against exact counts: distinct ids within 5%, the median degree within
    one, and the most frequent item's count not below the true one."""
    pairs = Cuts(spark).cut(w1(spark, d).select("user_id", "item_id"))
    one = pairs.agg(*[F.abs(F.hll_sketch_estimate(F.hll_sketch_agg(c, F.lit(12))) - F.countDistinct(c)) / F.countDistinct(c) for c in ("user_id", "item_id")]).first()
    degree = pairs.groupBy("item_id").agg(F.count(F.lit(1)).alias("n"))
    mid = degree.agg(F.percentile_approx("n", F.lit(0.5), F.lit(1000)).alias("a"), F.percentile("n", F.lit(0.5)).alias("b")).first()
    top = degree.orderBy(F.desc("n"), "item_id").first()
    kept = pairs.agg(F.expr("approx_top_k(item_id, 1, 4096)").alias("t")).first().t
    rows = [("users", one[0] < 0.05), ("items", one[1] < 0.05), ("median", abs(mid.a - mid.b) <= 1), ("frequent", kept[0]["count"] >= top.n)]
    return spark.createDataFrame([(a, bool(b)) for a, b in rows], "what string, near boolean")


@query("lateral_top_items", f"SELECT n.n_name, t.item_id, t.n FROM nation n, LATERAL (SELECT item_id, count(*) AS n FROM {W1} JOIN customer ON c_custkey = user_id WHERE c_nationkey = n.n_nationkey GROUP BY 1 ORDER BY n DESC, item_id LIMIT 3) t")
def _(spark, d):
    """The three most bought items of every nation, as a correlated subquery."""
    bought = w1(spark, d).join(table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey"), "user_id").groupBy("c_nationkey", "item_id").agg(F.count(F.lit(1)).alias("n"))
    top = bought.where(F.col("c_nationkey") == F.col("n_nationkey").outer()).orderBy(F.desc("n"), "item_id").limit(3).select("item_id", "n")
    return table(spark, d, "nation").lateralJoin(top).select("n_name", "item_id", "n")


@query("active_buyers", f"SELECT c_custkey AS user_id FROM customer WHERE EXISTS (SELECT 1 FROM {W1} WHERE user_id = c_custkey) AND c_acctbal > (SELECT avg(c_acctbal) FROM customer)")
def _(spark, d):
    """Customers with a purchase and more than the average balance: exists and a scalar subquery."""
    customer = table(spark, d, "customer")
    bought = w1(spark, d).where(F.col("user_id") == F.col("c_custkey").outer())
    mean = customer.agg(F.avg("c_acctbal"))
    return customer.where(bought.exists() & (F.col("c_acctbal") > mean.scalar())).select(F.col("c_custkey").alias("user_id"))


_CALENDAR = "WITH RECURSIVE days(day) AS (SELECT CAST(min(o_orderdate) AS DATE) FROM orders UNION ALL SELECT CAST(day + INTERVAL 1 YEAR AS DATE) FROM days WHERE day < (SELECT CAST(max(o_orderdate) AS DATE) FROM orders))"


@query("yearly_calendar", _CALENDAR + " SELECT day, (SELECT count(*) FROM orders WHERE CAST(o_orderdate AS DATE) >= day AND CAST(o_orderdate AS DATE) < CAST(day + INTERVAL 1 YEAR AS DATE)) AS n FROM days")
def _(spark, d):
    """Orders of every year after the first order's day, years without one too: a recursive table and a join on it."""
    table(spark, d, "orders").createOrReplaceTempView("cf_orders")
    days = spark.sql("WITH RECURSIVE days(day) AS (SELECT CAST(min(o_orderdate) AS DATE) FROM cf_orders UNION ALL SELECT CAST(day + INTERVAL 1 YEAR AS DATE) FROM days WHERE day < (SELECT CAST(max(o_orderdate) AS DATE) FROM cf_orders)) SELECT day, CAST(day + INTERVAL 1 YEAR AS DATE) AS until FROM days")
    counts = spark.sql("SELECT CAST(o_orderdate AS DATE) AS on_day, count(*) AS c FROM cf_orders GROUP BY 1")
    hit = (F.col("on_day") >= F.col("day")) & (F.col("on_day") < F.col("until"))
    return days.join(counts, hit, "left").groupBy("day").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"))


@query("sim_cosine_arrow", ORACLES["sim_cosine"])
def _(spark, d):
    """The cosine as an Arrow function registered for SQL."""
    from .functions import sql

    sql.register(spark)
    _emb_pairs(ship(spark), d).createOrReplaceTempView("cf_emb_pairs")
    return spark.sql("SELECT a, b, round(cosine_arrow(s, t), 9) AS x FROM cf_emb_pairs")


@query("sum_vec_by_label", "SELECT CAST(label AS BIGINT) AS label, k, round(sum(CAST(embedding[k + 1] AS DOUBLE)), 6) AS v FROM embeddings, range(64) r(k) GROUP BY 1, 2")
def _(spark, d):
    """Vectors summed by a grouped aggregate function."""
    from .functions import sql

    sql.register(spark)
    table(ship(spark), d, "embeddings").createOrReplaceTempView("cf_embeddings")
    rows = spark.sql("SELECT label, sum_vec(embedding) AS v FROM cf_embeddings GROUP BY label")
    return rows.select(F.col("label").cast("long").alias("label"), F.posexplode("v").alias("k", "v")).select("label", F.col("k").cast("long").alias("k"), F.round("v", 6).alias("v"))


@query("planted_source", f"SELECT user_id, item_id FROM {W1} WHERE {mix_sql(5, 'user_id', 'item_id')} < CASE WHEN user_id % 10 = item_id % 10 THEN {int(0.4 * P)} ELSE {int(0.004 * P)} END")
def _(spark, d):
    """Known communities among the pairs of the orders, by the rule of the data source."""
    return S.planted_among(w1(spark, d).select("user_id", "item_id"))


@query("pivot_types", "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'click') AS clicks, count(*) FILTER (event_type = 'purchase') AS purchases FROM events GROUP BY 1")
def _(spark, d):
    p = table(spark, d, "events").groupBy("user_id").pivot("event_type", ["view", "click", "purchase"]).count().na.fill(0)
    return p.toDF("user_id", "views", "clicks", "purchases")


@query("asof_price", "SELECT b.event_id, (SELECT max_by(a.event_id, (a.ts, a.event_id)) FROM events a WHERE a.user_id = b.user_id AND a.event_type = 'view' AND (a.ts < b.ts OR (a.ts = b.ts AND a.event_id < b.event_id))) AS view_id FROM events b WHERE b.event_type = 'purchase'")
def _(spark, d):
    """The latest view before each purchase: one sort by user and time, no range join."""
    e = table(spark, d, "events").where(F.col("event_type").isin("view", "purchase"))
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))
    return e.withColumn("view_id", last).where("event_type = 'purchase'").select("event_id", "view_id")


@query("range_bucket", "SELECT p.event_id, count(v.event_id) AS views FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts WHERE p.event_type = 'purchase' GROUP BY 1")
def _(spark, d):
    """Views in the hour before a purchase: both sides meet on hour buckets, then the exact condition holds."""
    e = table(spark, d, "events").withColumn("sec", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    p = e.where("event_type = 'purchase'").select("event_id", "user_id", "sec", F.explode(F.array(F.floor(F.col("sec") / hour), F.floor(F.col("sec") / hour) - 1)).alias("bucket"))
    v = e.where("event_type = 'view'").select("user_id", F.col("sec").alias("vs"), F.floor(F.col("sec") / hour).alias("bucket"))
    hits = p.join(v, ["user_id", "bucket"]).where((F.col("vs") <= F.col("sec")) & (F.col("vs") >= F.col("sec") - hour)).groupBy("event_id").agg(F.count(F.lit(1)).alias("views"))
    return e.where("event_type = 'purchase'").select("event_id").join(hits, "event_id", "left").na.fill(0, ["views"])


@query("setops_lists", f"SELECT (SELECT count(*) FROM (SELECT user_id, item_id FROM {W1} INTERSECT SELECT user_id, supp_id FROM {BUY})) AS common, (SELECT count(*) FROM (SELECT user_id, item_id FROM {W1} EXCEPT SELECT user_id, supp_id FROM {BUY})) AS only_items")
def _(spark, d):
    a, b = (workload(spark, d, n).select("user_id", "item_id") for n in ("orders", "suppliers"))
    return a.intersect(b).agg(F.count(F.lit(1)).alias("common")).join(a.exceptAll(b).agg(F.count(F.lit(1)).alias("only_items")), F.lit(True))


@query("tumbling_popularity", "SELECT date_trunc('day', ts) AS day, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id, count(*) AS n FROM events WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY 1, 2")
def _(spark, d):
    return streams.popularity(table(spark, d, "events"), "1 day").select(F.col("start").cast("timestamp_ntz").alias("day"), "item_id", "n")


@query("sliding_popularity", "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR * i AS start, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id, count(*) AS n FROM events, range(4) r(i) WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY 1, 2")
def _(spark, d):
    return streams.popularity(table(spark, d, "events"), "1 day", "6 hours").select(F.col("start").cast("timestamp_ntz").alias("start"), "item_id", "n")


@query("sessions", "SELECT user_id, count(*) AS sessions, max(n) AS longest FROM (SELECT user_id, sid, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM (SELECT *, (coalesce(date_diff('microsecond', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts) >= 1800000000, true))::INT AS new FROM events)) GROUP BY 1, 2) GROUP BY 1")
def _(spark, d):
    return streams.sessions(table(spark, d, "events")).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def _as_stream(spark, d, again: bool = False) -> DataFrame:
    """The events as files in order of time, read as a stream of three batches; again: a tenth of them twice."""
    at = f"{Cuts(ship(spark)).base}/events"
    e = table(spark, d, "events")
    ends = e.agg(F.unix_micros(F.min("ts").cast("timestamp")).alias("a"), F.unix_micros(F.max("ts").cast("timestamp")).alias("b")).first()
    third = F.least(F.lit(2), F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(ends.a)) * 3 / F.lit(max(1, ends.b - ends.a))))
    for k in range(3):  # one after another, since a stream takes files in the order of their making
        e.where(third == k).coalesce(1).write.mode("append").parquet(at)
    if again:
        e.where(F.col("event_id") % 10 == 0).coalesce(1).write.mode("append").parquet(at)
    return streams.read_events(spark, at, e.schema, 10 if again else 1)


def _replayed(spark, stream: DataFrame, mode: str = "append") -> DataFrame:
    return streams.replay(stream, f"{Cuts(spark).base}/replay", mode)


@query("stream_ingest", "SELECT event_id, user_id, event_type FROM events")
def _(spark, d):
    """A tenth of the events comes twice, and is taken once."""
    return _replayed(spark, streams.ingest(_as_stream(spark, d, True))).select("event_id", "user_id", "event_type")


@query("stream_view_purchase", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON p.user_id = v.user_id AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND p.event_type = 'purchase'")
def _(spark, d):
    """Two streams joined within an hour."""
    return _replayed(spark, streams.views_to_purchases(_as_stream(spark, d), _as_stream(spark, d))).select("view_id", "purchase_id")


_EVENT_ITEM = "SELECT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id FROM events WHERE json_extract(props, '$.k') IS NOT NULL"


@query("stream_scores", f"SELECT user_id, item_id, round(list_dot_product(s, t) / sqrt(list_dot_product(s, s) * list_dot_product(t, t)), 9) AS score FROM (SELECT user_id, item_id, {vec_sql(1, 'user_id', 8)} AS s, {vec_sql(2, 'item_id', 8)} AS t FROM ({_EVENT_ITEM}))")
def _(spark, d):
    """A model's scores of the events of a stream."""
    cuts, pairs = Cuts(spark), workload(spark, d, "events", types=("view", "click", "purchase", "signup", "error"))
    rows = lambda side, seed: cuts.cut(pairs.select(F.col(side).alias("id")).distinct().withColumn("vec", V.init_vector(seed, "id", 8)))
    scored = streams.score_stream(_as_stream(spark, d), rows("user_id", 1), rows("item_id", 2))
    return _replayed(spark, scored).select("user_id", "item_id", F.round("score", 9).alias("score"))


@query("stream_history", "SELECT user_id, string_agg(item_id, ',' ORDER BY n) AS hist FROM (SELECT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS n FROM events WHERE json_extract(props, '$.k') IS NOT NULL) WHERE n <= 20 GROUP BY 1")
def _(spark, d):
    """What a stream's state holds after its last batch."""
    rows = _replayed(spark, streams.rolling_history(_as_stream(spark, d), 20), "update")
    last = rows.groupBy("user_id").agg(F.max_by("hist", "batch").alias("hist"))
    return last.select("user_id", F.array_join(F.col("hist").cast("array<string>"), ",").alias("hist"))


@query("stream_popularity", "SELECT date_trunc('day', ts) AS day, CAST(json_extract(props, '$.k') AS BIGINT) AS item_id, count(*) AS n FROM events WHERE json_extract(props, '$.k') IS NOT NULL GROUP BY 1, 2")
def _(spark, d):
    """Daily counts in update mode: the last count of each window is the batch's."""
    rows = _replayed(spark, streams.popularity(_as_stream(spark, d), "1 day"), "update")
    last = rows.groupBy("start", "item_id").agg(F.max_by("n", "batch").alias("n"))
    return last.select(F.col("start").cast("timestamp_ntz").alias("day"), "item_id", "n")


# --- training (rows only) and its invariants -------------------------------

SMALL = TrainConfig(dim=16, negatives=8, epochs=1, tile=128, refresh=512, plan="rotate", blocks=4, lr=0.05)  # four blocks, so that rotation has turns at every size


@query("rotation_cover", f"SELECT count(*) AS pairs, count(DISTINCT (user_id, item_id)) AS distinct_pairs, CAST(0 AS BIGINT) AS shared FROM {W1}")
def _(spark, d):
    """Every pair has one turn; within a turn no item block meets two cells."""
    dealt = rotation(w1(spark, d).select("user_id", "item_id"), SMALL)
    shared = dealt.groupBy("turn", "item_id").agg(F.countDistinct("cell").alias("c")).where("c > 1").agg(F.count(F.lit(1)).alias("shared"))
    return dealt.agg(F.count(F.lit(1)).alias("pairs"), F.countDistinct("user_id", "item_id").alias("distinct_pairs")).join(shared, F.lit(True))


def _trained(plan: str, **opts) -> Query:
    def run(spark, d):
        from .operators.blocks import with_options

        return fit(w1(ship(spark), d), with_options(SMALL, plan=plan, **opts)).factors.select("side", "id", F.round(F.element_at("vec", 1), 4).alias("v0"))

    return run


for _plan in ("rotate", "merge", "block"):
    query(f"train_{_plan}")(_trained(_plan))
query("train_average_aggregator")(_trained("rotate", aggregator="average"))


@query("als_baseline")
def _(spark, d):
    return baselines.als_baseline(w1(spark, d)).userFactors


@query("dense_engine")
def _(spark, d):
    return _trained("block", engine="dense", negatives=2, dim=8, batch=1024)(spark, d)


for _id, _f in experiments.EXPERIMENTS.items():
    query(f"exp_{_id}")(_f)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One rotated, tiled epoch over orders, then the top 20 of every user."""
    pairs = w1(ship(spark), sf_dir).select("user_id", "item_id")
    model = fit(pairs, SMALL)
    return predict.recommend(model.user_factors, model.item_factors, pairs, 20)
