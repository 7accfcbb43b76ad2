"""Near-duplicate classes by an LSH forest.

A document's set is its distinct word shingles. Equal sets are one class from the start and
only their smallest id goes on. SIGNATURE minhash values give ORDERS sorted orders, order k
being the signature rotated by k steps; neighbours with a long common prefix in an order are
runs of equal prefixes, the regions. Regions start at depth 4 and deepen where more than
REGION documents share a prefix; the region they came from stays as a crowd. Within a region all pairs
are compared on full sets, in blocks of about BLOCK documents and at most about BLOCK_SHINGLES shingles, so no task
holds more than two blocks and no pair is emitted: a block returns a spanning forest of its links. Two rounds
use the orders: the second compares only pairs that the first left in different components.

Deepening and blocks drawn from the crowds link most of a crowd in the first round at a cost that
grows with its size. The second round then compares every pair of a crowd that is still open, so what
leaves the deeper regions keeps its links; its cost follows the documents outside the crowd's largest component.

A link of similarity s agrees on 4 values of a given order with probability s^4, so 16 orders
miss one of 0.85 with probability 7e-6 and one of 0.80 with 2e-4, in crowds as elsewhere. A document of a crowd
is lost only if it misses all its links, which the number of links makes rarer still.

Tables that grow are joined by sorting on both sides with each side written before, so that the planner can
split a region that holds many rows; no region is collected.

Defined cases: a text without words, or null, has an empty set and links with nothing; a row
with null id keeps a null component and is kept. Rows that repeat an id are judged by their own texts; two
texts with the same smallest id are one class.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch, mix64, word_hashes

WORDS = 3
PERCENT = 85
ORDERS = 16
STEP = 4
SIGNATURE = ORDERS * STEP
DEPTHS = (4, 6, 9, 13, 18, 24, 32, 48)
REGION = 2048
BLOCK = 256
BLOCK_SHINGLES = 1 << 20
#: Documents and shingles that a task of the comparison takes at once, about.
TASK_ROWS, TASK_SHINGLES = 2000, 4 << 20
FIRST_ORDERS = 4

_rng = np.random.default_rng(77)
_A = (_rng.integers(0, 2**32, size=(SIGNATURE, 1), dtype=np.uint64) | np.uint64(1)).astype(np.uint32)
_B = _rng.integers(0, 2**32, size=(SIGNATURE, 1), dtype=np.uint64).astype(np.uint32)
_K = _rng.integers(0, 2**63, size=8, dtype=np.uint64) | np.uint64(1)


def shingle_sets(texts: list, words: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's shingles; a text of fewer words is one shingle."""
    h, offsets = word_hashes(texts)
    out = []
    n = len(h)
    if n >= words:
        s = np.zeros(n - words + 1, np.uint64)
        for k in range(words):
            s += mix64(h[k : n - words + 1 + k] + np.uint64(k)) * _K[k]
        s = mix64(s)
    for lo, hi in zip(offsets[:-1], offsets[1:], strict=True):
        m = hi - lo
        if m == 0:
            out.append(np.zeros(0, np.uint64))
        elif m < words:
            v = np.full(1, m, np.uint64)
            for k in range(lo, hi):
                v = mix64(v * _K[4] + h[k : k + 1])
            out.append(v)
        else:
            out.append(np.unique(s[lo : hi - words + 1]))
    return out


def signature(shingles: np.ndarray) -> np.ndarray:
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    out = np.full(SIGNATURE, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(x), 8192):
        v = x[None, at : at + 8192] * _A
        v ^= v >> np.uint32(15)
        v *= np.uint32(0x2C1B3C6D)
        v += _B
        v ^= v >> np.uint32(13)
        np.minimum(out, v.min(1), out=out)
    return out


def _digest(shingles: bytes) -> np.ndarray:
    return np.frombuffer(hashlib.blake2b(shingles, digest_size=16).digest(), np.int64)


def _sign(words: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for lo in range(0, len(pdf), 1000):
                part = pdf.iloc[lo : lo + 1000]
                rows = []
                for s in shingle_sets(part["text"].tolist(), words):
                    d = _digest(s.tobytes())
                    rows.append((len(s), int(d[0]), int(d[1]), signature(s).astype("<u4").tobytes() if len(s) else None))
                out = pd.DataFrame(rows, columns=["n_shingles", "d1", "d2", "sig"])
                out.insert(0, "doc_id", part["doc_id"].astype("Int64").to_numpy() if part["doc_id"].isna().any() else part["doc_id"].to_numpy())
                yield out

    return run


def _sets(words: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for lo in range(0, len(pdf), 1000):
                part = pdf.iloc[lo : lo + 1000]
                sets = [s.tobytes() for s in shingle_sets(part["text"].tolist(), words)]
                own = [int(_digest(b)[0]) for b in sets]
                yield pd.DataFrame({"doc": part["doc_id"].to_numpy(), "d1": own, "shingles": sets})

    return run


def _common(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairwise intersections, by products of 0/1 columns of the shingles that occur twice."""
    n = len(sets)
    both = np.concatenate(sets)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    _, inverse, counts = np.unique(both, return_inverse=True, return_counts=True)
    shared = counts > 1
    column = np.cumsum(shared) - 1
    use = shared[inverse]
    owner, col = owner[use], column[inverse[use]]
    order = np.argsort(col, kind="stable")
    owner, col = owner[order], col[order]
    out = np.zeros((n, n), np.float32)
    width = 8192
    for at in range(0, int(shared.sum()), width):
        a, b = np.searchsorted(col, [at, at + width])
        x = np.zeros((n, width), np.float32)
        x[owner[a:b], col[a:b] - at] = 1
        out += x @ x.T
    return out


def _forest(percent: int):
    """Links of each block pair as a forest: every document that joins others points to the smallest."""

    def block(docs: np.ndarray, comps: np.ndarray, sets: list[np.ndarray]) -> list[tuple[int, int]]:
        n = len(docs)
        sizes = np.array([len(s) for s in sets], np.int64)
        if n <= 6:
            hits = []
            for i in range(n):
                for j in range(i + 1, n):
                    if comps[i] != comps[j] and 100 * min(sizes[i], sizes[j]) >= percent * max(sizes[i], sizes[j]):
                        c = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                        if 100 * c >= percent * (sizes[i] + sizes[j] - c):
                            hits.append((i, j))
        else:
            c = _common(sets).astype(np.int64)
            linked = (100 * c >= percent * (sizes[:, None] + sizes[None, :] - c)) & (comps[:, None] != comps[None, :])
            hits = np.argwhere(np.triu(linked, 1)).tolist()
        parent = list(range(n))

        def root(x: int) -> int:
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for i, j in hits:
            a, b = root(i), root(j)
            if a != b:
                if docs[a] < docs[b]:
                    parent[b] = a
                else:
                    parent[a] = b
        return [(int(docs[root(k)]), int(docs[k])) for k in range(n) if docs[root(k)] != docs[k]]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple[int, int]] = []
        for _, g in pdf.groupby(["region", "lo", "hi"], sort=False):
            g = g.sort_values("doc")
            docs, comps = g["doc"].to_numpy(), g["comp"].to_numpy()
            if (comps == comps[0]).all():
                continue
            out += block(docs, comps, [np.frombuffer(b, np.uint64) for b in g["shingles"]])
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return run


def components(links: DataFrame, scratch: Scratch, rounds: int = 60) -> DataFrame:
    """node, comp (smallest node reachable) of every node on a link, by alternating star contractions.

    links: a, b (long). Each round is two aggregations and joins over what is left of the
    links, written to the shared folder; nothing reaches the driver but two sums.
    """
    edges = scratch.cut(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    seen = None
    for _ in range(rounds):
        both = edges.union(edges.select("v", "u")).toDF("u", "v")
        least = scratch.cut(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
        before, edges = edges, scratch.cut(small.select("e.*").where("u <> v").distinct())
        scratch.drop(before)
        now = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("comp"))


def _regions(classes: DataFrame, scratch: Scratch) -> DataFrame:
    """region, n, weight, ord, doc, d1, shingles (their number), crowd: documents that share a prefix, deepened where more
    than REGION do.

    crowd marks regions of the first depth that were deepened; they hold every pair of the deeper ones.

    Only hashes of prefixes travel; signatures are joined again for what is deepened. All sides
    of these joins grow with the input, so none is broadcast whatever its size today.
    """

    def prefix(order: Column, depth: int) -> Column:
        return F.xxhash64(order, F.lit(depth), F.substring(F.concat("sig", "sig"), order * F.lit(4 * STEP) + F.lit(1), F.lit(4 * depth)))

    own = ["doc", "d1", "shingles"]
    orders = F.sequence(F.lit(0), F.lit(ORDERS - 1))
    keyed = classes.select(*own, F.explode(F.transform(orders, lambda k: F.struct(k.alias("ord"), prefix(k, DEPTHS[0]).alias("region")))).alias("o")).select(*own, "o.ord", "o.region")
    found = None
    for k in range(len(DEPTHS)):
        sizes = scratch.cut(keyed.groupBy("region").agg(F.count(F.lit(1)).alias("n"), F.sum("shingles").alias("weight")).where("n > 1"))
        keyed = scratch.cut(keyed.join(sizes.hint("merge"), "region"))
        here = keyed if k == 0 else keyed.where(F.col("n") <= REGION)
        done = here.select("region", "n", "weight", "ord", *own, (F.col("n") > REGION).alias("crowd"))
        found = done if found is None else found.unionByName(done)
        over = keyed.where(F.col("n") > REGION)
        if k == len(DEPTHS) - 1 or over.isEmpty():
            return found
        keyed = over.select(*own, "ord").join(classes.select("doc", "d1", "sig").hint("merge"), ["doc", "d1"]).select(*own, "ord", prefix(F.col("ord"), DEPTHS[k + 1]).alias("region"))
    return found


def _blocks(n: Column, weight: Column) -> Column:
    """Blocks that so many documents with so many shingles are dealt into."""
    return F.greatest(F.ceil(n / F.lit(BLOCK)), F.ceil(weight / F.lit(BLOCK_SHINGLES))).cast("int")


def _linked(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """a, b: spanning links of every region. members: region, doc, d1, shingles, comp, minor, few, rest, sample.

    minor marks documents outside their region's largest component; only pairs with one of these are
    open. The few blocks of minor documents meet each other and every block of the rest. In a region marked
    sample, a block meets only itself.
    """
    spark = members.sparkSession
    few, rest = F.col("few"), F.greatest("rest", F.lit(1))
    h = F.xxhash64("doc", "d1", "region")
    own = F.when(F.col("minor"), F.pmod(h, few)).otherwise(few + F.pmod(h, rest)).cast("int")
    rows = members.withColumns({"own": own, "blocks": F.col("few") + F.col("rest")})
    meets = F.when(F.col("minor"), F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.sequence(F.lit(0), F.col("few") - 1))
    others = F.when(F.col("sample") | (F.col("blocks") == 1), F.array("own")).otherwise(F.filter(meets, lambda j: j != F.col("own")))
    dealt = rows.select("region", "doc", "d1", "shingles", "comp", "own", F.explode(others).alias("j"))
    dealt = dealt.select("region", F.least("own", "j").alias("lo"), F.greatest("own", "j").alias("hi"), "doc", "d1", "shingles", "comp")
    size = dealt.agg(F.count(F.lit(1)), F.coalesce(F.sum("shingles"), F.lit(0))).first()
    parts = max(1, spark.sparkContext.defaultParallelism * 4, size[0] // TASK_ROWS, size[1] // TASK_SHINGLES)
    dealt = dealt.drop("shingles").withColumn("bucket", F.pmod(F.xxhash64("region", "lo", "hi"), F.lit(parts)))
    return dealt.join(sets.hint("merge"), ["doc", "d1"]).groupBy("bucket").applyInPandas(_forest(percent), "a long, b long")


def near_duplicates(docs: DataFrame, percent: int = PERCENT, words: int = WORDS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row."""
    spark = docs.sparkSession
    scratch = Scratch(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    signed = scratch.cut(rows.mapInPandas(_sign(words), "doc_id long, n_shingles long, d1 long, d2 long, sig binary"))
    whole = signed.where("n_shingles > 0 and doc_id is not null").groupBy("d1", "d2")
    classes = scratch.cut(whole.agg(F.min("doc_id").alias("doc"), F.first("n_shingles").alias("shingles"), F.first("sig").alias("sig")))
    regions = _regions(classes, scratch)
    # regions with the same documents in several orders are compared once, in the first of them
    prints = regions.groupBy("region").agg(F.first("ord").alias("ord"), F.first("n").alias("n"), F.bit_xor(F.xxhash64("doc", "d1", F.lit(1))).alias("x1"), F.bit_xor(F.xxhash64("doc", "d1", F.lit(2))).alias("x2"))
    first = scratch.cut(prints.groupBy("n", "x1", "x2").agg(F.min(F.struct("ord", "region")).alias("r")).select("r.region"))
    members = scratch.cut(regions.join(first.hint("merge"), "region", "left_semi"))
    ids = members.select(F.col("doc").alias("doc_id")).distinct()
    sets = scratch.cut(rows.join(ids.hint("merge"), "doc_id", "left_semi").mapInPandas(_sets(words), "doc long, d1 long, shingles binary").dropDuplicates(["doc", "d1"]))
    early = members.where((F.col("ord") < FIRST_ORDERS) | F.col("crowd"))
    early = early.withColumns({"comp": F.col("doc"), "minor": F.lit(True), "few": _blocks(F.col("n"), F.col("weight")), "rest": F.lit(0), "sample": F.col("crowd")})
    links = scratch.cut(_linked(early, sets, percent))
    comps = components(links, scratch)
    late = members.where((F.col("ord") >= FIRST_ORDERS) | F.col("crowd")).join(comps.withColumnRenamed("node", "doc").hint("merge"), "doc", "left").withColumn("comp", F.coalesce("comp", "doc"))
    late = scratch.cut(late)
    sizes = late.groupBy("region", "comp").agg(F.count(F.lit(1)).alias("c"), F.sum("shingles").alias("w"))
    most = F.max(F.struct("c", "comp", "w")).alias("most")
    split = scratch.cut(sizes.groupBy("region").agg(most, F.count(F.lit(1)).alias("k")).where("k > 1").select("region", "most"))
    late = late.join(split.hint("merge"), "region").withColumns({
        "minor": F.col("comp") != F.col("most.comp"), "sample": F.lit(False),
        "few": _blocks(F.col("n") - F.col("most.c"), F.col("weight") - F.col("most.w")), "rest": _blocks(F.col("most.c"), F.col("most.w")),
    })
    more = scratch.cut(_linked(scratch.cut(late.drop("most")), sets, percent))
    comps = components(links.union(more), scratch)
    named = classes.select("d1", "d2", "doc").join(comps.withColumnRenamed("node", "doc"), "doc", "left").select("d1", "d2", F.coalesce("comp", "doc").alias("component_id"))
    out = signed.drop("sig").join(scratch.cut(named).hint("merge"), ["d1", "d2"], "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component_id", "doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), component).alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def one_of_each(docs: DataFrame, percent: int = PERCENT, words: int = WORDS) -> DataFrame:
    """The rows of docs that stay when one document of each class does, with their columns as they were.
    An id stands for one document: of rows that repeat one, the row with the smallest hash of its text stays (of equal
    texts, any one, since only a row's other columns could differ: the one with the smallest hash of all columns). Rows without an id stay."""
    scratch = Scratch(docs.sparkSession)
    found = scratch.cut(near_duplicates(docs, percent, words))
    stay = found.where("kept and doc_id is not null").groupBy("doc_id").agg(F.lit(True).alias("_one"))
    again = found.where("doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select("doc_id")
    kept = docs.join(scratch.cut(stay).hint("merge"), "doc_id", "left_semi")
    again = scratch.cut(again)
    once = kept.join(again.hint("merge"), "doc_id", "left_anti")
    columns = [F.col(f"`{c}`") for c in docs.columns]
    order = W.partitionBy("doc_id").orderBy(F.xxhash64(F.col("text").cast("string")), F.xxhash64(*columns))
    repeated = kept.join(again.hint("merge"), "doc_id", "left_semi").withColumn("__place", F.row_number().over(order)).where("__place = 1")
    return once.select(*columns).unionByName(repeated.select(*columns)).unionByName(docs.where("doc_id is null"))
