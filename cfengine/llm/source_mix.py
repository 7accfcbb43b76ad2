"""Mixing sources to target weights along a curriculum.

Each source has a weight schedule over training time 0..1. Its integral gives the tokens
the source has to supply by any moment; a document's position is the moment at which the
integral reaches the tokens supplied before it (and half of its own). Documents are range-sorted by position.

A source passes over its documents in hash order, whole passes first; the last, partial
pass takes documents while they fit and then goes on over those that fit what is left, until
none does; one more is then added if that brings the total nearer. Documents are taken whole, at most max_repeats times.

Defined cases: a null or blank text has size 0 and takes nothing; a null source is a source
of its own, last in order. Repeated rows are separate documents. No row gives no row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import GAP, Scratch, ranked

WEIGHTS = (1.0, 2.0, 3.0)
MAX_REPEATS = 3
#: Weight schedules by rank of source, repeating: (time, factor) knots, linear between; fixed values.
SCHEDULES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (0.5, 1.0), (1.0, 1.5)))
#: Sources that the driver plans; their totals are one row each.
MAX_SOURCES = 1_000_000


def text_size(text: Column) -> Column:
    return F.size(F.filter(F.split(F.coalesce(text.cast("string"), F.lit("")), GAP), lambda w: w != "")).cast("long")


def targets(sizes: list[int], weights: list[float], total: float, most: float = MAX_REPEATS) -> list[float]:
    """Shares total by weight; a source stops at most times its size and the rest is shared again."""
    out = [0.0] * len(sizes)
    open_ = {k for k, s in enumerate(sizes) if s > 0}
    left = float(total)
    while open_:
        weight = sum(weights[k] for k in open_)
        full = {k for k in open_ if left * weights[k] / weight >= most * sizes[k]}
        if not full:
            for k in open_:
                out[k] = left * weights[k] / weight
            break
        for k in full:
            out[k] = float(most * sizes[k])
        left -= sum(out[k] for k in full)
        open_ -= full
        if left <= 0:
            break
    return out


@dataclass(frozen=True)
class Segment:
    """A stretch of a schedule: shares u of the source's demand from lo, at time t0, with rates r0 to r1."""

    lo: float
    t0: float
    t1: float
    r0: float
    r1: float


def segments(knots: tuple[tuple[float, float], ...]) -> list[Segment]:
    area = sum((t1 - t0) * (w0 + w1) / 2 for (t0, w0), (t1, w1) in zip(knots, knots[1:], strict=False))
    out, lo = [], 0.0
    for (t0, w0), (t1, w1) in zip(knots, knots[1:], strict=False):
        out.append(Segment(lo, t0, t1, w0 / area, w1 / area))
        lo += (t1 - t0) * (w0 + w1) / 2 / area
    return out


def position(share: Column, segs: Column) -> Column:
    """The time at which the demand integral reaches a share: the inverse of a piecewise quadratic."""
    seg = F.element_at(F.filter(segs, lambda s: s["lo"] <= F.greatest(share, F.lit(0.0))), -1)
    u = F.greatest(share - seg["lo"], F.lit(0.0))
    slope = (seg["r1"] - seg["r0"]) / (seg["t1"] - seg["t0"])
    root = F.sqrt(F.greatest(seg["r0"] * seg["r0"] + 2 * slope * u, F.lit(0.0)))
    return F.least(seg["t0"] + F.coalesce(F.try_divide(2 * u, seg["r0"] + root), F.lit(0.0)), seg["t1"])


def _filled(base: DataFrame, max_repeats: int, scratch: Scratch) -> DataFrame:
    """source, place: documents that fit what the prefix left of a source's target, in hash order, until none fits.

    A round passes over those of at most half of what is left, then takes the largest that still fits.
    Either the pass ends on one that does not fit, or only larger ones remain and two of
    these would not fit; so what is left halves and the rounds are few whatever the sizes.
    """
    same = lambda a, b: F.col(f"{a}.source").eqNullSafe(F.col(f"{b}.source"))
    left = base.groupBy("source").agg((F.first("_rest") - F.sum(F.when(F.col("_more"), F.col("size")).otherwise(0))).alias("left"))
    rows = base.where((F.col("size") > 0) & (F.col("_full") < max_repeats) & ~F.col("_more")).select("source", F.col("place").alias("row"), "size", "_h")
    open_ = scratch.cut(rows.alias("d").join(left.alias("o"), same("d", "o")).select("d.*", "o.left").where("size <= left"))
    found = base.select("source", "place").limit(0)
    while not open_.isEmpty():
        small = ranked(open_.where("size <= left / 2"), ["source"], F.col("row"), F.col("size"), scratch)
        small = scratch.cut(small.where("before + size <= left").select("source", "row", "size"))
        used = small.groupBy("source").agg(F.sum("size").alias("used"))
        rest = open_.alias("d").join(small.alias("s"), same("d", "s") & (F.col("d.row") == F.col("s.row")), "left_anti")
        rest = rest.alias("d").join(used.alias("u"), same("d", "u"), "left").select("d.source", "d.row", "d.size", "d._h", (F.col("d.left") - F.coalesce("u.used", F.lit(0))).alias("left"))
        rest = scratch.cut(rest.where("size <= left"))
        one = scratch.cut(rest.groupBy("source").agg(F.max(F.struct("size", "row")).alias("m")).select("source", "m.row", "m.size"))
        found = found.union(small.select("source", "row")).union(one.select("source", "row"))
        next_ = rest.alias("d").join(one.alias("o"), same("d", "o") & (F.col("d.row") != F.col("o.row")))
        open_ = scratch.cut(next_.select("d.source", "d.row", "d.size", "d._h", (F.col("d.left") - F.col("o.size")).alias("left")).where("size <= left"))
    return found


def plan_mix(docs: DataFrame, weights: tuple = WEIGHTS, schedules: tuple = SCHEDULES, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies, positions (one a copy), source; one row a document."""
    spark = docs.sparkSession
    scratch = Scratch(spark)
    rows = docs.select("doc_id", F.col("source").cast("string").alias("source"), text_size(F.col("text")).alias("size"))
    sized = scratch.cut(rows.withColumn("_h", F.xxhash64(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))))
    found = sized.groupBy("source").agg(F.sum("size").alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(found) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    found.sort(key=lambda r: (r["source"] is None, r["source"] or ""))
    sizes = [int(r["n"] or 0) for r in found]
    goal = targets(sizes, [weights[k % len(weights)] for k in range(len(found))], sum(sizes), max_repeats)
    plan = [(r["source"], goal[k], [(s.lo, s.t0, s.t1, s.r0, s.r1) for s in segments(schedules[k % len(schedules)])]) for k, r in enumerate(found)]
    plan_df = spark.createDataFrame(plan, "source string, target double, segs array<struct<lo: double, t0: double, t1: double, r0: double, r1: double>>")

    placed = ranked(sized, ["source"], F.struct("doc_id", "size"), F.col("size"), scratch)
    base = placed.alias("d").join(plan_df.alias("s"), F.col("d.source").eqNullSafe(F.col("s.source"))).select("d.*", "s.target", "s.segs")
    passes = F.floor(F.coalesce(F.try_divide(F.col("target"), F.col("group_size")), F.lit(0.0)) + F.lit(1e-9))
    base = base.withColumn("_full", F.least(passes, F.lit(max_repeats)).cast("long"))
    base = base.withColumn("_rest", F.col("target") - F.col("_full") * F.col("group_size"))
    more = (F.col("_full") < max_repeats) & (F.col("size") > 0) & (F.col("before") + F.col("size") <= F.col("_rest"))
    base = scratch.cut(base.withColumn("_more", more))
    extra = _filled(base, max_repeats, scratch)
    base = base.alias("d").join(extra.withColumn("_extra", F.lit(True)).alias("e"), F.col("d.source").eqNullSafe(F.col("e.source")) & (F.col("d.place") == F.col("e.place")), "left")
    base = scratch.cut(base.select("d.*", "e._extra").withColumn("_more", F.col("_more") | F.coalesce("_extra", F.lit(False))).drop("_extra"))
    # what is still missing, a source, and the document whose size comes nearest to it
    off = base.groupBy("source").agg((F.first("_rest") - F.sum(F.when(F.col("_more"), F.col("size")).otherwise(0))).alias("_off"))
    with_off = base.alias("d").join(off.alias("o"), F.col("d.source").eqNullSafe(F.col("o.source"))).select("d.*", "o._off")
    fits = (F.col("size") > 0) & (F.col("_full") < max_repeats) & (F.col("_more") == (F.col("_off") < 0)) & (F.abs(F.abs("_off") - F.col("size")) < F.abs("_off"))
    fix = with_off.where(fits).groupBy("source").agg(F.min(F.struct(F.abs(F.abs("_off") - F.col("size")).alias("gap"), "_h", "doc_id", "place")).alias("_fix"))
    fixed = base.alias("d").join(fix.alias("f"), F.col("d.source").eqNullSafe(F.col("f.source")), "left").select("d.*", F.col("f._fix.place").alias("_swap"))
    turned = F.coalesce(F.col("place") == F.col("_swap"), F.lit(False))
    fixed = fixed.withColumn("copies", F.col("_full") + (F.col("_more") != turned).cast("long"))
    share = lambda k: F.try_divide(k * F.col("group_size") + F.col("before") + F.col("size") / 2, F.col("target"))
    every = F.transform(F.sequence(F.lit(0), F.lit(max_repeats - 1)), lambda k: F.coalesce(position(F.least(share(k), F.lit(1.0)), F.col("segs")), F.lit(0.0)))
    return fixed.select(
        "doc_id", "size", F.col("group_size").alias("source_size"), "target",
        (F.col("copies") * F.col("size")).alias("taken"), "copies", F.slice(every, 1, F.col("copies").cast("int")).alias("positions"), "source",
    )


def training_order(docs: DataFrame, mix: DataFrame) -> DataFrame:
    """The documents' rows in training order, one a copy, range-sorted by position; position is added.
    mix: what plan_mix gave for docs. Rows that share an id, or have none, all follow the one of them that was
    planned first (the least list of positions)."""
    copies = mix.where("copies > 0").groupBy("doc_id").agg(F.min("positions").alias("positions")).select("doc_id", F.explode("positions").alias("position"))
    joined = docs.alias("d").join(copies.alias("m"), F.col("d.doc_id").eqNullSafe(F.col("m.doc_id"))).select("d.*", "m.position")
    return joined.repartitionByRange("position").sortWithinPartitions("position")


def source_mix(docs: DataFrame) -> DataFrame:
    """The mix of all documents, range-sorted by first position (documents that are not taken come last)."""
    mix = plan_mix(docs)
    first = F.coalesce(F.get("positions", F.lit(0)), F.lit(2.0))
    return mix.withColumn("_p", first).repartitionByRange(F.col("_p"), F.col("doc_id")).sortWithinPartitions("_p", "doc_id").drop("_p")
