"""What the training-data operators share: table access, folds, cut points, word kernels.

Words are maximal runs of bytes other than 0x20 and 0x09-0x0D. All of these
are ASCII, so splitting UTF-8 bytes gives the same words as splitting text.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(doc_id: Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(n))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a local one will do only for a
    local master: elsewhere each executor would write to its own disk."""
    sc = spark.sparkContext
    at = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
        at = tempfile.mkdtemp(prefix="cfengine-")
        sc.setCheckpointDir(at)
        at = sc.getCheckpointDir()
    return at


class Scratch:
    """Tables written to the shared folder, so that lost executors cost no more than one stage."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.base = f"{shared_dir(spark).rstrip('/')}/cut-{uuid.uuid4().hex}"
        self.n = 0

    def cut(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.base}/{self.n}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path).alias(f"cut{self.n}")
        out._cut_path = path
        return out

    def drop(self, df: DataFrame) -> None:
        """Delete the table behind a frame that cut() gave, once nothing reads it."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(df._cut_path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def fewer(df: DataFrame, per_core: int = 4) -> DataFrame:
    """At most per_core tasks a core, so that per-task summaries stay few; no shuffle."""
    return df.coalesce(max(1, df.sparkSession.sparkContext.defaultParallelism * per_core))


def about(df: DataFrame, key: str, n: int) -> DataFrame:
    """About n rows, those with the smallest hashes of a key; a filter, so no task sends more than its share."""
    rows = df.count()
    if rows <= n:
        return df
    return df.where(F.pmod(F.xxhash64(key, F.lit(404)), F.lit(1 << 31)) < F.lit(int((1 << 31) * n / rows)))


def text_or_empty(t) -> str:
    return t if isinstance(t, str) else ""


# --- word kernels -----------------------------------------------------------

_GAPS = np.zeros(256, dtype=bool)
_GAPS[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_PLACES = 64
_TABLE = np.random.default_rng(20240229).integers(0, 2**64, size=_PLACES * 256, dtype=np.uint64)
_M1, _M2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(33))
    x = x * _M1
    x ^= x >> np.uint64(33)
    x *= _M2
    x ^= x >> np.uint64(33)
    return x


def hash_words(buf: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, start, end) of each word of a byte array."""
    if lower:
        buf = _LOWER[buf]
    gap = _GAPS[buf]
    edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
    if len(buf) and not gap[0]:
        edge = np.concatenate(([0], edge))
    if len(buf) and not gap[-1]:
        edge = np.concatenate((edge, [len(buf)]))
    starts, ends = edge[0::2], edge[1::2]
    if not len(starts):
        return np.zeros(0, np.uint64), starts, ends
    lens = ends - starts
    firsts = np.concatenate(([0], np.cumsum(lens)[:-1]))
    place = np.arange(int(lens.sum()), dtype=np.int64) - np.repeat(firsts, lens)
    chars = buf[~gap].astype(np.int64)
    if int(lens.max()) <= _PLACES:
        part = _TABLE[place * 256 + chars]
    else:
        # the first _PLACES characters count as in the branch above: a word's hash is its own, whatever its batch holds
        turn = np.where(place < _PLACES, np.uint64(1), mix64((place // _PLACES).astype(np.uint64) * np.uint64(2) + np.uint64(1)))
        part = _TABLE[(place % _PLACES) * 256 + chars] * turn
    return mix64(np.add.reduceat(part, firsts) + lens.astype(np.uint64)), starts, ends


def _parts(data: bytes, limit: int) -> Iterator[bytes]:
    """A long text in pieces that end at a gap; a word is never cut."""
    at = 0
    while len(data) - at > limit:
        end = at + limit
        while end < len(data) and not _GAPS[data[end]]:
            end += 1
        yield data[at:end]
        at = end
    yield data[at:]


def word_hashes(texts: Iterable, lower: bool = True, limit: int = 2_000_000) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of all words of all texts in order, offset of each text and the end); null counts as empty."""
    out, counts, n = [], [], 0
    group: list[bytes] = []
    owners: list[int] = []
    size = 0

    def flush():
        nonlocal size
        if not group:
            return
        joined = b"\n".join(group)
        h, starts, _ = hash_words(np.frombuffer(joined, dtype=np.uint8), lower)
        ends = np.cumsum([len(x) + 1 for x in group])
        per = np.diff(np.concatenate(([0], np.searchsorted(starts, ends))))
        out.append(h)
        for k, c in zip(owners, per, strict=True):
            counts[k] += int(c)
        group.clear()
        owners.clear()
        size = 0

    for t in texts:
        counts.append(0)
        for part in _parts(text_or_empty(t).encode("utf-8", "surrogatepass"), limit):
            group.append(part)
            owners.append(n)
            size += len(part) + 1
            if size >= limit:
                flush()
        n += 1
    flush()
    return (np.concatenate(out) if out else np.zeros(0, np.uint64)), np.concatenate(([0], np.cumsum(counts))).astype(np.int64)


def ranked(df: DataFrame, keys: list[str], order: Column, size: Column, scratch: Scratch, share: int = 4096) -> DataFrame:
    """Adds before (sum of size over earlier rows of the group), place (their number) and
    group_size, group_rows, in the order of a hash. Groups of any size: each is dealt into about
    rows/share ranges of the hash, ranges are summed first, and only ranges are ordered as a whole.

    df needs a hash column _h (any long); order breaks its ties.
    """
    totals = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("group_rows"), F.sum(size).alias("group_size"))
    totals = scratch.cut(totals.withColumn("_ranges", F.ceil(F.col("group_rows") / F.lit(share)).cast("long")))
    same = [F.col(f"d.{k}").eqNullSafe(F.col(f"g.{k}")) for k in keys]
    cond = same[0]
    for c in same[1:]:
        cond = cond & c
    top = F.shiftrightunsigned(F.col("_h"), 33)  # 31 bits
    rows = df.alias("d").join(totals.alias("g"), cond).select("d.*", "g.group_rows", "g.group_size", F.floor(top * F.col("g._ranges") / F.lit(2**31)).cast("long").alias("_range"))
    from pyspark.sql import Window as W

    sums = rows.groupBy(*keys, "_range").agg(F.sum(size).alias("_s"), F.count(F.lit(1)).alias("_n"))
    so_far = W.partitionBy(*keys).orderBy("_range").rowsBetween(W.unboundedPreceding, -1)
    bases = sums.select(*keys, "_range", F.coalesce(F.sum("_s").over(so_far), F.lit(0)).alias("_s0"), F.coalesce(F.sum("_n").over(so_far), F.lit(0)).alias("_n0"))
    inside = W.partitionBy(*keys, "_range").orderBy("_h", order).rowsBetween(W.unboundedPreceding, -1)
    placed = rows.withColumns({"_s1": F.coalesce(F.sum(size).over(inside), F.lit(0)), "_n1": F.count(F.lit(1)).over(inside)})
    cond = F.col("p._range") == F.col("b._range")
    for k in keys:
        cond = cond & F.col(f"p.{k}").eqNullSafe(F.col(f"b.{k}"))
    return placed.alias("p").join(bases.alias("b"), cond).select("p.*", (F.col("_s0") + F.col("_s1")).alias("before"), (F.col("_n0") + F.col("_n1")).alias("place")).drop("_s1", "_n1", "_range")
