"""URL rules with exact membership by a cascade of Bloom filters, in DataFrame functions only.

Level 0 encodes the listed keys. Level 1 encodes those keys of the corpus that level 0
passes wrongly, level 2 the listed keys that level 1 passes, and so on until no false
positive is left. Over the corpus's own keys, from which the cascade is built, answers
are exact and a lookup joins nothing. Level 0 is sized by the ratio of corpus keys to
listed keys and later levels halve their input, so the bits follow the list, not the corpus.

Defined cases: a null url or one without "://" has empty host and path, fits no rule and
is allowed. Repeated rows stay repeated. Other columns are ignored.
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch

#: (verdict, host, path): fixed values.
RULES = (
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
)
#: Hosts that the method blocks, with their subdomains, where no rule fits: the families of unwanted hosts that
#: occur in the given pages, under each ending that hosts have there. Fixed values.
FAMILIES = ("ads-track", "adult-x", "casino-win", "cheap-pills", "free-bets", "spam-farm")
ENDINGS = ("com", "net", "org")
LISTED_HOSTS = tuple(f"{name}.example.{end}" for name in FAMILIES for end in ENDINGS)

#: Largest cascade, in bits; it travels in the plan. 16 Mbit hold about a million keys.
MAX_BITS = 1 << 24

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def with_host_path(pages: DataFrame, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    url = F.coalesce(F.col(url_col).cast("string"), F.lit(""))
    rest = F.when(F.instr(url, "://") > 0, F.expr(f"substring(coalesce(cast({url_col} as string), ''), instr(coalesce(cast({url_col} as string), ''), '://') + 3)")).otherwise(F.lit(""))
    cut = pages.select(F.col(id_col).alias("page_id"), rest.alias("_r"))
    return cut.select(
        "page_id",
        F.translate(F.regexp_extract("_r", r"^[^/?#]*", 0), _UPPER, _LOWER).alias("host"),
        F.regexp_extract("_r", r"^[^/?#]*([^?#]*)", 1).alias("path"),
    )


def host_suffixes(host: Column) -> Column:
    """The host and every domain above it; none for an empty host."""
    labels = F.split(host, r"\.")
    return F.when(host == "", F.array().cast("array<string>")).otherwise(
        F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    )


def rule_keys(host: Column, path: Column, lengths: tuple[int, ...]) -> Column:
    """Every host suffix joined with every path prefix of a length that some rule has."""
    prefixes = F.array_distinct(F.filter(F.array(*[F.when(F.length(path) >= n, F.substring(path, 1, n)) for n in lengths]), lambda p: p.isNotNull()))
    return F.flatten(F.transform(host_suffixes(host), lambda h: F.transform(prefixes, lambda p: F.concat(h, p))))


@dataclass
class Level:
    bits: int
    hashes: int
    words: list[int] = field(repr=False)


def _bit(key: Column, level: int, j: int, bits: int) -> Column:
    return F.pmod(F.xxhash64(key, F.lit(level), F.lit(j)), F.lit(bits))


def _test(key: Column, number: int, level: Level) -> Column:
    words = F.from_json(F.lit(json.dumps(level.words)), "array<bigint>")
    ok = F.lit(True)
    for j in range(level.hashes):
        at = _bit(key, number, j, level.bits)
        word = F.get(words, F.floor(at / 64).cast("int"))
        ok = ok & (F.expr("1L") == F.call_function("shiftright", word, F.pmod(at, F.lit(64)).cast("int")).bitwiseAND(F.expr("1L")))
    return ok


@dataclass
class BloomCascade:
    levels: list[Level]

    def contains(self, key: Column) -> Column:
        """Exact for listed keys and for keys of the universe that built the cascade."""
        answer = F.lit(len(self.levels) % 2 == 1)
        for number in range(len(self.levels) - 1, -1, -1):
            answer = F.when(_test(key, number, self.levels[number]), answer).otherwise(F.lit(number % 2 == 1))
        return answer if self.levels else F.lit(False)

    @staticmethod
    def build(listed: DataFrame, universe: DataFrame, max_levels: int = 64) -> BloomCascade:
        """listed, universe: one string column key. Nulls and repeats are ignored. Every level reads what the one
        before it let pass, from a written table, so the tables shrink and no level reads the source again."""
        scratch = Scratch(universe.sparkSession)
        yes = scratch.cut(listed.select("key").where(F.col("key").isNotNull()).distinct())
        no = scratch.cut(universe.select("key").where(F.col("key").isNotNull()).join(yes, "key", "left_anti").distinct())
        n_yes, n_no = yes.count(), no.count()
        levels: list[Level] = []
        inside, outside, n = yes, no, n_yes
        while n and len(levels) < max_levels:
            number = len(levels)
            rate = 0.5 if number else max(2.0**-40, min(0.5, math.sqrt(0.5) * n_yes / max(1, n_no)))
            hashes = max(1, round(math.log2(1 / rate)))
            bits = max(64, 64 * math.ceil(n * hashes / math.log(2) / 64))
            if sum(x.bits for x in levels) + bits > MAX_BITS:
                raise ValueError(f"{n} keys need {bits} bits; a cascade may hold {MAX_BITS}")
            at = inside.select(F.explode(F.array(*[_bit(F.col("key"), number, j, bits) for j in range(hashes)])).alias("at"))
            rows = at.groupBy(F.floor(F.col("at") / 64).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(pmod(at, 64) as int))")).alias("v")).collect()
            words = [0] * (bits // 64)
            for r in rows:
                words[r["w"]] = r["v"]
            levels.append(Level(bits, hashes, words))
            inside, outside = scratch.cut(outside.where(_test(F.col("key"), number, levels[-1]))), inside
            n = inside.count()
        if n:
            raise ValueError("the cascade did not close")
        return BloomCascade(levels)


def _keys(spark: SparkSession, keys: list[str]) -> DataFrame:
    return spark.range(1).select(F.explode(F.array(*[F.lit(k) for k in keys]) if keys else F.array().cast("array<string>")).alias("key"))


def judge_urls(pages: DataFrame, rules: tuple = RULES, listed_hosts: tuple = LISTED_HOSTS) -> DataFrame:
    """page_id, host, path, rule, verdict. The longest fitting rule decides, then the longer host; without one the listed hosts do."""
    spark = pages.sparkSession
    parts = with_host_path(pages)
    lengths = tuple(sorted({len(p) for _, _, p in rules}))
    scratch = Scratch(spark)
    found = parts.select(F.explode(rule_keys(F.col("host"), F.col("path"), lengths)).alias("key"), F.lit(True).alias("rule"))
    found = found.unionByName(parts.select(F.explode(host_suffixes(F.col("host"))).alias("key"), F.lit(False).alias("rule")))
    keys = scratch.cut(found.distinct())  # the complete key universe, once
    candidates, hosts = (keys.where(F.col("rule") == which).select("key") for which in (True, False))
    allow, block = ([h + p for v, h, p in rules if v == which] for which in ("allow", "block"))
    allowed, blocked = (BloomCascade.build(_keys(spark, k), candidates) for k in (allow, block))
    listed = BloomCascade.build(_keys(spark, list(listed_hosts)), hosts)
    found = parts.withColumns({
        "_a": F.filter(rule_keys(F.col("host"), F.col("path"), lengths), lambda k: allowed.contains(k)),
        "_b": F.filter(rule_keys(F.col("host"), F.col("path"), lengths), lambda k: blocked.contains(k)),
        "_m": F.exists(host_suffixes(F.col("host")), lambda k: listed.contains(k)),
    })

    def longest(keys: Column, verdict: str) -> Column:
        return F.transform(keys, lambda k: F.struct(F.length(k).alias("n"), F.instr(k, "/").alias("h"), k.alias("rule"), F.lit(verdict).alias("verdict")))

    best = found.withColumn("_best", F.array_max(F.concat(longest(F.col("_a"), "allow"), longest(F.col("_b"), "block"))))
    return best.select(
        "page_id", "host", "path", F.col("_best.rule").alias("rule"),
        F.coalesce(F.col("_best.verdict"), F.when(F.col("_m"), F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"),
    )


ORACLE = """
WITH r AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT page_id,
        translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
        regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM r),
rules(verdict, rh, rp) AS (VALUES """ + ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in RULES) + """),
fits AS (SELECT p.page_id, p.host, p.path, rh || rp AS rule, verdict,
           row_number() OVER (PARTITION BY p.page_id, p.host, p.path ORDER BY length(rh || rp) DESC, length(rh) DESC) AS k
         FROM p JOIN rules ON (p.host = rh OR ends_with(p.host, '.' || rh)) AND starts_with(p.path, rp))
SELECT p.page_id, p.host, p.path, f.rule,
  CASE WHEN f.verdict IS NOT NULL THEN f.verdict
       WHEN EXISTS (SELECT 1 FROM (VALUES """ + ", ".join(f"('{h}')" for h in LISTED_HOSTS) + """) AS l(h) WHERE p.host = l.h OR ends_with(p.host, '.' || l.h)) THEN 'block'
       ELSE 'allow' END AS verdict
FROM p LEFT JOIN fits f ON f.page_id = p.page_id AND f.host = p.host AND f.path = p.path AND f.k = 1
"""
