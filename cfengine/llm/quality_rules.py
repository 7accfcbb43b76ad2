"""Quality rules as a bitmask ledger, in DataFrame functions only.

Each rule is evaluated once per document. The ledger keeps the measurements and one
bit per failed rule; policies are versioned masks over those bits, so a new policy or
an ablation reads the ledger and never the text.

Defined cases: a null or blank text has no words, so every count is 0 and too_few_words
fails. Repeated rows stay repeated rows. Other columns of the input are ignored.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import GAP

WINDOW = 8

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")

#: Rules by bit: name and the condition under which it fails, in whole numbers.
RULES: tuple[tuple[str, str], ...] = (
    ("too_few_words", "n_words < 20"),
    ("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    ("symbols_over_words", "n_symbols > n_words"),
    ("duplicate_lines", "2 * n_dup_lines > n_lines and n_lines > 3"),
    ("words_too_long", "word_chars > 20 * n_words"),
    ("words_too_short", "word_chars < 2 * n_words"),
)

BIT = {name: 1 << k for k, (name, _) in enumerate(RULES)}


@dataclass(frozen=True)
class Policy:
    """A named set of rules of which any failure rejects."""

    version: str
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        return sum(BIT[r] for r in self.rules)


BASE = Policy("base", ("too_few_words", "repeated_windows"))
POLICIES = {p.version: p for p in (BASE, Policy("v1", (*BASE.rules, "symbols_over_words")), Policy("v2", tuple(BIT)))}


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Binds a value once; the optimizer would otherwise copy its expression to every use."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _repeats(hashes: Column) -> Column:
    """From one hash per word: how many words lie in a window of eight that occurs twice or more.

    Windows are hashed by doubling (2, 4, 8 words), so a word costs three combinations.
    Only texts with a repeated window pay for the sort that places them.
    """

    def double(h: Column, by: int) -> Column:
        rest = F.slice(h, by + 1, F.greatest(F.size(h) - by, F.lit(0)))
        return F.zip_with(F.slice(h, 1, F.greatest(F.size(h) - by, F.lit(0))), rest, lambda a, b: F.xxhash64(a, b))

    def placed(w: Column) -> Column:
        by_hash = F.array_sort(F.zip_with(w, F.sequence(F.lit(0), F.size(w) - 1), lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return _let(by_hash, lambda s: _let(F.array_sort(F.transform(F.filter(
            F.transform(s, lambda x, k: F.struct(x["i"].alias("i"), (
                ((k > 0) & (F.get(s, k - 1)["h"] == x["h"])) | F.coalesce(F.get(s, k + 1)["h"] == x["h"], F.lit(False))).alias("twice"))),
            lambda x: x["twice"]), lambda x: x["i"])), covered))

    def covered(at: Column) -> Column:
        return F.aggregate(F.transform(at, lambda p, k: F.least(F.lit(WINDOW), F.coalesce(F.get(at, k + 1) - p, F.lit(WINDOW)))), F.lit(0), lambda a, x: a + x)

    windows = double(double(double(hashes, 1), 2), 4)
    return _let(windows, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0)).otherwise(placed(w)))


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", carry: bool = False) -> DataFrame:
    """id, the measurements (long) and failed (long, one bit per rule): the ledger. One pass, no shuffle.
    carry: also the input's row as the struct _row, so that a filter needs no join."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    row = ["_row"] if carry else []
    words = F.filter(F.split(F.col("_t"), GAP), lambda w: w != "")
    lines = F.filter(F.split(F.col("_t"), "\n"), lambda x: F.length(F.regexp_replace(x, GAP, "")) > 0)
    base = docs.select(F.col(id_col).alias("doc_id"), text.alias("_t"), *([F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")] if carry else []))
    parts = base.select(
        *row, "doc_id",
        F.transform(words, lambda w: F.xxhash64(w)).alias("_h"),
        F.length(F.regexp_replace("_t", GAP, "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace("_t", r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        _let(F.transform(lines, lambda x: F.xxhash64(x)), lambda h: F.struct(F.size(h).alias("n"), F.size(F.array_distinct(h)).alias("d"))).alias("_l"),
    )
    # one generated row keeps the word hashes from being computed at both of their uses
    parts = parts.select(F.inline(F.array(F.struct(*row, "doc_id", "_h", "word_chars", "n_symbols", "_l"))))
    counted = parts.select(
        *row, "doc_id", F.size("_h").cast("long").alias("n_words"), "word_chars", "n_symbols",
        (F.col("_l.n") - F.col("_l.d")).cast("long").alias("n_dup_lines"),
        F.when(F.size("_h") < 2 * 1 + WINDOW - 1, F.lit(0)).otherwise(_repeats(F.col("_h"))).cast("long").alias("n_repeat_words"),
        F.col("_l.n").cast("long").alias("n_lines"),
    )
    counted = counted.select(F.inline(F.array(F.struct(*counted.columns))))
    failed = F.lit(0).cast("long")
    for name, fails in RULES:
        failed = failed.bitwiseOR(F.when(F.expr(fails), F.lit(BIT[name])).otherwise(F.lit(0)).cast("long"))
    return counted.withColumn("failed", failed)


def apply_policy(ledger: DataFrame, policy: Policy) -> DataFrame:
    """Adds base_failed and kept; reads the ledger's bits alone."""
    bits = F.col("failed")
    return ledger.withColumns({
        "base_failed": bits.bitwiseAND(F.lit(BASE.mask).cast("long")) != 0,
        "kept": bits.bitwiseAND(F.lit(policy.mask | BASE.mask).cast("long")) == 0,
    })


def ablations(ledger: DataFrame, policy: Policy) -> DataFrame:
    """For each rule of the policy: documents that fail it, that only it rejects, and that stay if it is
    left out. One aggregation over at most 2^rules distinct bit sets."""
    sets = ledger.groupBy(F.col("failed").bitwiseAND(F.lit(policy.mask).cast("long")).alias("bits")).agg(F.count(F.lit(1)).alias("n"))
    rules = ", ".join(f"named_struct('rule', '{r}', 'bit', {BIT[r]}L)" for r in policy.rules)
    return (
        sets.select("bits", "n", F.inline(F.expr(f"array({rules})")))
        .groupBy("rule")
        .agg(
            F.sum(F.when(F.col("bits").bitwiseAND(F.col("bit")) != 0, F.col("n")).otherwise(0)).alias("fails"),
            F.sum(F.when(F.col("bits") == F.col("bit"), F.col("n")).otherwise(0)).alias("only_this"),
            F.sum(F.when(F.col("bits").bitwiseAND(F.bitwise_not(F.col("bit"))) == 0, F.col("n")).otherwise(0)).alias("kept_without"),
        )
    )


def reject(docs: DataFrame, policy: Policy = POLICIES["v1"]) -> DataFrame:
    """The rows of docs that the policy keeps, with their columns as they were."""
    return apply_policy(measure(docs, carry=True), policy).where("kept").select("_row.*")


def quality_rules(docs: DataFrame, policy: Policy = POLICIES["v1"]) -> DataFrame:
    return apply_policy(measure(docs), policy)


ORACLE = r"""
WITH w AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, i, array_to_string(ws[i:i + 7], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 6)) AS i FROM w WHERE len(ws) >= 8)),
twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS c FROM win) WHERE c > 1),
marked AS (SELECT doc_id, count(DISTINCT i + o) AS n FROM twice, range(8) r(o) GROUP BY 1),
lines AS (SELECT doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM w),
m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
        CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(ls) - list_unique(ls) AS BIGINT) AS n_dup_lines,
        CAST(coalesce(marked.n, 0) AS BIGINT) AS n_repeat_words, CAST(len(ls) AS BIGINT) AS n_lines
      FROM w JOIN lines USING (doc_id) LEFT JOIN marked USING (doc_id)),
f AS (SELECT *, CAST(""" + " + ".join(f"CASE WHEN {cond} THEN {BIT[name]} ELSE 0 END" for name, cond in RULES) + f""" AS BIGINT) AS failed FROM m)
SELECT *, (failed & {BASE.mask}) <> 0 AS base_failed, (failed & {POLICIES["v1"].mask | BASE.mask}) = 0 AS kept FROM f
"""
