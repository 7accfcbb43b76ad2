"""Secrets in texts: strong patterns, and weak parts that count only beside their complements.

Base kinds are assign, access and hex. The method adds identifiers, keys and endpoints
that are too weak alone: within one scope (a run of text without a blank line) they
are joined; an identifier counts when a key is there, a key when an identifier or
endpoint is, an endpoint when both are. Scopes are the intervals of the join: parts meet over the whole of one,
however far apart, and none meets across a border. Every search is linear in the text, runs without a break too.

Defined cases: a null text is empty and has no spans. Repeated rows stay repeated.
Offsets are code points, ends exclusive. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _either(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


_NAMES = "|".join(_either(w) for w in ("password", "passwd", "secret", "token")) + "|" + _either("api") + "_?" + _either("key")
ASSIGN = re.compile(rf"""({_NAMES})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")  # whole runs, so the same as runs of 24 or more

WEAK_ID = re.compile(r"(?:AKIA|ASIA|AROA|AIDA)[A-Z0-9]{8,}|(?:client|account|user)_id[\"']?\x20*[:=]\x20*[\"']?[A-Za-z0-9._-]{6,}")
WEAK_KEY = re.compile(r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z0-9+/_-]*[0-9])(?=[A-Za-z0-9+/_-]*[A-Z])(?=[A-Za-z0-9+/_-]*[a-z])[A-Za-z0-9+/_-]{20,}")
ADDRESS = re.compile(r"(?:https?|s3|postgres(?:ql)?|mysql|mongodb|redis|amqps?)://[^\s\"'<>]+")
CLOUD, HOST = ".amazonaws.com", frozenset("abcdefghijklmnopqrstuvwxyz0123456789.-")
SCOPE = re.compile(r"\n[\x20\x09\x0B-\x0D]*\n")

KINDS = ("assign", "access", "hex", "id", "key", "endpoint")
MASK = "[redacted]"

Span = tuple[int, int, str]


def base_spans(text: str) -> list[Span]:
    out: list[Span] = []
    if "=" in text or ":" in text:
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return out


def endpoints(text: str) -> list[Span]:
    """Addresses with a scheme, and cloud hosts outside them: from each occurrence of the cloud's domain the run of host
    characters around it, from its first letter or digit to its last such domain. A run is walked once."""
    out = [(m.start(), m.end(), "endpoint") for m in ADDRESS.finditer(text)]
    starts, at = [s for s, _, _ in out], 0
    hosts: list[Span] = []
    while (k := text.find(CLOUD, at)) >= 0:
        inside = bisect_right(starts, k) - 1
        if inside >= 0 and out[inside][1] > k:
            at = max(k + 1, out[inside][1])
            continue
        lo = k
        while lo > at and text[lo - 1] in HOST:
            lo -= 1
        hi = k + len(CLOUD)
        while hi < len(text) and text[hi] in HOST:
            hi += 1
        while lo < k and text[lo] in ".-":
            lo += 1
        end = text.rfind(CLOUD, k, hi) + len(CLOUD)
        if lo < k:
            hosts.append((lo, end, "endpoint"))
        at = hi
    return sorted(out + hosts)


def overlapping(spans: list[Span], others: list[Span]) -> set[Span]:
    """Spans that share a character with one of the others: an interval join by sorted starts and, since
    others may nest, the running maximum of their ends."""
    others = sorted(others)
    starts, ends, most = [s for s, _, _ in others], [], 0
    for _, e, _ in others:
        most = max(most, e)
        ends.append(most)
    found = set()
    for x in spans:
        k = bisect_left(starts, x[1])  # all that start before x ends
        if k and ends[k - 1] > x[0]:
            found.add(x)
    return found


def linked_spans(text: str, base: list[Span]) -> list[Span]:
    """Weak parts with their complements in the same scope; none that overlaps a base span."""
    has_end = "://" in text or CLOUD in text
    if not (has_end or "_id" in text or any(p in text for p in ("AKIA", "ASIA", "AROA", "AIDA"))):
        return []
    ids = [(m.start(), m.end(), "id") for m in WEAK_ID.finditer(text)]
    ends = endpoints(text) if has_end else []
    if not (ids or ends):
        return []
    keys = [(m.start(), m.end(), "key") for m in WEAK_KEY.finditer(text)]
    borders = [m.start() for m in SCOPE.finditer(text)]
    scopes: dict[int, list[list[Span]]] = {}
    for which, spans in enumerate((ids, keys, ends, base)):
        for x in spans:
            scopes.setdefault(bisect_left(borders, x[0]), [[], [], [], []])[which].append(x)
    out: list[Span] = []
    for own_ids, own_keys, own_ends, strong in scopes.values():
        some_id = own_ids or any(x[2] == "access" for x in strong)
        some_key = own_keys or any(x[2] != "access" for x in strong)
        out += own_ids if some_key else []
        out += own_keys if some_id or own_ends else []
        out += own_ends if some_id and some_key else []
    covered = overlapping(out, base)
    return [x for x in out if x not in covered]


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{s}:{e}" for s, e, kind in sorted(spans, key=lambda x: (x[0], KINDS.index(x[2]), x[1])))


def _scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in batches:
        rows = []
        for t in pdf["text"]:
            t = t if isinstance(t, str) else ""
            base = base_spans(t)
            both = base + linked_spans(t, base)
            n = [sum(1 for x in base if x[2] == k) for k in KINDS[:3]]
            rows.append((*n, hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(both)))
        yield pd.DataFrame(rows, columns=["n_assign", "n_access", "n_hex", "base_sha256", "spans"]).assign(doc_id=pdf["doc_id"].to_numpy())[["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"]]


def scan_secrets(docs: DataFrame) -> DataFrame:
    """One row a document: counts of base spans, the hash of their list, and all spans. No shuffle."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInPandas(
        _scan, f"doc_id {kind}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redact(text: str, mask: str = MASK) -> str:
    """The text with every reported stretch replaced by the mask; overlapping spans become one."""
    base = base_spans(text)
    spans = sorted(base + linked_spans(text, base))
    if not spans:
        return text
    out, at = [], 0
    for s, e, _ in spans:
        if s > at or (s == at and not out):
            out += [text[at:s], mask]
        at = max(at, e)
    return "".join(out) + text[at:]


def redact_secrets(docs: DataFrame) -> DataFrame:
    """The same rows and columns, with every reported span of text replaced. No shuffle."""
    masked = F.pandas_udf(lambda texts: texts.map(lambda t: redact(t) if isinstance(t, str) else None), "string")
    return docs.withColumn("text", masked(F.col("text").cast("string")))
