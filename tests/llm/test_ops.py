"""Operators against brute force, on the small tables and on awkward rows."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from cfengine.llm import hidden_markov as H
from cfengine.llm import packing as P
from cfengine.llm import quality_rules as Q
from cfengine.llm import secret_scan as S
from cfengine.llm import source_mix as M
from cfengine.llm.language_id import LanguageModel, _viterbi, language_id
from cfengine.llm.near_dedup import components, near_duplicates, one_of_each
from cfengine.llm.permutation_index import nearest_neighbours, search_block, choose_pivots
from cfengine.llm.quality_model import quality_scores
from cfengine.llm.url_filter import BloomCascade, _keys, judge_urls

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _h long, size long, target string"


def fold(i, n):
    return zlib.crc32(("" if i is None else str(i)).encode()) % n


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").cache()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, blanks, a long text, repeated rows, and columns whose names clash with inner ones."""
    base = "the of and to a in is it you that he was for on are with as his they be at"
    rows = [(1, None), (2, ""), (3, " \t\n\x0b\x0c\r "), (4, base), (4, base), (5, base.upper()), (None, base), (6, "é" * 3 + " \u3000 \U0001f600 ..."), (7, (base + " ") * 3000), (8, "x"), (9, "x"), (10, "a b"), (11, "a\x00b c\x1cd")]
    return spark.createDataFrame([(i, t, "en" if k % 2 else None, None if k % 3 else "s", None, 1, 2, "z") for k, (i, t) in enumerate(rows)], SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words(t):
    return WORD.findall(t or "")


# --- 4 ----------------------------------------------------------------------


def measure(t):
    w = words(t)
    c = collections.Counter(tuple(w[k : k + 8]) for k in range(len(w) - 7))
    mark = set()
    for k in range(len(w) - 7):
        if c[tuple(w[k : k + 8])] > 1:
            mark.update(range(k, k + 8))
    lines = [x for x in (t or "").split("\n") if words(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(mark)


@pytest.mark.parametrize("which", ["docs", "odd", "empty"])
def test_quality_measures(request, which):
    df = request.getfixturevalue(which)
    got = sorted((str(r.doc_id), r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in Q.quality_rules(df).collect())
    want = []
    for r in df.collect():
        m = measure(r.text)
        want.append((str(r.doc_id), *m, m[0] < 20 or 100 * m[4] > 30 * m[0]))
    assert got == sorted(want)


def test_ablations_count_bits(docs):
    ledger = Q.measure(docs)
    p = Q.POLICIES["v2"]
    rows = {r.rule: r for r in Q.ablations(ledger, p).collect()}
    assert rows["too_few_words"].fails == ledger.where("n_words < 20").count()
    without = sum(1 for r in ledger.collect() if not r.failed & p.mask & ~Q.BIT["symbols_over_words"])
    assert rows["symbols_over_words"].kept_without == without


def test_reject_keeps_columns(odd):
    out = Q.reject(odd)
    assert out.columns == odd.columns and out.count() == Q.quality_rules(odd).where("kept").count()


# --- 9 ----------------------------------------------------------------------


def plain_spans(t):
    name = "(" + "|".join("".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in w) for w in ("password", "passwd", "secret", "token")) + "|[aA][pP][iI]_?[kK][eE][yY])"
    out = [("assign", m) for m in re.finditer(name + r"""["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t) if len(m.group(2)) >= 6]
    out += [("access", m) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m.group()) >= 20]
    out += [("hex", m) for m in re.finditer("[0-9a-f]+", t) if len(m.group()) >= 24]
    order = ("assign", "access", "hex")
    return ",".join(f"{k}:{m.start()}:{m.end()}" for k, m in sorted(out, key=lambda x: (x[1].start(), order.index(x[0]))))


EXTRA = ["", "toKen:abc token = abcdef", "AKIA" + "A" * 16 + " x AKIA1234", "PASSWORD='a.b=c/d' é\U0001f600 " + "f" * 30, "api_key=" + "0" * 40, "ſecret=abcdefg apiKey:'123456'"]


def test_base_spans(spark, docs, odd):
    extra = spark.createDataFrame([(1000 + k, t) for k, t in enumerate(EXTRA)], "doc_id long, text string")
    df = docs.select("doc_id", "text").union(odd.select("doc_id", "text")).union(extra)
    text = sorted(((str(r.doc_id), hashlib.sha256(plain_spans(r.text or "").encode()).hexdigest()) for r in df.collect()))
    assert sorted((str(r.doc_id), r.base_sha256) for r in S.scan_secrets(df).collect()) == text


def test_weak_parts_need_their_complement():
    ident, key = "client_id = acme-7788", "Zx9" + "aB3dE5" * 4
    end = "https://db.internal.example/api"
    far = " word" * 100
    kinds = lambda t: sorted(k for _, _, k in S.linked_spans(t, S.base_spans(t)))
    assert kinds(ident) == [] and kinds(key) == [] and kinds(end) == []
    assert kinds(f"{ident} {key}") == ["id", "key"]
    assert kinds(f"{ident} {key} {end}") == ["endpoint", "id", "key"]
    assert kinds(f"{ident} {far} {key}") == ["id", "key"] and kinds(f"{ident}\n\n{key}") == []
    assert key not in S.redact(f"{ident} {key}")


def test_parts_at_both_ends_of_a_scope(spark):
    ident, key, end = "client_id = acme-7788", "Zx9" + "aB3dE5" * 4, "https://db.internal.example/api"
    far = " word" * 1000
    rows = [(0, f"{ident} {far} {key}"), (1, f"{end} {far} {ident} {far} {key}"), (2, f"{ident} {far}\n\n{key}")]
    got = {r.doc_id: [x.split(":")[0] for x in r.spans.split(",") if x] for r in S.scan_secrets(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {0: ["id", "key"], 1: ["endpoint", "id", "key"], 2: []}
    assert key not in S.redact(rows[0][1]) and ident not in S.redact(rows[0][1]) and S.redact(rows[2][1]) == rows[2][1]


def plain_linked(t):
    """Weak parts by trying every pair of spans."""
    host = "abcdefghijklmnopqrstuvwxyz0123456789.-"
    base = [(int(x.split(":")[1]), int(x.split(":")[2]), x.split(":")[0]) for x in plain_spans(t).split(",") if x]
    ids = [(m.start(), m.end(), "id") for m in S.WEAK_ID.finditer(t)]
    keys = [(m.start(), m.end(), "key") for m in S.WEAK_KEY.finditer(t)]
    ends = [(m.start(), m.end(), "endpoint") for m in S.ADDRESS.finditer(t)]
    for m in re.finditer(r"[a-z0-9][a-z0-9.-]*\.amazonaws\.com", t):
        if not any(a < m.end() and m.start() < b for a, b, _ in ends):
            ends.append((m.start(), m.end(), "endpoint"))
    assert all(set(t[a:b]) <= set(host) for a, b, _ in ends if "://" not in t[a:b])
    borders = [m.start() for m in S.SCOPE.finditer(t)]
    scope = lambda x: sum(b < x[0] for b in borders)
    out = []
    for x in ids + keys + ends:
        mates = [y for y in ids + keys + ends + base if y != x and scope(y) == scope(x)]
        has_id = any(y[2] in ("id", "access") for y in mates)
        has_key = any(y[2] in ("key", "assign", "hex") for y in mates)
        good = {"id": has_key, "key": has_id or any(y[2] == "endpoint" for y in mates), "endpoint": has_id and has_key}[x[2]]
        if good and not any(a < x[1] and x[0] < b for a, b, _ in base):
            out.append(x)
    return sorted(out)


def test_linked_spans_against_every_pair():
    rng = np.random.default_rng(7)
    parts = ["client_id=acme-7788", "Zx9" + "aB3dE5" * 4, "https://db.example/api", "s3.eu.amazonaws.com", "-.x.amazonaws.com.b.amazonaws.com-", "AKIA" + "B" * 16, "AKIA12345678", "f" * 30, "token=" + "a" * 24 + ":" + "b" * 25, "token=" + " ".join(["0" * 24] * 4), "\n\n", "\n \t\n", "\n", "word", "user_id: 'abcdef12'"]
    found = 0
    for _ in range(400):
        t = "".join(parts[k] + ("" if rng.random() < 0.2 else " ") for k in rng.integers(0, len(parts), int(rng.integers(1, 14))))
        want = plain_linked(t)
        assert sorted(S.linked_spans(t, S.base_spans(t))) == want, t
        found += len(want)
    assert found > 300
    nested = "token=" + "0f" * 12 + "." + "1e" * 12 + "." + "a" * 400 + "client_id=acme-7788 " + "Zx9" + "aB3dE5" * 4
    assert sorted(S.linked_spans(nested, S.base_spans(nested))) == plain_linked(nested)


def test_long_runs_take_linear_time(spark):
    import time

    for run in ("a" * 1_000_000, "a.-" * 350_000, "AKIA" * 250_000, "token " * 170_000, "x.amazonaws.com" * 70_000, " " * 1_000_000, "\n" * 1_000_000, "client_id" * 100_000, "aB3" * 350_000):
        t = run + " client_id=acme-7788 https://h/ " + "Zx9" + "aB3dE5" * 4 + " b.amazonaws.com"
        began = time.perf_counter()
        S.linked_spans(t, S.base_spans(t))
        assert time.perf_counter() - began < 2, run[:12]
    assert S.scan_secrets(spark.createDataFrame([], SCHEMA)).count() == 0


def test_redaction_leaves_clean_text(docs):
    for r in docs.limit(50).collect():
        if not S.base_spans(r.text) and not S.linked_spans(r.text, []):
            assert S.redact(r.text) == r.text


# --- 10 ---------------------------------------------------------------------


def test_urls(spark):
    urls = [None, "", "nourl", "http://A.org/x", "https://example.org/es/1?x", "http://sub.example.org/en/12#a", "http://example.org/en/2", "http://x.com/de/1", "http://x.com", "http://casino-win.example.net?x/fr/", "HTTP://y.com/fr/", "x://org", "http://norg/", "a://b://c", "http://.com/de/"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("host", F.lit("clash"))
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in judge_urls(df).collect()}
    from cfengine.llm.url_filter import LISTED_HOSTS, RULES

    for k, u in enumerate(urls):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        host = re.match(r"[^/?#]*", rest).group().translate(LOWER)
        path = re.match(r"[^/?#]*([^?#]*)", rest).group(1)
        fits = sorted(((len(h + p), len(h), h + p, v) for v, h, p in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)), reverse=True)
        listed = any(host == x or host.endswith("." + x) for x in LISTED_HOSTS)
        want = (host, path, fits[0][2] if fits else None, fits[0][3] if fits else "block" if listed else "allow")
        assert got[k] == want, u
    assert judge_urls(df.limit(0)).count() == 0


def test_cascade_is_exact(spark):
    universe = spark.range(20_000).select(F.concat(F.lit("k"), F.col("id")).alias("key"))
    listed = [f"k{k}" for k in range(0, 20_000, 37)] + ["elsewhere"]
    c = BloomCascade.build(_keys(spark, listed), universe)
    assert len(c.levels) > 1
    got = {r.key for r in universe.where(c.contains(F.col("key"))).collect()}
    assert got == set(listed) - {"elsewhere"}


# --- 6 ----------------------------------------------------------------------


def exact_classes(rows, n, percent):
    sets = {}
    for i, t in rows:
        w = words((t or "").translate(LOWER))
        sets[i] = frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)]) if w else frozenset()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if sets[a] and sets[b]:
                c = len(sets[a] & sets[b])
                if 100 * c >= percent * (len(sets[a]) + len(sets[b]) - c):
                    x, y = find(a), find(b)
                    root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_near_duplicates(docs, odd, empty):
    for df in (docs, odd.where("doc_id is not null")):
        want = exact_classes([(r.doc_id, r.text) for r in df.collect()], 3, 85)
        for r in near_duplicates(df).collect():
            assert (r.n_shingles, r.component_id) == want[r.doc_id] and r.kept == (r.doc_id == r.component_id)
    assert near_duplicates(odd).count() == odd.count() and near_duplicates(empty).count() == 0


def test_large_region_is_compared_in_blocks(spark, monkeypatch):
    """A crowd of near copies larger than a block: all links are found and none is lost to a cap."""
    rng = np.random.default_rng(4)
    vocab = [f"w{k}" for k in range(400)]
    base = rng.choice(vocab, 120).tolist()
    rows = []
    for i in range(600):
        t = list(base)
        for k in rng.choice(120, int(rng.integers(0, 6)), replace=False):
            t[k] = vocab[int(rng.integers(400))]
        rows.append((i, " ".join(t)))
    got = {r.doc_id: r.component_id for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: c for i, (_, c) in exact_classes(rows, 3, 85).items()}


def test_crowded_region_keeps_the_links_of_its_depth(spark, monkeypatch):
    """A family with shingles of its own in each document: most leave the crowd as it is deepened, and still belong to it."""
    from cfengine.llm import near_dedup as N

    monkeypatch.setattr(N, "REGION", 50)
    monkeypatch.setattr(N, "BLOCK", 16)
    base = " ".join(f"t{k}" for k in range(100))
    rows = [(i, " ".join([base, *(f"d{i}x{k}" for k in range(7))])) for i in range(400)]
    rows += [(i, " ".join([base, *(f"d{i}x{k}" for k in range(40))])) for i in range(400, 440)]
    got = {r.doc_id: r.component_id for r in near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: c for i, (_, c) in exact_classes(rows, 3, 85).items()}


def exact_crowd(texts, percent, n):
    """Components of all links by products of 0/1 rows."""
    from cfengine.llm.near_dedup import shingle_sets

    sets = shingle_sets(texts, n)
    _, inverse, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    owner, col = np.repeat(np.arange(len(sets)), [len(x) for x in sets]), np.cumsum(counts > 1) - 1
    use = (counts > 1)[inverse]
    m = np.zeros((len(sets), int((counts > 1).sum())), np.float32)
    m[owner[use], col[inverse[use]]] = 1
    size = np.array([len(x) for x in sets])
    label = np.arange(len(sets))
    linked = []
    for a in range(0, len(sets), 500):
        c = (m[a : a + 500] @ m.T).astype(np.int64)
        linked.append(100 * c >= percent * (size[a : a + 500, None] + size[None, :] - c))
    linked = np.concatenate(linked)
    while True:  # every document takes the smallest label among its links
        new = np.array([label[row].min() for row in linked])
        if (new == label).all():
            return label
        label = new


@pytest.mark.parametrize("kind", ["edits", "own"])
def test_crowd_of_five_thousand_loses_no_link(spark, kind):
    rng = np.random.default_rng(1)
    if kind == "edits":
        texts = []
        for _ in range(5000):
            t = [f"b{k}" for k in range(100)]
            for k in rng.choice(100, int(rng.integers(1, 4)), replace=False):
                t[k] = f"x{k}y{rng.integers(2)}"
            texts.append(" ".join(t))
    else:
        base = " ".join(f"t{k}" for k in range(60))
        texts = [" ".join([base, *(f"d{i}x{k}" for k in range(4))]) for i in range(5000)]
    got = {r.doc_id: r.component_id for r in near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8)).collect()}
    assert [got[i] for i in range(5000)] == exact_crowd(texts, 85, 3).tolist()


def test_one_id_with_several_texts(spark):
    base = " ".join(f"w{k}" for k in range(60))
    rows = [(5, base), (5, "something else entirely " * 5), (7, base + " z"), (7, base + " z"), (9, "lonely words here"), (None, base)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in near_duplicates(df).collect())
    assert got == sorted([("5", 58, "5"), ("5", 3, "5"), ("7", 59, "5"), ("7", 59, "5"), ("9", 1, "9"), ("None", 58, "None")])
    for part in (1, 4):
        left = sorted((str(r.doc_id), r.text) for r in one_of_each(df.repartition(part), 85, 3).collect())
        assert [i for i, _ in left] == ["5", "9", "None"] and left == sorted((str(r.doc_id), r.text) for r in one_of_each(df, 85, 3).collect())


def test_one_of_each(docs):
    want = {c for _, c in exact_classes([(r.doc_id, r.text) for r in docs.collect()], 5, 80).values()}
    out = one_of_each(docs, 80, 5)
    assert sorted(r.doc_id for r in out.collect()) == sorted(want) and out.columns == docs.columns


def test_components_of_a_chain(spark):
    from cfengine.llm.common import Scratch

    links = spark.range(1, 200).select(F.col("id").alias("a"), (F.col("id") - 1).alias("b"))
    got = components(links, Scratch(spark))
    assert got.count() == 199 and got.where("comp <> 0").isEmpty()


# --- 2 ----------------------------------------------------------------------


def test_mix(docs, odd, empty):
    for df in (docs, odd):
        rows = M.plan_mix(df).collect()
        assert len(rows) == df.count()
        src = collections.defaultdict(list)
        for r in rows:
            src[r.source].append(r)
        names = sorted(src, key=lambda s: (s is None, s or ""))
        total = sum(r.size for r in rows)
        goal = dict(zip(names, M.targets([sum(r.size for r in src[s]) for s in names], [(1, 2, 3)[k % 3] for k in range(len(names))], total), strict=True))
        for s, own in src.items():
            size = sum(r.size for r in own)
            assert all(r.source_size == size and r.target == pytest.approx(goal[s]) and r.taken <= 3 * r.size and r.taken == r.copies * r.size for r in own)
            assert abs(sum(r.taken for r in own) - goal[s]) <= max(1, max(r.size for r in own) / 2)
        assert all(len(r.positions) == r.copies and all(0 <= x <= 1 for x in r.positions) for r in rows)
        assert sorted(map(str, rows)) == sorted(map(str, M.plan_mix(df.repartition(5)).collect()))
    assert M.plan_mix(empty).count() == 0


def test_long_document_does_not_end_the_pass(spark):
    """One of 1,000 words first in hash order, small ones behind it that meet the target exactly."""
    ids = [(k,) for k in range(101)]
    order = [r.id for r in spark.createDataFrame(ids, "id long").orderBy(F.xxhash64(F.md5(F.col("id").cast("string")))).collect()]
    rows = [(i, "w " * (1000 if i == order[0] else 10), "a") for i in order] + [(1000, "w " * 3400, "b")]
    taken = spark_sums(M.plan_mix(spark.createDataFrame(rows, "doc_id long, text string, source string"), weights=(400, 5000)))
    assert taken["a"] == 400


def spark_sums(mix):
    return {r.source: r.n for r in mix.groupBy("source").agg(F.sum("taken").alias("n")).collect()}


def shares_by_hand(sizes, weights):
    """Targets by pouring a little at a time into every source that is not yet full."""
    total, out = sum(sizes), [0.0] * len(sizes)
    steps = 20_000
    for _ in range(steps):
        open_ = [k for k, s in enumerate(sizes) if out[k] < 3 * s - 1e-9]
        for k in open_:
            out[k] += total / steps * weights[k] / sum(weights[j] for j in open_)
    return out


def test_targets_against_pouring():
    rng = np.random.default_rng(2)
    for _ in range(10):
        sizes = [int(x) for x in rng.choice([0, 3, 10, 50, 1000], 5)]
        weights = [(1, 2, 3)[k % 3] for k in range(5)]
        if sum(sizes):
            assert M.targets(sizes, weights, sum(sizes)) == pytest.approx(shares_by_hand(sizes, weights), abs=max(1, sum(sizes)) / 500)


def test_order_of_repeated_ids(spark):
    df = spark.createDataFrame([(k % 3 if k % 4 else None, "w " * (k + 1), "s") for k in range(24)], "doc_id long, text string, source string")
    mix = M.plan_mix(df)
    one = [(r.doc_id, r.text, r.position) for r in M.training_order(df, mix).collect()]
    two = [(r.doc_id, r.text, r.position) for r in M.training_order(df.repartition(5), M.plan_mix(df.repartition(3))).collect()]
    assert sorted(map(str, one)) == sorted(map(str, two))


def test_targets_reshare_what_caps_leave():
    assert M.targets([10, 1000], [1, 1], 1010) == [30.0, 980.0]
    assert sum(M.targets([5, 5, 90], [3, 3, 1], 100)) == pytest.approx(100)


def test_positions_invert_the_integral(spark):
    for knots in M.SCHEDULES:
        segs = F.array(*[F.struct(*[F.lit(v).alias(n) for n, v in s.__dict__.items()]) for s in M.segments(knots)])
        for r in spark.range(21).select((F.col("id") / 20).alias("u")).withColumn("t", M.position(F.col("u"), segs)).collect():
            grid = np.linspace(0, r.t, 2001)
            w = np.interp(grid, *zip(*knots, strict=True))
            whole = np.linspace(0, 1, 2001)
            assert np.trapezoid(w, grid) / np.trapezoid(np.interp(whole, *zip(*knots, strict=True)), whole) == pytest.approx(r.u, abs=1e-6)


def test_training_order(docs):
    mix = M.plan_mix(docs)
    out = M.training_order(docs, mix)
    pos = [r.position for r in out.collect()]
    assert pos == sorted(pos) and len(pos) == mix.agg(F.sum("copies")).first()[0]


# --- 5 ----------------------------------------------------------------------


def test_packing(docs, odd, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(P.tokenizer_path())
    for df in (docs, odd):
        rows = P.best_fit_packing(df).collect()
        want = []
        for r in df.collect():
            ids = tok.encode(r.text or "", add_special_tokens=False).ids + [1]
            want += [(str(r.doc_id), k // 4096, k, len(ids[k : k + 4096]), zlib.crc32(np.array(ids[k : k + 4096], "<u4").tobytes())) for k in range(0, len(ids), 4096)]
        assert sorted((str(r.doc_id), r.piece, r.start, r.length, r.ids_crc32) for r in rows) == sorted(want)
        seqs = collections.defaultdict(list)
        for r in rows:
            seqs[r.sequence_id].append((r.offset, r.length))
        for parts in seqs.values():
            at = 0
            for o, n in sorted(parts):
                assert o == at
                at += n
            assert at <= 4096
        counts = collections.Counter(r.length for r in rows)
        assert len(seqs) <= P.lower_bound(counts) + 2
    assert P.best_fit_packing(empty).count() == 0


def test_encoder_on_odd_characters():
    from tokenizers import Tokenizer

    tok, enc = Tokenizer.from_file(P.tokenizer_path()), P.WordEncoder(P.tokenizer_path(), limit=50)
    rng = np.random.default_rng(0)
    for t in ["a\x1cb c", "don't it's", "<|endoftext|> x", "e\u0301 J\u030c \u03a3\u03a3 \u03a3", "a\u200bb\x85c\xa0d", "\u3000你好"] + ["".join(map(chr, rng.integers(0, 600, 50))) for _ in range(200)]:
        assert list(np.frombuffer(next(iter(enc.encode([t]))), "<u4")) == tok.encode(t, add_special_tokens=False).ids


def test_reduction_is_optimal_on_small_instances():
    """Bins after reduction and best fit against the true optimum by search."""
    rng = np.random.default_rng(3)

    def optimum(ws, cap):
        ws = sorted(ws, reverse=True)
        best = [len(ws)]

        def go(k, bins):
            if len(bins) >= best[0]:
                return
            if k == len(ws):
                best[0] = len(bins)
                return
            for j in sorted(set(range(len(bins))), key=lambda j: bins[j]):
                if bins[j] + ws[k] <= cap:
                    bins[j] += ws[k]
                    go(k + 1, bins)
                    bins[j] -= ws[k]
            go(k + 1, bins + [ws[k]])

        go(0, [])
        return best[0]

    for _ in range(60):
        cap = 20
        ws = rng.integers(1, cap + 1, size=8).tolist()
        c = collections.Counter(ws)
        p = P.pack_lengths(dict(c), cap)
        assert collections.Counter(w for pat, n in p.patterns for w in pat for _ in range(n)) == c
        done, rest = P.reduce_by_dominance(dict(c), cap)
        left = [w for w, n in rest.items() for _ in range(n)]
        assert sum(n for _, n in done) + optimum(left, cap) == optimum(ws, cap)
        assert p.bins <= optimum(ws, cap) + 1


# --- 1, 3, 7, 8 -------------------------------------------------------------


def test_language_id(docs, odd, empty):
    got = {r.doc_id: r for r in language_id(docs).collect()}
    held = [r for r in docs.collect() if fold(r.doc_id, 5) == 0]
    assert np.mean([got[r.doc_id].lang_pred == r.lang for r in held]) > 0.97
    assert all(got[i].held_out == (fold(i, 5) == 0) and 0 <= got[i].score <= 1 for i in got)
    rows = language_id(odd).collect()
    assert len(rows) == odd.count() and {r.lang_pred for r in rows if r.doc_id in (1, 2, 3)} == {"und"}
    assert language_id(empty).count() == 0


def predicted_by_loops(m, text):
    """Every word scored gram by gram, every path step by step."""
    from cfengine.llm import language_id as L

    mask, points = (1 << 64) - 1, list(L._points([text.replace("\0", " ")]))
    letter = L._letters()

    def mixed(x):
        x ^= x >> 33
        x = x * 0xFF51AFD7ED558CCD & mask
        x ^= x >> 33
        x = x * 0xC4CEB9FE1A85EC53 & mask
        return x ^ (x >> 33)

    chars = [int(p) if letter[p] else 0 for p in points]
    words, at = [], 0
    while at < len(chars):
        end = at
        while end < len(chars) and letter[points[end]]:
            end += 1
        if end > at:
            words.append((at, end))
        at = end + 1
    if not words:
        return "und", 0.0
    k = len(m.langs)
    scores = []
    for a, b in words:
        own = np.zeros(k)
        for p in range(a, b):
            for n in L.ORDERS:
                h = 0
                for q in range(p - 1, p - 1 + n):
                    h = (h * 1_000_003 + (chars[q] if 0 <= q < len(chars) else 0) + 7) & mask
                own += m.logp[mixed((h + n - 1) & mask) & (L.BUCKETS - 1)]
        script = L.SCRIPT_KINDS[np.searchsorted(L.SCRIPT_STARTS, points[a], side="right") - 1]
        scores.append(own / len(L.ORDERS) + np.where(m.allowed[script], 0, -50))
    value, back = list(scores[0]), []
    for s in scores[1:]:
        moves = [max(range(k), key=lambda i: (value[i] - m.penalty * (i != j), i == j)) for j in range(k)]
        value = [value[moves[j]] - m.penalty * (moves[j] != j) + s[j] for j in range(k)]
        back.append(moves)
    state = int(np.argmax(value))
    path = [state]
    for moves in reversed(back):
        state = moves[state]
        path.append(state)
    share = np.zeros(k)
    for j, (a, b) in zip(reversed(path), words, strict=True):
        share[j] += b - a
    return m.langs[int(share.argmax())], share.max() / share.sum()


def test_predictions_against_loops(docs):
    from cfengine.llm.language_id import fit_language_model

    m = fit_language_model(docs)
    texts = [r.text for r in docs.collect() if r.text and len(r.text) < 700][:40]
    texts += [texts[0][:200] + " " + texts[5][:200] + " \u0416\u0443\u043a 123 " + texts[9][:150], "a\0b", "x", "12 ?", ""]
    langs, scores = m.predict(texts)
    for t, lang, score in zip(texts, langs, scores, strict=True):
        want = predicted_by_loops(m, t)
        assert (lang, score) == (want[0], pytest.approx(want[1], abs=0.02)), t[:50]


def test_long_texts_in_pieces_are_whole(monkeypatch):
    """Texts above the working size of a kernel give what they give at once."""
    from cfengine.llm import quality_model as QM
    from cfengine.llm.common import word_hashes

    rng = np.random.default_rng(0)
    texts = [" ".join(rng.choice(["alpha", "Beta", "g\u00e9", "x1", "..."], int(n))) for n in (0, 1, 3000, 7, 900)] + [None, "z" * 5000]
    whole, parts = word_hashes(texts), word_hashes(texts, limit=64)
    assert all((a == b).all() for a, b in zip(whole, parts, strict=True))
    table = rng.normal(size=(QM.TOKENS, QM.DIM)).astype(np.float32)
    once = QM.pool(texts, table)
    monkeypatch.setattr(QM, "CHUNK", 100)
    assert np.allclose(once, QM.pool(texts, table), atol=1e-5)


def test_viterbi_against_full_search():
    rng = np.random.default_rng(1)
    for n in (1, 2, 5):
        scores = rng.normal(size=(n, 3)).astype(np.float32) * 3
        import itertools

        def value(path):
            return sum(scores[k, s] for k, s in enumerate(path)) - 2.0 * sum(a != b for a, b in zip(path, path[1:]))

        best = max(itertools.product(range(3), repeat=n), key=value)
        got = _viterbi(np.concatenate((scores, scores)), np.array([0, n, n, 2 * n]), 2.0)
        assert value(got[:n]) == pytest.approx(value(best)) and value(got[n:]) == pytest.approx(value(best))


def test_spans_of_mixed_text(docs):
    from cfengine.llm.language_id import fit_language_model

    m = fit_language_model(docs)
    by = {lang: next(r.text for r in docs.collect() if r.lang == lang and 400 < len(r.text) < 3000) for lang in ("en", "fr")}
    found = [lang for _, _, lang in m.spans(by["en"][:300] + " " + by["fr"][:300])]
    assert found[0] == "en" and found[-1] == "fr" and len(found) <= 4
    assert LanguageModel([], np.zeros((1, 0)), np.zeros((17, 0), bool)).predict(["a"])[0] == ["und"]


def test_neighbours(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    v = e.toPandas()
    ids, x = v["vec_id"].to_numpy(), np.stack(v["embedding"]).astype(float)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    rows = collections.defaultdict(list)
    for r in nearest_neighbours(e).collect():
        rows[r.query_id].append((r.rank, r.vec_id, r.score))
    hit = n = 0
    for q in ids[ids % 50 == 0]:
        s = unit @ unit[np.flatnonzero(ids == q)[0]]
        s[ids == q] = -9
        hit += len(set(ids[np.lexsort((ids, -s))[:5]]) & {i for _, i, _ in rows[q]})
        n += 5
        for _, i, score in rows[q]:
            assert score == pytest.approx(s[np.flatnonzero(ids == i)[0]], abs=1e-12)
        assert [r for r, _, _ in sorted(rows[q])] == [1, 2, 3, 4, 5]
    assert hit / n >= 0.9


def test_index_of_several_blocks(spark):
    """20,000 vectors in ten blocks, found again from an index that was written once."""
    rng = np.random.default_rng(3)
    n, width = 20_000, 32
    centres = rng.normal(size=(200, width))
    x = (centres[rng.integers(0, 200, n)] + 0.5 * rng.normal(size=(n, width))).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").repartition(8)
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    rows = collections.defaultdict(dict)
    for r in nearest_neighbours(df, every=200, block=2000).collect():
        rows[r.query_id][r.rank] = (r.vec_id, r.score)
    hit = 0
    for q in range(0, n, 200):
        s = unit @ unit[q]
        s[q] = -9
        best = np.lexsort((np.arange(n), -s))[:5]
        hit += len(set(best.tolist()) & {v for v, _ in rows[q].values()})
        assert all(abs(s[v] - score) < 1e-9 for v, score in rows[q].values())
    assert hit / (5 * len(rows)) >= 0.9 and len(rows) == 100


def test_neighbours_on_awkward_vectors(spark):
    rows = [(0, [1.0, 0.0], 1), (1, [1.0, 0.0], 1), (2, [2.0, 0.0], 1), (3, [0.0, 0.0], 1), (4, None, 1), (5, [1.0, None], 1), (6, [float("nan"), 1.0], 1), (50, [0.0, 1.0], 1), (7, [float("inf"), 1.0], 1), (8, [1.0], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, rank int")
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in nearest_neighbours(df).collect()}
    assert {k: v[0] for k, v in got.items()} == {(0, 1): 1, (0, 2): 2, (0, 3): 50, (50, 1): 0, (50, 2): 1, (50, 3): 2}
    assert nearest_neighbours(df.limit(0)).count() == 0


def test_crowd_of_equal_vectors_does_not_hide_others():
    rng = np.random.default_rng(0)
    crowd, rest = np.tile(rng.normal(size=(1, 16)), (3000, 1)), rng.normal(size=(1000, 16))
    x = np.concatenate((crowd, rest))
    q = rest[5:6] + 0.05 * rng.normal(size=(1, 16))
    got = search_block(np.arange(4000), x, np.array([-1]), q, choose_pivots(x[rng.choice(4000, 500)]), 5)
    assert got.sort_values("score")["vec_id"].iloc[-1] == 3005


def test_quality_model(spark, sf, docs, odd, empty):
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    rows = quality_scores(docs, labels).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) and r.held_out == (fold(r.doc_id, 5) == 0) for r in rows)
    y = {r.doc_id: r.quality for r in labels.collect()}
    good, bad = ([r.score for r in rows if y.get(r.doc_id) == k] for k in (1, 0))
    assert np.mean(good) > np.mean(bad) + 0.3
    assert quality_scores(odd, labels.limit(0)).where("score = 0.5").count() == odd.count()
    assert quality_scores(empty, labels).count() == 0


def test_context_vectors_and_pooling_against_loops(spark):
    """Neighbours' random vectors summed token by token, and means of unit vectors text by text."""
    from cfengine.llm import quality_model as QM

    texts = ["The cat sat on the mat. THE CAT", "a b", "one", "", None, "x1 y2 -- x1 y2 ?!", "é ü 3.5 é"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    word, form, offsets = QM.token_ids(texts)
    table = np.zeros((QM.TOKENS, QM.DIM))
    for a, b in zip(offsets[:-1], offsets[1:], strict=True):
        for k in range(a, b):
            for j in (k - 1, k + 1):
                if a <= j < b:
                    for own in (word[k], form[k]):
                        for other in (word[j], form[j]):
                            for d in range(2):
                                table[own, QM._AT[other, d]] += QM._SIGN[other, d]
    table -= table.sum(0) / max(1.0, np.abs(table).sum()) * np.abs(table).sum(1, keepdims=True)
    table /= np.maximum(np.linalg.norm(table, axis=1, keepdims=True), 1e-9)
    got = QM.context_vectors(df)
    assert np.allclose(got, table, atol=1e-5)
    pooled = QM.pool(texts, got)
    for n, (a, b) in enumerate(zip(offsets[:-1], offsets[1:], strict=True)):
        want = np.zeros(QM.FEATURES)
        if b > a:
            for at, ids in ((0, word), (1, form)):
                mean = got[ids[a:b]].mean(0)
                want[at * QM.DIM : (at + 1) * QM.DIM], want[2 * QM.DIM + at] = mean, mean @ mean
        want[-1] = np.log1p(b - a) / 10
        assert np.allclose(pooled[n], want, atol=1e-5)


def test_network_gradient_and_temperature():
    from cfengine.llm.quality_model import Network

    rng = np.random.default_rng(0)
    x = rng.normal(size=(2400, 6))
    y = (x[:, 0] * x[:, 1] > 0).astype(float)
    net = Network().fit(x, y, epochs=80)
    p = net.predict(x)
    assert np.mean((p > 0.5) == y) > 0.85
    assert 0.25 <= net.temperature <= 8
    one = Network().fit(x, np.ones(2400), epochs=5).predict(x)
    assert (one > 0.5).all()


def test_quality_on_held_out_documents(spark):
    """Area under the curve over labelled rows that training did not see, and a sample bound that binds."""
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    y = {r.doc_id: r.quality for r in labels.collect()}
    for sample, least in ((20_000, 0.85), (100, 0.7)):
        rows = [(r.score, y[r.doc_id]) for r in quality_scores(docs, labels, sample).collect() if r.held_out and r.doc_id in y]
        good, bad = ([s for s, v in rows if v == k] for k in (1, 0))
        assert np.mean([(a > b) + 0.5 * (a == b) for a in good for b in bad]) > least


def test_language_model(docs, odd, empty):
    for df in (docs, odd):
        train = collections.Counter()
        for r in df.collect():
            if fold(r.doc_id, 10):
                train.update([*words((r.text or "").translate(LOWER)), "\0end"])
        n, v = sum(train.values()), len(train)
        want = []
        for r in df.collect():
            w = [*words((r.text or "").translate(LOWER)), "\0end"]
            want.append((str(r.doc_id), len(w), sum(train[x] > 0 for x in w), n, round(sum(math.log10((train[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w), 5)))
        got = H.hmm_scores(df, 2).collect()
        assert sorted((str(r.doc_id), r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 5)) for r in got) == sorted(want)
        assert all(np.isfinite(r.score) for r in got)
    held = H.hmm_scores(docs).where("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert held[0] > held[1]
    assert H.hmm_scores(empty, 1).count() == 0


def test_forward_and_counts_against_all_paths(monkeypatch):
    """Texts of one, two and five tokens, cut into segments of two: every path, one by one."""
    import itertools

    monkeypatch.setattr(H, "SEGMENT", 2)
    rng = np.random.default_rng(2)
    states, size = 3, 7
    start, trans, table = rng.dirichlet(np.ones(states)), rng.dirichlet(np.ones(states), states), rng.random((size, states))
    texts = [np.array([3]), np.array([3, 5]), np.array([1, 6, 1, 0, 2])]
    offsets = np.concatenate(([0], np.cumsum([len(t) for t in texts])))
    likes, c_start, c_trans, c_emit = [], np.zeros(states), np.zeros((states, states)), np.zeros((size, states))
    for t in texts:
        paths = {}
        for path in itertools.product(range(states), repeat=len(t)):
            q = start[path[0]] * table[t[0], path[0]]
            for k in range(1, len(t)):
                q *= trans[path[k - 1], path[k]] * table[t[k], path[k]]
            paths[path] = q
        total = sum(paths.values())
        likes.append(math.log10(total))
        for path, q in paths.items():
            c_start[path[0]] += q / total
            for k, s in enumerate(path):
                c_emit[t[k], s] += q / total
                if k:
                    c_trans[path[k - 1], s] += q / total
    codes = np.concatenate(texts)
    assert H.forward_log10(codes, offsets, start, trans, table) == pytest.approx(likes)
    s, t, e, like = H.expected_counts(codes, offsets, start, trans, table)
    assert s == pytest.approx(c_start, rel=1e-4) and np.allclose(t, c_trans, rtol=1e-4) and np.allclose(e, c_emit, atol=1e-5)
    assert like / math.log(10) == pytest.approx(sum(likes), rel=1e-5)


def test_segments_change_nothing(monkeypatch):
    rng = np.random.default_rng(4)
    start, trans, table = rng.dirichlet(np.ones(4)), rng.dirichlet(np.ones(4), 4), rng.random((50, 4)) ** 3 / 100
    offsets = np.concatenate(([0], np.cumsum(rng.integers(1, 900, 12))))
    codes = rng.integers(0, 50, offsets[-1])
    got = []
    for size in (7, 256, 4096):
        monkeypatch.setattr(H, "SEGMENT", size)
        got.append((H.forward_log10(codes, offsets, start, trans, table), *H.expected_counts(codes, offsets, start, trans, table)[:3]))
    for other in got[:2]:
        assert all(np.allclose(a, b, rtol=2e-3, atol=1e-3) for a, b in zip(other, got[2], strict=True))


def test_blocks_share_their_counts(spark, docs):
    """The same texts in one block and in nine: a word of every block has one count, and the model is the same."""
    one = {r.doc_id: r for r in H.hmm_scores(docs.coalesce(1), 3).collect()}
    nine = {r.doc_id: r for r in H.hmm_scores(docs.repartition(9), 3).collect()}
    assert one.keys() == nine.keys()
    for i, a in one.items():
        b = nine[i]
        assert (a.n_tokens, a.n_known, a.train_tokens) == (b.n_tokens, b.n_known, b.train_tokens)
        assert a.base_score == pytest.approx(b.base_score) and a.score == pytest.approx(b.score, rel=1e-3)


# --- pipeline ---------------------------------------------------------------


def test_pipeline(spark, sf, docs):
    import corpus_pipeline as C

    assert [n for n, _ in C.STAGES] == ["quality_rules", "near_dedup", "secret_scan", "source_mix", "packing"]
    d = docs
    for name, stage in C.STAGES:
        out = stage(spark, d, sf).cache()
        if name != "packing":
            assert out.columns == docs.columns
            assert {r.doc_id for r in out.collect()} <= {r.doc_id for r in d.collect()}
        if name == "secret_scan":
            assert out.count() == d.count() and S.scan_secrets(out).agg(F.sum("n_hex")).first()[0] == 0
        d = out
    assert d.count() == C.run(spark, sf).count() > 0


def test_stages_on_awkward_rows(spark, sf, docs, odd, empty):
    """Nulls, blanks, repeated ids and columns with clashing names go through every stage; no row comes from nowhere."""
    import corpus_pipeline as C

    for df in (odd, empty):
        d = df
        for name, stage in C.STAGES:
            out = stage(spark, d, sf).cache()
            if name != "packing":
                assert out.columns == df.columns
            if name in ("quality_rules", "near_dedup"):
                assert out.count() <= d.count()
            if name == "secret_scan":
                assert out.count() == d.count()
            d = out
            d.count()
