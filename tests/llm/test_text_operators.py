"""Rules, classifier, exact and near duplicates, mixing."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from recall_engine.llm import exact_dedup, host_rules, mixing, parity_join, quadratic, textkit

from . import fixtures

W = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def brute_counts(t):
    t = t or ""
    w = W.findall(t)
    seen, dup = set(), 0
    for line in t.split("\n"):
        if W.search(line):
            dup += line in seen
            seen.add(line)
    c, marked = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2)), set()
    for i in range(len(w) - 2):
        if c[tuple(w[i : i + 3])] > 1:
            marked |= {i, i + 1, i + 2}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(marked)


def test_counts_equal_brute_force():
    texts = ["a b c a b c", "", None, "  x\n\nx\nx ", "#a *b | <c> d", "é é é é", "one", "a b a b a b a b", "\n\n", "x\x0by\x1cz"]
    got = host_rules.rule_counts(pa.array(texts))
    assert [tuple(int(got[c][i]) for c in host_rules.COUNTS) for i in range(len(texts))] == [brute_counts(t) for t in texts]


def test_words_of_texts_that_touch():
    raw, off = textkit.string_buffers(pa.array(["ab", "cd", None, " e", ""]))
    flat, bounds = textkit.words(raw, off)
    assert flat.to_pylist() == ["ab", "cd", "e"] and bounds.tolist() == [0, 1, 2, 2, 3, 3]


def test_rules_query_and_stage(spark):
    df, rows = fixtures.documents(spark)
    got = host_rules.judged(df).toPandas()
    assert len(got) == len(rows)
    expected = Counter((r[0], *brute_counts(r[1])) for r in rows)
    found = Counter(tuple(None if pd.isna(v) else int(v) for v in x) for x in got[["doc_id", *host_rules.COUNTS]].itertuples(index=False))
    assert found == expected
    bad = (got.n_words < 50) | (100 * got.n_repeat_words > 50 * got.n_words)
    assert (got.base_failed == bad).all() and not got.kept[bad].any()
    kept = host_rules.kept_documents(df)
    assert kept.columns == df.columns and kept.count() == got.kept.sum()
    assert host_rules.judged(fixtures.empty(spark)).count() == 0 == host_rules.kept_documents(fixtures.empty(spark)).count()


def test_verdicts_decide_as_plain_python_does(spark):
    """Hosts that are trusted, ordinary and rejected; documents that soft rules hit, hit at half their limits, and don't."""
    import random

    rng = random.Random(3)
    rows = []
    for host, n, bad in (("good", 400, 0.01), ("fair", 60, 0.2), ("bad", 60, 0.9), ("few", 2, 0.5), (None, 30, 0.3)):
        for k in range(n):
            text = fixtures.prose(rng, 60)
            if k < bad * n:
                text += " #" * 12 if k % 2 or host == "good" else "\nl l" * 6
            elif k % 5 == 0:
                text += " #" * 5
            rows.append((len(rows), text, host))
    rows += [(len(rows) + k, t, "bad") for k, t in enumerate(("short", None, ""))]
    df = spark.createDataFrame(rows, "doc_id long, text string, host string").repartition(4)

    def fails(t, share):
        n, chars, symbols, lines, repeated = brute_counts(t)
        soft = 100 * symbols > 10 * share * n or not (8.5 - 6.5 * share) * n <= chars <= (8.5 + 6.5 * share) * n or lines > 3 * share
        return n < 50 or 100 * repeated > 50 * n, soft

    hosts = defaultdict(list)
    for _, t, h in rows:
        hosts[h].append(any(fails(t, 1.0)))
    rates = [np.mean(f) for f in hosts.values()]
    strength = max(1.0, np.mean(rates) * (1 - np.mean(rates)) / np.var(rates, ddof=1) - 1)
    expected, decided = {}, 0
    for d, t, h in rows:
        n = len(hosts[h])
        rate = (sum(hosts[h]) + np.mean(rates) * strength) / (n + strength)
        trusted = rate + 1.645 * np.sqrt(rate * (1 - rate) / (n + strength + 1)) < 0.05
        base, soft = fails(t, 0.5 if rate > 0.5 else 1.0)
        expected[d] = not base and (not soft or (trusted and rate <= 0.5))
        decided += not base and expected[d] == any(fails(t, 1.0))
    got = host_rules.judged(df, host="host", keep=("doc_id", "host")).toPandas()
    assert dict(zip(got.doc_id, got.kept, strict=True)) == expected and list(got.columns[:2]) == ["doc_id", "host"]
    kept = host_rules.kept_documents(df, host="host")
    assert {r.doc_id for r in kept.collect()} == {d for d, k in expected.items() if k} and kept.columns == df.columns
    assert decided >= 10 and got.host_trusted.any() and got.host_rejected.any()


def test_columns_with_clashing_names(spark):
    """Columns named like the operators' own pass through."""
    df, rows = fixtures.documents(spark)
    names = ("_stays", "_copy", "_copy_of", "host", "row", "_text", "_id", "_sha", "comp", "node", "bucket", "stays", "kept", "size", "__of")
    wide = df.drop("_text", "size").withColumns({n: F.concat(F.lit(f"{n} "), F.coalesce("text", F.lit(""))) for n in names})
    for stage in (host_rules.kept_documents, exact_dedup.keep_one, parity_join.one_of_each, mixing.mixed_documents):
        out = stage(wide)
        assert out.columns == wide.columns, stage
        assert all(r[n] == f"{n} {r.text or ''}" for r in out.collect() for n in names), stage
    assert host_rules.judged(wide, keep=("doc_id", "host", "_text")).count() == len(rows)
    assert mixing.mixed(wide).count() == len(rows) == exact_dedup.deduplicated(wide).count()


def plain_statistics(t):
    t = t or ""
    nw, nc, symbols, dup, repeated = brute_counts(t)
    w = W.findall(t)
    share = lambda part, whole: np.log((part + 0.5) / (max(whole - part, 0) + 0.5))
    b = t.encode()
    lines = t.count("\n") + 1
    some = lambda lo, hi=None: sum(lo <= x <= (lo if hi is None else hi) for x in b)
    return [
        np.log1p(nw), np.log((nc + 1) / (nw + 1)), share(symbols, nc), np.log1p(dup), share(repeated, nw), share(some(65, 90), nc), share(some(48, 57), nc), share(some(33), nc),
        share(some(124), nc), share(some(46), nc), share(some(44), nc), np.log(lines), np.log((nw + 1) / lines), share(len(set(w)), nw), share(max(Counter(w).values(), default=0), nw),
        share(some(192, 255), nc), share(sum(len(x) > 12 for x in w), nw), share(some(34) + some(39), nc),
    ]


def test_classifier_equals_plain_version(spark):
    """Statistics, class covariances, both shrinkages and scores, made again with solves instead of kept factors."""
    df, rows = fixtures.documents(spark)
    rows = [(i, r[1]) for i, r in enumerate(rows)] + [(1000 + i, fixtures.prose(__import__("random").Random(i), 30 + i) + "!" * (i % 5)) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    labels = {d: d % 2 for d, _ in rows if d % 3}
    got = quadratic.scored(docs, spark.createDataFrame(list(labels.items()), "doc_id long, quality int")).toPandas().set_index("doc_id")
    x = {d: np.array(plain_statistics(t)) for d, t in rows}
    outside = lambda d: zlib.crc32(str(d).encode()) % 3 == 1
    c = {k: np.array([x[d] for d, y in labels.items() if y == k and not outside(d)]) for k in (0, 1)}
    n = {k: len(v) for k, v in c.items()}
    cov = {k: np.cov(v.T, bias=True) for k, v in c.items()}
    pooled = (n[0] * cov[0] + n[1] * cov[1]) / (n[0] + n[1])
    scale = np.sqrt(np.maximum(np.diag(pooled), 1e-9))
    logs = {}
    for k in (0, 1):
        s = (0.7 * cov[k] + 0.3 * pooled) / np.outer(scale, scale)
        s = 0.95 * s + 0.05 * np.trace(s) / len(s) * np.eye(len(s))
        logs[k] = lambda v, k=k, s=s: -0.5 * ((v - c[k].mean(0)) / scale) @ np.linalg.solve(s, (v - c[k].mean(0)) / scale) - 0.5 * np.linalg.slogdet(s)[1] + np.log(n[k])
    for d, _ in rows:
        score = 1 / (1 + np.exp(-np.clip((logs[1](x[d]) - logs[0](x[d])) / 4.0, -700, 700)))
        assert got.held_out[d] == outside(d) and abs(got.score[d] - score) < 1e-6 and got.predicted[d] == (got.score[d] >= 0.5)


def test_very_long_texts(spark):
    """A text of some megabytes beside small ones, in the operators that read texts in Python."""
    rng = np.random.default_rng(1)
    long = " ".join(f"w{k}" for k in rng.integers(0, 50_000, 400_000).tolist())
    rows = [(1, long), (2, "a b c"), (3, long[: len(long) // 2]), (4, long + " end")]
    df = spark.createDataFrame([(*r, "s") for r in rows], "doc_id long, text string, source string")
    got = host_rules.judged(df).toPandas().set_index("doc_id")
    assert [got.n_words[d] for d, _ in rows] == [len(t.split()) for _, t in rows]
    near = {r.doc_id: (r.n_shingles, r.component_id) for r in parity_join.grouped(df).collect()}
    assert near[4][1] == near[1][1] == 1 and near[3][1] == 3 and near[4][0] == near[1][0] + 1
    labels = spark.createDataFrame([(2, 0), (3, 1)], "doc_id long, quality int")
    assert quadratic.scored(df, labels).where("score between 0 and 1").count() == 4


def test_shrunk_rates(spark):
    hosts = spark.createDataFrame([("one", 1, 1), ("good", 1000, 50), ("bad", 1000, 900), ("fair", 1000, 60)], "host string, n long, failed long")
    got = {r.host: (r.host_rate, r.host_rejected) for r in host_rules.verdicts(hosts).collect()}
    assert got["bad"][1] and not got["good"][1] and got["one"][0] < 1.0 and abs(got["good"][0] - 0.05) < 0.02


def test_classifier_on_held_out_documents(spark, sf):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = quadratic.scored(docs, labels).join(labels, "doc_id").where("held_out").toPandas()
    s, y = got.score.to_numpy(), got.quality.to_numpy()
    auc = np.mean([(a > b) + 0.5 * (a == b) for a in s[y == 1] for b in s[y == 0]])
    assert auc > 0.97 and ((s >= 0) & (s <= 1)).all() and ((got.predicted == 1) == (s >= 0.5)).all()


def test_classifier_edge_cases(spark):
    df, rows = fixtures.documents(spark)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = quadratic.scored(df, none).toPandas()
    assert len(got) == len(rows) and (got.score == 0.5).all()
    assert quadratic.scored(fixtures.empty(spark), none).count() == 0
    some = spark.createDataFrame([(i, i % 2, 0) for i in range(30)] + [(3, 1, 0), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert quadratic.scored(df, some).where("score BETWEEN 0 AND 1").count() == len(rows)


@pytest.mark.parametrize("weak", [False, True])
def test_exact_dedup(spark, weak):
    df, rows = fixtures.documents(spark)
    # A weak key collides for the first seed, so the next one must be taken.
    key = (lambda b, seed: F.struct((F.octet_length(b) % (3 if seed == 1 else 1 << 40)).cast("long").alias("k1"), F.xxhash64(F.lit(seed), b).alias("k2") if seed > 1 else F.lit(0).cast("long").alias("k2"))) if weak else exact_dedup.block_key
    got = exact_dedup.deduplicated(df, block_bytes=64, buckets=8, key=key).toPandas()
    groups = defaultdict(list)
    for r in rows:
        groups[(r[1] or "").translate(LOWER)].append(r[0])
    assert len(got) == len(rows) and got.kept.sum() == len(groups)
    by_sha = {hashlib.sha256(t.encode()).hexdigest(): ids for t, ids in groups.items()}
    for x in got.itertuples():
        ids = by_sha[x.text_sha256]
        best = max((i for i in ids if i is not None), default=None)
        assert x.group_size == len(ids) and (pd.isna(x.keep_id) if best is None else x.keep_id == best)
        assert not x.kept or (pd.isna(x.doc_id) and best is None) or x.doc_id == best
    stays = exact_dedup.keep_one(df, block_bytes=64)
    assert stays.columns == df.columns and stays.count() == len(groups)
    assert exact_dedup.deduplicated(fixtures.empty(spark)).count() == 0


def sets(rows, width=5):
    out = []
    for r in rows:
        w = W.findall((r[1] or "").translate(LOWER))
        out.append(frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else []))
    return out


def brute_components(rows):
    s = sets(rows)
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if s[i] and s[j] and 100 * len(s[i] & s[j]) >= 75 * len(s[i] | s[j]):
                parent[find(i)] = find(j)
    least = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            least[find(i)] = min(least.get(find(i), r[0]), r[0])
    return Counter((r[0], len(s[i]), (least.get(find(i)) if s[i] else r[0])) for i, r in enumerate(rows))


def as_counter(frame):
    return Counter(tuple(None if pd.isna(v) else int(v) for v in x) for x in frame.itertuples(index=False))


def test_near_duplicates(spark):
    df, rows = fixtures.documents(spark)
    assert as_counter(parity_join.grouped(df).toPandas()) == brute_components(rows)
    assert parity_join.grouped(fixtures.empty(spark)).count() == 0
    stays = parity_join.one_of_each(df)
    assert stays.columns == df.columns and stays.count() < len(rows)


@pytest.mark.parametrize("blocks", [(512, 2048), (3, 5)])
def test_near_duplicates_in_chains(spark, monkeypatch, blocks):
    """Texts that link only with their neighbours, and many that share a passage without a link; buckets in one block and in many."""
    import random
    from functools import partial

    monkeypatch.setattr(parity_join, "across", partial(parity_join.across, outside=blocks[0], inside=blocks[1]))

    rng = random.Random(5)
    rows, words, k = [], fixtures.prose(rng, 150).split(), 0
    for step in range(40):
        for _ in range(3):
            words[rng.randrange(150)] = f"n{k}_{step}_{rng.randrange(9999)}"
        rows.append((k, " ".join(words)))
        k += 1
    passage = fixtures.prose(rng, 60)
    for _ in range(60):
        rows.append((k, fixtures.prose(rng, 40) + " " + passage + " " + fixtures.prose(rng, rng.choice([10, 40, 90]))))
        k += 1
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    assert as_counter(parity_join.grouped(df).toPandas()) == brute_components(rows)


@pytest.mark.parametrize("hot, chunk, rounds, named, graph", [(2, 2048, 2, 64, 1 << 20), (3, 4, 2, 1, 0), (64, 4, 1, 2, 1 << 20), (64, 2048, 0, 64, 0)])
def test_near_duplicates_in_hot_buckets(spark, monkeypatch, hot, chunk, rounds, named, graph):
    """Near copies of three texts around the threshold, with hot keys, small chunks, few named buckets, few rounds, and components by either way."""
    import random
    from functools import partial

    monkeypatch.setattr(parity_join, "HOT_KEY", hot)
    monkeypatch.setattr(parity_join, "CHUNK", chunk)
    monkeypatch.setattr(parity_join, "ROUNDS", rounds)
    monkeypatch.setattr(parity_join, "NAMED_BUCKETS", named)
    monkeypatch.setattr(parity_join, "SMALL_GRAPH", graph)
    monkeypatch.setattr(parity_join, "nearest", partial(parity_join.nearest, chunk=chunk))
    rng = random.Random(11)
    rows = []
    for family in range(3):
        words = fixtures.prose(rng, 120).split()
        for _ in range(70):
            own = list(words)
            for _ in range(rng.randrange(5)):
                own[rng.randrange(120)] = f"x{family}_{rng.randrange(10**6)}"
            rows.append((len(rows), " ".join(own)))
    rows += [(len(rows) + k, r[1]) for k, r in enumerate(rows[:20])]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert as_counter(parity_join.grouped(df).toPandas()) == brute_components(rows)


def test_nearest_gives_each_node_one_pair(spark):
    """A bucket of n nodes makes at most n pairs, and blocks repeat no pair."""
    rng = np.random.default_rng(2)
    base = np.sort(rng.integers(0, 1 << 63, 200).astype(np.uint64))
    sets = [np.unique(np.concatenate([base[10:], rng.integers(0, 1 << 63, 10).astype(np.uint64)])) for _ in range(40)]
    h, bounds = np.concatenate(sets), np.concatenate([[0], np.cumsum([len(x) for x in sets])])
    names = [bytes(x) for x in parity_join.node_ids(h, bounds)]
    assert len(set(names)) == 40 and all(len(n) == 16 for n in names)
    sk = spark.createDataFrame([(n, k, len(x), s) for k, (n, x, s) in enumerate(zip(names, sets, parity_join.bit_sketch(h, bounds), strict=True))], "node binary, short long, n_shingles long, sketch binary").withColumn("small", F.col("sketch"))
    members = spark.createDataFrame([(b, k) for b in range(5) for k in range(40)], "bucket long, short long")
    near = parity_join.nearest(members, None, sk, parity_join.large_buckets(members, 2048), parity_join.SIMILARITY, 0).collect()
    assert 20 <= len(near) <= 40 and {x for r in near for x in (bytes(r.a), bytes(r.b))} == set(names)
    every = parity_join.across(members, None, sk, parity_join.SIMILARITY, outside=7, inside=9)
    assert every.count() == 40 * 39 // 2


def test_no_pair_is_lost_by_the_parts():
    rng = np.random.default_rng(3)
    for n in (1, 2, 3, 5, 7, 8, 20, 63, 64, 65, 300, 500, 520):
        for trial in range(6):
            a = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64))
            drop = rng.integers(0, n // 4 + 1)
            more = rng.integers(0, n // 4 + 1)
            b = np.unique(np.concatenate([a[drop:], rng.integers(0, 1 << 63, more).astype(np.uint64)]))
            common = len(np.intersect1d(a, b))
            if 100 * common < 75 * (len(a) + len(b) - common):
                continue
            h, bounds = np.concatenate([a, b]), np.array([0, len(a), len(a) + len(b)])
            own, key = parity_join.part_keys(h, bounds, np.zeros(0, np.uint64), np.zeros(0, np.uint64))
            assert np.intersect1d(key[own == 0], key[own == 1]).size
            s = parity_join.bit_sketch(h, bounds)
            w = min(map(len, s))
            assert int.from_bytes((parity_join.folded(s[0], w) ^ parity_join.folded(s[1], w)).tobytes(), "little").bit_count() <= len(a) + len(b) - 2 * common


@pytest.mark.parametrize("m, n", [(3, 4), (4, 5), (6, 8), (7, 9), (9, 12)])
@pytest.mark.parametrize("parts", [1, 2])
def test_small_sets_in_few_parts_meet(m, n, parts):
    """Sets of m shingles in sets of n, all of them in one or two parts of any band."""
    rng = np.random.default_rng(4)
    none = np.zeros(0, np.uint64)
    for _ in range(200):
        b = np.unique((rng.integers(0, 1 << 48, n) | (rng.integers(0, parts, n) << 62)).astype(np.uint64))
        a = np.sort(rng.permutation(b)[:m])
        often = np.sort(rng.permutation(b)[:2])
        for frequent, level in ((none, none), (often, np.array([5, 9], np.uint64))):
            own, key = parity_join.part_keys(np.concatenate([a, b]), np.array([0, m, m + n]), frequent, level)
            assert np.intersect1d(key[own == 0], key[own == 1]).size


def test_near_duplicates_of_few_words(spark):
    """Texts of 8 words whose four shingles fall into one of 16 parts, each with its first seven words: 3 of 4 shingles."""
    texts = [" ".join(f"v{(k * 8 + j) * 7919 % 1000003}" for j in range(8)) for k in range(60_000)]
    h, bounds = parity_join.shingles(pa.array(texts), 5)
    part = (h >> np.uint64(60)).astype(int)
    one = [k for k in range(len(texts)) if bounds[k + 1] - bounds[k] == 4 and len(set(part[bounds[k] : bounds[k + 1]])) == 1]
    assert len(one) >= 5
    rows = [(2 * i + j, t) for i, k in enumerate(one) for j, t in enumerate((texts[k], texts[k].rsplit(" ", 1)[0]))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = parity_join.grouped(df).toPandas()
    assert as_counter(got) == brute_components(rows) and got.component_id.nunique() == len(one)


def test_mixing(spark):
    df, rows = fixtures.documents(spark)
    one = mixing.mixed(df, block_tokens=16).toPandas()
    two = mixing.mixed(df.repartition(5), block_tokens=16).toPandas()
    cols = ["doc_id", "size", "source_size", "target", "taken"]
    key = lambda f: sorted(map(str, f[cols].itertuples(index=False)))
    assert key(one) == key(two) and len(one) == len(rows)
    assert (one.taken <= 2 * one["size"]).all()
    sizes = Counter()
    for r in rows:
        sizes[r[3]] += len(W.findall(r[1] or ""))
    order = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    target, open_ = {}, set(order)
    left = 1.5 * sum(sizes.values())
    while True:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > 2 * sizes[s]]
        if not over:
            target |= {s: left * weight[s] / total for s in open_}
            break
        for s in over:
            target[s] = 2 * sizes[s]
            left -= target[s]
            open_.discard(s)
    for s, g in one.groupby(one.source.map(lambda v: v if isinstance(v, str) else "\0null")):
        s = None if s == "\0null" else s
        assert g.source_size.iloc[0] == sizes[s] and abs(g.target.iloc[0] - target[s]) < 1e-6 * max(1, target[s])
        assert abs(g.taken.sum() - target[s]) <= max(17, 0.02 * target[s])
    assert mixing.mixed(fixtures.empty(spark)).count() == 0
    mixed = mixing.mixed_documents(df, block_tokens=16)
    assert mixed.columns == df.columns and mixed.count() > 0


def test_schedule_is_spread_evenly(spark):
    t = spark.createDataFrame([("a", 8000.0), ("b", 4000.0), (None, 2000.0)], "source string, target double")
    got = mixing.schedule(t, 10).orderBy("slot").toPandas()
    assert got.groupby(got.source.fillna("-"))["tokens"].sum().to_dict() == {"a": 8000, "b": 4000, "-": 2000}
    first = got[got.slot < 700].source.value_counts()
    assert abs(first["a"] - 400) <= 4 and abs(first["b"] - 200) <= 4


def test_narrow_sources_get_their_whole_target(spark):
    """Sources of 60 to 400 words at 24 places beside 10^8 words, and one narrower than a point."""
    quota = {}
    for k in range(24):
        quota[f"s{k:02d}a"], quota[f"s{k:02d}b"] = 4_000_000 + 7919 * k, (60, 100, 200, 400)[k % 4]
    t = spark.createDataFrame([(s, float(n)) for s, n in quota.items()], "source string, target double")
    got = mixing.schedule(t).toPandas()
    assert got.groupby("source")["tokens"].sum().to_dict() == quota
    assert got.slot.is_unique and (got.tokens > 0).all() and (got.groupby("source")["rank"].max() + 1 == got.groupby("source")["rank"].nunique()).all()
    wide = spark.createDataFrame([("a", 2e10), ("b", 1.0), ("c", 2e10)], "source string, target double")
    got = mixing.schedule(wide, 100_000).groupBy("source").agg(F.sum("tokens").alias("n")).collect()
    assert {r.source: r.n for r in got} == {"a": 20_000_000_000, "b": 1, "c": 20_000_000_000}
