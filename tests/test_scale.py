"""Plans that hold at larger tables: kept tables, slices, shared draws, whole results."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from recall_engine.keep import kept, kept_in_slices
from recall_engine.operators import features, grid
from recall_engine.sources.layers import workload


def test_kept_tables_are_columns(spark):
    x = spark.range(1000).select("id", F.md5(F.col("id").cast("string")).alias("h"))
    y = kept(x)
    assert sorted(y.collect()) == sorted(x.collect()) and y.dtypes == x.dtypes
    plan = y.groupBy().agg(F.sum("id"))._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<id:bigint>" in plan  # only the column that is asked for is read


def test_pairs_in_slices_equal_the_whole(spark, sf, monkeypatch):
    from recall_engine import keep

    monkeypatch.setattr(keep, "SLICE_ROWS", 100)
    s, t = workload(spark, sf, "w4")
    theta = grid.cell_size(s)
    whole = grid.candidates(s, t, theta).select("s_id", "t_id", "t_u0", "s_v1", "s_c")
    parts = kept_in_slices(lambda k, n: grid.candidates(s, t, theta, part=(k, n)).select(*whole.columns), 1000)
    assert sorted(parts.collect()) == sorted(whole.collect())
    plain = {r.id: (r.c, r.u0, r.v1) for r in s.collect()}
    assert all((r.s_c, r.s_v1) == (plain[r.s_id][0], plain[r.s_id][2]) for r in parts.collect())
    with pytest.raises(ValueError):
        grid.candidates(s, t, theta, dedup="distinct", part=(0, 2))


def test_counted_pairs(spark):
    pairs = spark.createDataFrame([("a", "x"), ("a", "y"), ("b", "y")], "s_id string, t_id string")
    got = features.counted(features.counted(pairs, "s"), "t")
    assert sorted((r.s_id, r.t_id, r._ns, r._nt) for r in got.collect()) == [("a", "x", 2, 1), ("a", "y", 2, 2), ("b", "y", 1, 2)]


def test_targets_and_variants_share_resamples():
    from recall_engine.params import RULES, TARGETS
    from recall_engine.plans import bootstrap

    rng = np.random.default_rng(4)
    g = {"p": rng.random(300), "w": rng.random(300) + 0.5, "d": rng.integers(0, 3, 300)}
    shared = bootstrap.Resamples(TARGETS)
    for w in (None, g["w"]):
        for by_stratum in (False, True):
            for t in TARGETS:
                for names in (RULES, ("quantile",), ("wilson", "jeffreys")):
                    one = bootstrap.resample(g["p"], w, g["d"], 20, 5, names, t, 0.1, "standard", by_stratum)
                    got = shared.of(g, w, 20, 5, names, t, 0.1, "standard", by_stratum)
                    assert one.keys() == got.keys() and all(np.array_equal(one[r], got[r]) for r in one)
    assert len(shared.found) == 4


def test_binomial_tails_at_once():
    from recall_engine.functions import special

    for n, k in ((5, 0), (5, 6), (40, 13), (3000, 2400)):
        p = np.concatenate([[0.0, 1.0], np.linspace(0.01, 0.99, 30)])
        assert np.allclose(special.binomial_tails(n, p, k), [special.binomial_tail(n, x, k) for x in p], rtol=1e-12, atol=1e-15)


def test_sums_of_networks_are_their_scores(spark):
    from recall_engine.plans import ranker

    rng = np.random.default_rng(1)
    x = spark.createDataFrame([(str(k), *map(float, rng.random(16) * 10_000)) for k in range(50)], "pair_id string, " + ", ".join(f"f{k:02d} double" for k in range(1, 17)))
    nets = [ranker.Network.init(seed) for seed in (1, 2)]
    every = {r.pair_id: r.ps for r in ranker.score_all(x, nets, batch=7).collect()}
    sums = ranker.sums_all(x, nets, batch=7)
    assert dict(sums.dtypes)["z1"] == "float"
    for r in sums.select("pair_id", *[ranker.sigmoid(F.col(f"z{k}")).alias(f"p{k}") for k in (0, 1)]).collect():
        assert np.allclose([r.p0, r.p1], every[r.pair_id], rtol=1e-14)


def test_a_trial_draws_each_sample_once(spark, monkeypatch):
    from recall_engine.params import Params
    from recall_engine.plans import calibrate, experiment

    rows = [(str(k), k / 400, int(k / 40), k % 3 == 0) for k in range(400)]
    x = spark.createDataFrame(rows, "pair_id string, p double, d int, y boolean")
    params, drawn, draw = Params(k=100, subsamples=2, n_boot=5), [], calibrate.draw
    monkeypatch.setattr(calibrate, "draw", lambda *a, **b: drawn.append(a[1]) or draw(*a, **b))
    shared = {}
    got = [experiment.thresholds(x, "x", params, methods=("ivw_min",), shared=shared, fuse=f) for f in ("min", "median")]
    alone = [experiment.thresholds(x, "x", params, methods=("ivw_min",), fuse=f) for f in ("min", "median")]
    assert got == alone and len(drawn) == 3


def test_sessions_reach_no_driver_table(spark, sf, monkeypatch):
    import __spark_entry__ as entry
    from recall_engine.streaming import monitor

    monkeypatch.setattr(monitor, "run_to_end", lambda *a, **b: pytest.fail("a memory table"))
    got = entry.queries()["stream_sessions"](spark, sf).collect()
    events = spark.read.parquet(f"{sf}/events.parquet")
    w = F.session_window("ts", "30 minutes").alias("w")
    plain = events.groupBy("user_id", w).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "user_id", "n")
    assert sorted(got) == sorted(plain.collect()) and sum(r.n for r in got) == events.count()


def test_nested_loop_in_tiles(spark, sf):
    s, t = workload(spark, sf, "w1")
    whole = {(r.s_id, r.t_id) for r in grid.nested_loop(s, t).select("s_id", "t_id").collect()}
    for tiles in (1, 3.5, 16):
        got = [(r.s_id, r.t_id) for r in grid.nested_loop(s, t, tiles).select("s_id", "t_id").collect()]
        assert len(got) == len(whole) and set(got) == whole


def test_ranks_read_their_sizes_from_a_table(spark, sf):
    import __spark_entry__ as entry
    from recall_engine.functions import rules

    lines = spark.read.parquet(f"{sf}/lineitem.parquet")
    sizes = {r["count"] for k in ("l_orderkey", "l_partkey", "l_suppkey") for r in lines.groupBy(k).count().collect()}
    for rule in ("wilson", "quantile"):
        df = entry.queries()[f"rank_{rule}"](spark, sf)
        assert any("lineitem" in f for f in df.inputFiles())
        assert sorted(map(tuple, df.collect())) == sorted((n, t, r) for n in sizes for t in (700, 800, 900) if (r := rules.rank(rule, n, t)) is not None)


@pytest.mark.parametrize("block", [7, 40, 1000])
def test_vector_pairs_in_blocks(spark, monkeypatch, block):
    from recall_engine.operators import vector_pairs

    for name in ("COUNT_BLOCK", "ROW_BLOCK"):
        monkeypatch.setattr(vector_pairs, name, block)
    monkeypatch.setattr(vector_pairs, "TILE", 5)
    rng = np.random.default_rng(2)
    x = rng.integers(-2, 3, (60, 3)).astype(np.float32)  # scores on the edges of strata, vectors of length zero and copies
    rows = [(int(3 * k), x[k].tolist(), int(k % 4)) for k in range(60)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    score, hist = {}, {}
    for a in rows:
        for b in rows:
            if a[0] < b[0]:
                dot, na, nb = sum(u * v for u, v in zip(a[1], b[1])), sum(u * u for u in a[1]) ** 0.5, sum(v * v for v in b[1]) ** 0.5
                p = max(0.0, min(1.0, (1 + (dot / (na * nb) if na * nb else 0.0)) / 2))
                score[f"{a[0]}|{b[0]}"] = (p, a[2] == b[2])
                h = hist.setdefault(min(9, int(p * 10)), [0, 0])
                h[0], h[1] = h[0] + 1, h[1] + (a[2] == b[2])
    got = vector_pairs.scored_pairs(df).collect()
    assert len(got) == len(score) and all(abs(score[r.pair_id][0] - r.p) < 1e-12 and score[r.pair_id][1] == r.y for r in got)
    assert {r.d: [r.n, r.pos] for r in vector_pairs.score_histogram(df).collect()} == hist


def test_matrices_at_once_equal_one_by_one(spark):
    from recall_engine.functions import polygons

    rng = np.random.default_rng(6)
    shapes = [[(0, 0), (4, 0), (4, 4), (0, 4)], [(0, 0), (6, 0), (6, 6), (3, 2), (0, 6)], [(0, 0), (2, 0), (2, 0), (2, 2), (0, 2), (0, 0)], [(0, 0), (4, 0), (2, 3)], [(1, 0), (3, 0), (4, 1), (4, 3), (3, 4), (1, 4), (0, 3), (0, 1)], [(0, 0), (1, 1)], []]
    rings = [[(x * f + dx, y * f + dy) for x, y in s] for s in shapes for f in (1, 2) for dx, dy in [(0, 0), (2, 0), (4, 4), (0.5, 0.25), *rng.integers(-4, 5, (3, 2)).tolist()]]
    pairs = [(i, j) for i in range(len(rings)) for j in range(len(rings)) if (i + j) % 3 == 0]
    as_rows = lambda r: [(float(x), float(y)) for x, y in r]
    kind = "array<struct<x: double, y: double>>"
    df = spark.createDataFrame([(f"{i}|{j}", as_rows(rings[i]), as_rows(rings[j])) for i, j in pairs], f"pair_id string, s_ring {kind}, t_ring {kind}")
    got = {r.pair_id: r.matrix for r in polygons.related(df).collect()}
    assert got == {f"{i}|{j}": polygons.matrix(rings[i], rings[j]) for i, j in pairs} and len(set(got.values())) > 8


def test_trials_are_drawn_together(spark, sf):
    """All samples of all trials come from two passes, equal to those drawn one by one; each drawn sample was a table before."""
    from recall_engine.operators import sampler
    from recall_engine.params import Params
    from recall_engine.plans import experiment
    from recall_engine.queries import scored_pairs

    x = kept(scored_pairs(spark, sf, "w1", tiles=3).select("pair_id", "p", "d", "y"))
    params = Params(k=150, subsamples=3, n_boot=10)
    for options in ({}, {"quota": "equal"}, {"methods": ("exact_beta", "ht_lower")}, {"fuse": "median", "weighting": "none"}):
        alone = [r for t in range(2) for r in experiment.thresholds(x, "x", params, trials=1, first_trial=t, shared={}, **options)]
        got = experiment.thresholds(x, "x", params, trials=2, **options)
        assert sorted(got) == sorted(alone) and len(got) == len(alone)
    n = sampler.sizes(x)
    q = sampler.quotas(n, 150, "proportional")
    draw = sampler.Draw(5, False, n, q)
    chosen = sampler.sample(x, 150, 5, "proportional").where("y").collect()
    packed = sampler.taken(x, [draw], [[0]]).collect()
    rows = np.frombuffer(b"".join(r.packed for r in packed if r.draw == 0), sampler.PACKED)
    assert sorted(rows["hash_key"].tolist()) == sorted(r.hash_key for r in chosen)
    assert sum(r.pairs for r in packed if r.draw == -1) == sum(q.values()) == 150


def test_tiles_make_the_same_pairs(spark, sf):
    from recall_engine.queries import scored_pairs

    for w in ("w1", "w2"):
        one, three = (scored_pairs(spark, sf, w, tiles=k) for k in (1, 3))
        assert three.count() == one.count() and one.exceptAll(three).isEmpty()


def test_counts_come_with_the_pairs(spark, sf, monkeypatch):
    """Features of pairs made in slices, counts with them, equal those of the whole."""
    from recall_engine import keep, more_queries
    from recall_engine.functions.kdop import relate
    from recall_engine.queries import candidate_pairs

    monkeypatch.setattr(keep, "SLICE_ROWS", 2000)
    plain = features.raw(candidate_pairs(spark, sf, "w4")).select("pair_id", relate("covers").alias("y"), *features.NAMES)
    plain = features.scale(plain, features.fit_minmax(plain))
    got = more_queries.scaled_pairs(spark, sf, "w4")
    assert got.count() == plain.count() and plain.exceptAll(got).isEmpty()


def test_vector_pairs_are_not_kept(spark, monkeypatch, tmp_path):
    """Samples and recall of pairs made anew in each pass equal those of pairs that are all kept; only what samples can hold is kept."""
    import __spark_entry__ as entry
    from recall_engine import more_queries
    from recall_engine.functions import strata
    from recall_engine.operators import sampler, vector_pairs
    from recall_engine.params import Params
    from recall_engine.plans import experiment

    rng = np.random.default_rng(8)
    rows = [(k, x.tolist(), k % 4) for k, x in enumerate(rng.normal(size=(300, 8)).astype(np.float32))]
    params, sizes = Params(k=200, subsamples=3, n_boot=10), []
    for module in (experiment, more_queries):
        monkeypatch.setattr(module, "PUBLISHED", params, raising=False)
    monkeypatch.setattr(experiment, "kept", lambda df: (out := kept(df), sizes.append(out.count()))[0])

    def query(vectors):
        spark.createDataFrame(vectors, "vec_id long, embedding array<float>, label int").write.mode("overwrite").parquet(f"{tmp_path}/embeddings.parquet")
        return {r[1:3]: r for r in entry.queries()["stress_no_signal_w5"](spark, str(tmp_path)).collect()}

    got = query(rows)
    assert len(got) == 15 and len(sizes) == 1 and sizes[0] < 44_850 / 8
    x = vector_pairs.scored_pairs(spark.read.parquet(f"{tmp_path}/embeddings.parquet")).withColumn("d", strata.equal_width(F.col("p")))
    want = {r[1:3]: r for r in experiment.run_methods(spark, x, "w5", params).collect()}
    assert got.keys() == want.keys() and all(np.allclose([float(v) for v in got[k][3:]], [float(v) for v in want[k][3:]], rtol=1e-12) for k in want)
    monkeypatch.setattr(sampler, "near", lambda df, draws: df.limit(0))  # a margin that was too small: all pairs are read
    assert {k: r[4] for k, r in query(rows).items()} == {k: r[4] for k, r in got.items()}
    monkeypatch.undo()
    assert {r.candidates for r in query(rows[:2]).values()} == {1} and not any(r.feasible for r in query(rows[:1]).values())


def test_places_of_vector_pairs(spark, monkeypatch):
    from recall_engine.operators import vector_pairs

    monkeypatch.setattr(vector_pairs, "TILE", 7)
    rng = np.random.default_rng(9)
    x = spark.createDataFrame([(k, v.tolist(), k % 3) for k, v in enumerate(rng.integers(-2, 3, (50, 3)).astype(np.float32))], "vec_id long, embedding array<float>, label int")
    pairs = vector_pairs.scored_pairs(x).collect()
    values = sorted({r.p for r in pairs[::40]} | {0.0, 0.25, 0.3, 0.3 + 1e-12, 1.0})
    for some in (values, [], [0.5]):
        want = {}
        for r in pairs:
            at = want.setdefault(sum(v <= r.p for v in some), [0, 0])
            at[0], at[1] = at[0] + 1, at[1] + r.y
        assert {r.place: [r.n, r.pos] for r in vector_pairs.counts_by_place(x, some).collect()} == want
    assert {r.p: r.d for r in pairs} == {r.p: min(9, int(r.p * 10)) for r in pairs}


@pytest.mark.parametrize("name, workloads, methods", [("recall_table", 4, 5), ("plain_rules_w4", 1, 4)])
def test_tables_hold_all_trials(spark, sf, monkeypatch, name, workloads, methods):
    import __spark_entry__ as entry
    from recall_engine import more_queries
    from recall_engine.params import Params

    monkeypatch.setattr(more_queries, "PUBLISHED", Params(k=100, subsamples=2, n_boot=5))
    got = entry.queries()[name](spark, sf).where("workload IS NOT NULL AND method IS NOT NULL AND target_mille IS NOT NULL").collect()
    assert len(got) == workloads * methods * 3 and {r.runs for r in got} == {10}
    assert any(r.sd_recall > 0 for r in got)


def test_cuts_of_many_draws_in_small_batches(spark, sf):
    """The keys around the cuts of all draws travel together; the cuts are those of each draw by itself."""
    from recall_engine.operators import sampler

    x = spark.createDataFrame([(str(k), k % 3) for k in range(3000)], "pair_id string, d int").repartition(3)
    n = sampler.sizes(x)
    draws = [sampler.Draw(s, False, n, sampler.quotas(n, 90, "proportional")) for s in range(12)] + [sampler.Draw(5, True, {0: 3000}, {0: 50})]
    want = [{h: None for h in w.n} for w in draws]
    for i, w in enumerate(draws):
        for h in w.n:
            keys = sorted(r.k0 for r in sampler._keyed(x if w.plain else x.where(F.col("d") == h), [w]).collect())
            want[i][h] = keys[w.q[h] - 1]
    assert sampler.cuts(x, draws) == want
