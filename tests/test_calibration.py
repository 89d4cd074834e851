"""Keys, samples, rules, bootstrap, fusion, review, measures, ranker, streams."""

import math

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from recall_engine import sql
from recall_engine.functions import hashing, rules, special, strata
from recall_engine.operators import features, measures, sampler, verify
from recall_engine.params import Params
from recall_engine.plans import bootstrap, calibrate, ensemble, experiment, inverse_prob, ranker
from recall_engine.queries import scored_pairs
from recall_engine.streaming import monitor

RULES = ("exact_beta", "jeffreys", "wilson", "quantile")


@pytest.fixture(scope="module")
def w4(spark):
    return scored_pairs(spark, "/root/testdata/sf0.01", "w4").cache()


def test_hash_vectors(spark):
    vectors = {(0, 0): "5a6b1816035e2b3e", (1, 9): "cc2b136268c31312", (123456, 5): "9fcf2fb13e6cd561"}
    for (i, d), want in vectors.items():
        got = spark.range(1).select(hashing.concatenated(F.lit(i), F.lit(d)).alias("h")).first().h
        assert f"{got & (2**64 - 1):016x}" == want == xxhash.xxh64_hexdigest(i.to_bytes(8, "big") + bytes([d]), seed=42)
    chain = {(0, 0): "21fe5259fd550193", (1, 9): "d7660a235b3dbd92", (123456, 5): "487c6501c26a8967", (-7, 3): "4a2aab2cceb4e1be"}
    for (i, d), want in chain.items():
        got = spark.range(1).select(F.xxhash64(F.lit(2025).cast("long"), F.lit(i).cast("long"), F.lit(d).cast("int")).alias("h")).first().h
        assert f"{got & (2**64 - 1):016x}" == want


def test_strata(spark):
    got = spark.createDataFrame([(0.0,), (0.0999,), (0.1,), (0.95,), (1.0,)], "p double").select(strata.equal_width(F.col("p")).alias("d")).collect()
    assert [r.d for r in got] == [0, 0, 1, 9, 9]
    e = strata.dynamic_edges(0.7)
    assert all(a < b for a, b in zip(e, e[1:])) and max(np.diff([0, *e, 1])) > 0.15


@pytest.mark.parametrize("quota", ["equal", "proportional", "global"])
@pytest.mark.parametrize("family", ["xxhash64", "md5"])
def test_samples_do_not_depend_on_partitions(spark, w4, quota, family):
    one = {r.pair_id for r in sampler.sample(w4, 1000, 5, quota, family).collect()}
    two = {r.pair_id for r in sampler.sample(w4.repartition(23).orderBy(F.rand(1)), 1000, 5, quota, family).collect()}
    assert one == two and len(one) == 1000
    if quota == "global":
        return
    s = sampler.sample(w4, 1000, 5, quota, family)
    n = sampler.sizes(w4)
    assert {r.d: r["count"] for r in s.groupBy("d").count().collect()} == {h: q for h, q in sampler.quotas(n, 1000, quota).items() if q}
    assert abs(s.agg(F.sum("w")).first()[0] - sum(n.values())) < 1e-6 * sum(n.values())
    if quota == "equal":
        assert one <= {r.pair_id for r in sampler.sample(w4, 2000, 5, quota, family).collect()}


def test_global_is_not_stratified(w4):
    n = sampler.sizes(w4)
    s = {r.d: r["count"] for r in sampler.sample(w4, 1000, 5, "global").groupBy("d").count().collect()}
    assert s != sampler.quotas(n, 1000, "proportional")


def test_quotas():
    n = {0: 5, 1: 100, 2: 1000}
    assert sampler.quotas(n, 300, "equal") == {0: 5, 1: 100, 2: 100} and sum(sampler.quotas(n, 300, "equal", True).values()) == 300
    assert sum(sampler.quotas(n, 300, "proportional").values()) == 300
    assert sampler.quotas(n, 110, "neyman", sigma={0: 0.0, 1: 1.0, 2: 0.0})[1] == 100


def test_subsamples(w4):
    split = sampler.subsamples(w4, 3, 300, 5, "split")
    assert split.select("pair_id").distinct().count() == split.count() == 900
    again = sampler.subsamples(w4, 3, 300, 5)
    assert {r["count"] for r in again.groupBy("subsample").count().collect()} == {300}
    alone = {r.pair_id for r in sampler.sample(w4, 300, 6, "proportional").collect()}
    assert {r.pair_id for r in again.where("subsample = 1").collect()} == alone


RANKS = {(10, 700): (10, 9, 9, 8), (22, 900): (22, 22, 22, 20), (50, 800): (45, 44, 44, 41), (200, 900): (186, 186, 186, 181), (1000, 700): (720, 719, 719, 701), (16000, 900): (14450, 14449, 14449, 14401), (16000, 800): (12866, 12865, 12865, 12801)}


def test_rank_table():
    for (n, target), want in RANKS.items():
        assert tuple(rules.rank(r, n, target) for r in RULES) == want
    assert [rules.rank(r, 10, 900) for r in RULES] == [None, None, None, 10]
    assert rules.rank("wilson", 16000, 900, form="printed") == 15913
    assert rules.rank("quantile", 0, 900) is None


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 400), st.sampled_from([500, 700, 800, 900, 950]))
def test_ranks_are_the_smallest(n, target):
    for rule in ("exact_beta", "jeffreys", "wilson"):
        k = rules.rank(rule, n, target)
        if k is None:
            assert not rules.reaches(rule, n, n, target / 1000)
        else:
            assert rules.lower_bound(rule, k, n) >= target / 1000 - 1e-9 and (k == 1 or not rules.reaches(rule, k - 1, n, target / 1000))
    exact, jeff = rules.rank("exact_beta", n, target), rules.rank("jeffreys", n, target)
    assert exact is None or (jeff is not None and exact >= jeff)


def test_special_functions():
    assert math.isclose(special.student_quantile(0.95, 8), 1.8595480375, rel_tol=1e-9)
    assert math.isclose(special.betainc(2, 3, 0.4), 0.5248, rel_tol=1e-12)
    direct = sum(math.comb(50, k) * 0.8**k * 0.2 ** (50 - k) for k in range(45, 51))
    assert math.isclose(special.binomial_tail(50, 0.8, 45), direct, rel_tol=1e-10)
    assert math.isclose(special.betainc(44.5, 6.5, 0.8), 0.0720, abs_tol=1e-4) and math.isclose(special.betainc(43.5, 7.5, 0.8), 0.1428, abs_tol=1e-4)


def test_exact_bound_keeps_its_promise():
    rng = np.random.default_rng(4)
    n, target, missed = 200, 0.8, 0
    k = rules.rank("exact_beta", n, 800)
    for _ in range(2000):
        u = np.sort(rng.random(n))[::-1]  # scores of positives; recall at threshold t is 1 - t
        missed += 1 - u[k - 1] < target
    assert missed / 2000 <= 0.10 + 3 * math.sqrt(0.09 / 2000)


def test_weighted_rules_reduce_to_plain_ones():
    p = np.random.default_rng(2).random(500)
    plain = bootstrap.thresholds(p, None, RULES, 800, 0.1)
    assert bootstrap.thresholds(p, np.full(500, 3.0), RULES, 800, 0.1) == plain


def test_bootstrap_engines_agree(spark):
    p = np.random.default_rng(3).random(300)
    got = bootstrap.resample(p, None, None, 4000, 1, RULES, 900, 0.1)
    for rule, (m, v) in bootstrap.analytic(p, RULES, 900, 0.1).items():
        assert abs(got[rule].mean() - m) < 4 * math.sqrt(v / 4000) and abs(got[rule].std() - math.sqrt(v)) < 0.1 * math.sqrt(v)
    rows = spark.createDataFrame([(0, str(i), float(x), 0, 1.0) for i, x in enumerate(p[:60])], "subsample int, pair_id string, p double, d int, w double")
    hashed = {r.rule: r for r in ensemble.moments(bootstrap.hashed_replicates(rows, 800, 40)).collect()}
    for rule, (m, v) in bootstrap.analytic(p[:60], RULES, 800, 0.1).items():
        assert abs(hashed[rule].mean_tau - m) < 5 * math.sqrt(v / 40)
    table = bootstrap.replicates(rows, 800, 10)
    assert table.count() == 40 and table.where("tau IS NULL").count() == 0


def test_fusion(spark):
    taus = [0.50 + 0.02 * k for k in range(9)]
    assert [round(ensemble.fuse(taus, h), 6) for h in ("min", "median", "mean")] == [0.50, 0.58, 0.58]
    lo, hi = ensemble.student_interval(taus, 0.58, center="mean")
    assert math.isclose(hi - 0.58, 1.8595480375 * np.std(taus, ddof=1) / 3, rel_tol=1e-9) and lo < 0.58
    m = spark.createDataFrame([(0, r, 0.5, 0.0, 9) for r in RULES] + [(1, "a", 0.4, 1.0, 9), (1, "b", 0.6, 3.0, 9)], "subsample int, rule string, mean_tau double, var_tau double, replicates long")
    w = {(r.subsample, r.rule): r.weight for r in ensemble.weights(m).collect()}
    assert all(math.isclose(w[0, r], 0.25) for r in RULES) and math.isclose(w[1, "a"], 0.75)
    assert {r.subsample: round(r.tau_ens, 9) for r in ensemble.ivw(m).collect()} == {0: 0.5, 1: 0.45}
    x = {"a": np.random.default_rng(1).normal(0.5, 0.1, 200), "b": np.random.default_rng(2).normal(0.5, 0.01, 200)}
    assert abs(ensemble.gls(x) - x["b"].mean()) < 0.01


SMALL = Params(pool=1000, labels=200, k=4000, subsamples=3, n_boot=40)


def test_quantile_rule_hits_the_target(w4):
    errors = []
    for trial in range(5):
        r = calibrate.calibrate(w4, F.col("y"), 800, method="quantile", params=SMALL, trial=trial)
        errors.append(measures.evaluated(w4, r.tau).first().recall - 0.8)
    assert abs(np.mean(errors)) <= max(0.01, 3 * np.std(errors, ddof=1) / math.sqrt(5) + 1e-3)


def test_equal_quotas_need_weights(w4):
    """Unweighted equal quotas miss the target; design weights bring it back."""
    plain = calibrate.calibrate(w4, F.col("y"), 700, method="ivw_single", params=SMALL, quota="equal", weighting="none", rules=("quantile",))
    design = calibrate.calibrate(w4, F.col("y"), 700, method="ivw_single", params=SMALL, quota="equal", rules=("quantile",))
    a, b = (measures.evaluated(w4, r.tau).first().recall for r in (plain, design))
    assert abs(b - 0.7) < 0.035 < abs(a - 0.7)


def test_methods_and_trials(spark, w4):
    rows = experiment.run_methods(spark, w4, "w4", SMALL, trials=2).toPandas()
    assert len(rows) == 5 * 3 * 2 and (rows.abs_error < 0.06).all()
    m = rows[rows.method == "ivw_min"]
    assert (m.ci_low <= m.tau).all() and (m.tau <= m.ci_high).all() and (m.label_cost > rows[rows.method == "ivw_single"].label_cost.max()).all()
    summary = measures.recall_summary(experiment.runs(spark, w4, experiment.thresholds(w4, "w4", SMALL, methods=("wilson_hash",), trials=2)))
    assert summary.where("workload IS NULL AND method IS NULL AND target_mille IS NULL").count() == 1
    again = calibrate.calibrate(w4.repartition(9), F.col("y"), 800, params=SMALL)
    assert again.tau == calibrate.calibrate(w4, F.col("y"), 800, params=SMALL).tau


def test_no_positives_and_ties(spark):
    rows = [(str(i), 0.5, 5, i % 4 == 0) for i in range(100)]
    x = spark.createDataFrame(rows, "pair_id string, p double, d int, y boolean")
    none = calibrate.calibrate(x, F.lit(False), 800, params=Params(k=50, subsamples=3, n_boot=10))
    assert none.tau == 0.0 and not none.feasible
    tied = calibrate.calibrate(x, F.col("y"), 800, params=Params(k=80, subsamples=3, n_boot=10))
    assert abs(tied.tau - 0.5) < 1e-9
    kept = verify.split_at_recall(x, 0.5, 0.8, hashing.key(F.col("pair_id"), F.col("d"), 1))
    assert 60 <= kept.count() <= 95


def test_inverse_probability_bound():
    p = np.linspace(1, 0.001, 1000)
    tau = inverse_prob.threshold(p, np.ones(1000), 800)
    kept = (p >= tau).mean()
    assert 0.8 + 1.28 * math.sqrt(0.16 / 1000) - 0.002 <= kept <= 0.8 + 1.28 * math.sqrt(0.16 / 1000) + 0.002
    assert inverse_prob.threshold(np.zeros(0), np.zeros(0), 800) is None


def test_review_within_budget(w4):
    x = w4.withColumn("hash_key", F.xxhash64("pair_id"))
    n = x.where("p >= 0.4").count()
    for budget in (1, 777, n, n + 5):
        got = verify.review(x, 0.4, budget, "split")
        assert got.count() == min(n, budget)
        best = x.orderBy(F.desc("p")).limit(min(n, budget)).agg(F.min("p")).first()[0]
        assert got.agg(F.min("p")).first()[0] == best
        assert verify.review(x, 0.4, budget).count() <= budget
    assert verify.review(x, 0.4).count() == n


def test_measures(w4):
    total, pos = w4.count(), w4.where("y").count()
    ideal = measures.ideal_threshold(w4, 800)
    at = measures.evaluated(w4, ideal["tau"]).first()
    assert at.recall >= 0.8 and at.candidates == total and at.relevant == pos and at.reviewed == ideal["reviewed"]
    curve = measures.recall_curve(w4).orderBy("bin").collect()
    assert all(a.recall >= b.recall for a, b in zip(curve, curve[1:])) and curve[0].recall == 1.0
    assert math.isclose(measures.variance_bound(250_000, 0.05), 1e-7) and measures.state_bytes(9, 16_000, 4, 200) == 8 * (144_000 + 7_200)
    t = measures.StageTimer()
    with t.stage("a", 10):
        pass
    assert t.table()[0]["share"] == 1.0


def test_features(spark, sf):
    from recall_engine.operators import grid
    from recall_engine.sources.layers import workload

    x = features.raw(grid.candidates(*workload(spark, sf, "w4")))
    scaled = features.scale(x, features.fit_minmax(x))
    ends = scaled.agg(*[F.min(n).alias(f"{n}_lo") for n in features.NAMES], *[F.max(n).alias(f"{n}_hi") for n in features.NAMES]).first()
    for n in features.NAMES[:-1]:
        assert abs(ends[f"{n}_lo"]) < 1e-6 and abs(ends[f"{n}_hi"] - 10_000) < 1e-6
    assert ends["f16_hi"] == 0.0


def test_network_gradients_and_folding():
    rng = np.random.default_rng(0)
    x, y = rng.random((32, 16)), (rng.random(32) > 0.5).astype(float)
    net = ranker.Network.init(1)
    # With one seed the dropout masks repeat, so differences of the loss are gradients.
    p, memory = net.copy().forward(x, np.random.default_rng(9))
    g = net.backward(p, y, memory)
    for name, k, at in (("w", 0, (3, 5)), ("w", 1, (7, 2)), ("w", 2, (4, 0)), ("b", 2, (0,)), ("gamma", 0, (6,)), ("beta", 1, (3,))):
        sides = []
        for step in (1e-6, -1e-6):
            other = net.copy()
            getattr(other, name)[k][at] += step
            sides.append(ranker.cross_entropy(other.forward(x, np.random.default_rng(9))[0], y))
        assert math.isclose((sides[0] - sides[1]) / 2e-6, g[name][k][at], rel_tol=2e-3, abs_tol=1e-7)
    y2 = (x[:, 0] + x[:, 1] > 1).astype(float)
    fitted = ranker.fit(np.tile(x, (20, 1)), np.tile(y2, 20), seed=3)
    assert all((a == b).all() for a, b in zip(fitted.w, ranker.fit(np.tile(x, (20, 1)), np.tile(y2, 20), seed=3).w))
    w, b = fitted.folded()
    h = x
    for k in range(2):
        h = np.maximum(h @ w[k] + b[k], 0)
    assert np.allclose(1 / (1 + np.exp(-(h @ w[2] + b[2])[:, 0])), fitted.forward(x)[0])
    assert ((fitted.forward(x)[0] > 0.5) == y2).mean() > 0.85


def test_learned_score_on_w4(spark):
    from recall_engine import more_queries

    got = more_queries.network_scored(spark, "/root/testdata/sf0.01").select("p", "y").toPandas()
    order = got.p.rank()
    pos = got.y.sum()
    auc = (order[got.y].sum() - pos * (pos + 1) / 2) / (pos * (len(got) - pos))
    assert auc > 0.97 and got.p.between(0, 1).all()


def test_stream_sample_equals_batch(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet").withColumn("p", F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("value") / 500.0)))
    d = strata.equal_width(F.col("p"))
    batch = events.select("event_id", d.alias("d"), hashing.key(F.col("event_id"), d, 2026).alias("h"))
    expected = {}
    for r in batch.collect():
        expected.setdefault(r.d, []).append((r.h, r.event_id))
    updates = monitor.run_to_end(monitor.bottom_k(monitor.replay(spark, sf), 20, 2026), "t_bottom_k")
    got = {}
    for r in updates.distinct().collect():
        got.setdefault(r.d, []).append((r.hash_key, r.event_id))
    assert {k: sorted(v)[:20] for k, v in got.items()} == {k: sorted(v)[:20] for k, v in expected.items()}


def test_sql_surface(spark, sf, w4):
    sql.register(spark)
    assert spark.sql("SELECT rank_for('exact_beta', 50, 800, 0.1) AS r").first().r == 45
    curve = spark.sql("SELECT * FROM recall_curve_of(array(0.9D, 0.5D, 0.7D), array(true, true, false))").collect()
    assert [(r.rank, r.tau, r.recall) for r in curve] == [(1, 0.9, 0.5), (2, 0.5, 1.0)]
    sql.views(spark, sf)
    assert spark.table("scored").count() == 4694
    w4.createOrReplaceTempView("w4_scored")
    row = sql.calibrate(spark, "w4_scored", "p", "y", 800, params=SMALL).first()
    assert row.feasible and 0 < row.tau < 1


def test_entry_and_registry(spark):
    import __spark_entry__ as entry

    names = entry.queries()
    assert set(entry.oracle_sql()) <= set(names)
    assert entry.entry(spark).count() == 15


def test_parameters_do_not_depend_on_the_folders_name(spark, sf, tmp_path):
    import __spark_entry__ as entry

    (tmp_path / "other").symlink_to(sf)
    gate = entry.queries()["variant_gate"]
    assert gate(spark, sf).collect() == gate(spark, str(tmp_path / "other")).collect()


def test_trials_over_the_networks_initialisation(spark, sf):
    import __spark_entry__ as entry

    got = entry.queries()["recall_table_network_w4"](spark, sf, trials=2).where("workload IS NOT NULL AND method IS NOT NULL AND target_mille IS NOT NULL").collect()
    assert len(got) == 15 and all(r.runs == 2 and r.sd_recall is not None for r in got) and any(r.sd_recall > 0 for r in got)
