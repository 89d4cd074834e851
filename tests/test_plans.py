"""Operators whose plans were made to spread hot keys: against plain versions."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from recall_engine.operators import csr, measures, sampler, verify
from recall_engine.params import Params
from recall_engine.plans import bootstrap, calibrate, ranker
from recall_engine.sources.layers import layer


def scored(spark, rows):
    return spark.createDataFrame([(str(k), float(p), int(min(9, p * 10)), bool(y)) for k, (p, y) in enumerate(rows)], "pair_id string, p double, d int, y boolean")


def test_thresholds_in_one_pass_equal_one_by_one(spark):
    rng = random.Random(2)
    x = scored(spark, [(rng.choice([0.0, 0.25, 0.5, 1.0, rng.random()]), rng.random() < 0.3) for _ in range(500)])
    taus = [(f"m{k}", t) for k, t in enumerate([0.0, 0.25, 0.25, 0.3, 0.5, 0.999, 1.0, 1.5])]
    got = {(r.method, r.tau): (r.candidates, r.relevant, r.reviewed, r.hits) for r in measures.evaluated_many(x, spark.createDataFrame(taus, "method string, tau double")).collect()}
    assert len(got) == len(taus)
    for m, t in taus:
        one = measures.evaluated(x, t).first()
        assert got[m, t] == (one.candidates, one.relevant, one.reviewed, one.hits)


@pytest.mark.parametrize("kind", ["even", "one bin", "ties", "tiny differences"])
def test_cut_score_however_scores_are_spread(spark, kind):
    rng = random.Random(3)
    p = {"even": [rng.random() for _ in range(400)], "one bin": [0.7 + rng.random() * 1e-6 for _ in range(400)], "ties": [0.5] * 300 + [0.2] * 100, "tiny differences": [0.9 + k * 2.0**-50 for k in range(400)]}[kind]
    x = scored(spark, [(v, False) for v in p])
    ranked = sorted(p, reverse=True)
    for budget in (1, 57, 300, 400):
        tau, of_tie = verify.cut_score(x, budget)
        assert tau == ranked[budget - 1] and of_tie == budget - sum(v > tau for v in p)
    assert verify.cut_score(x, 401) == (0.0, 401)


@pytest.mark.parametrize("most", [7, 1000])
def test_compressed_rows_of_a_hot_key(spark, most):
    rows = [("hot", f"t{k}") for k in range(300)] + [(f"s{k}", f"t{k % 5}") for k in range(40)]
    got = csr.build(spark.createDataFrame(rows, "s_id string, t_id string").repartition(5), most, 8)
    parts = got.collect()
    assert all(r.row_len == len(r.t_ids) <= most and r.t_ids == sorted(r.t_ids) for r in parts)
    assert sorted((r.s_id, t) for r in parts for t in r.t_ids) == sorted(rows)
    spans = sorted((r.row_offset, r.row_len) for r in parts)
    assert all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:])) and spans[0][0] == 0
    hot = sorted(r.part for r in parts if r.s_id == "hot")
    assert hot == list(range(-(-300 // most))) and sorted((r.s_id, r.t_id) for r in csr.explode(got).collect()) == sorted(rows)


def test_values_by_stratum(spark):
    got = spark.createDataFrame([(k,) for k in (-1, 0, 2, 3, 9)], "d int").select("d", sampler._by_stratum({0: 0.5, 2: 1.5, 3: 2.5}, F.col("d"), 7.0).alias("v")).collect()
    assert {r.d: r.v for r in got} == {-1: 7.0, 0: 0.5, 2: 1.5, 3: 2.5, 9: 7.0}


def test_layers_reach_the_optimiser_as_columns(spark, sf):
    plan = layer(spark, sf, "s_ord").where("x0 < x1 AND y0 < y1 AND u0 < u1")._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("o_totalprice") < 12


def test_calibrate_does_what_it_is_told_or_refuses():
    g = {0: {"p": np.linspace(1, 0, 50), "w": np.linspace(1, 2, 50), "d": np.zeros(50), "hash_key": np.arange(50)}}
    for engine in ("analytic", "hashed"):
        with pytest.raises(ValueError):
            calibrate.from_positives(g, 50, 800, "ivw_single", Params(n_boot=5), engine=engine)
    assert calibrate.from_positives(g, 50, 800, "ivw_single", Params(n_boot=5), engine="analytic", weighting="none").feasible
    # Weights that differ by less than a thousandth count too.
    near = {0: {**g[0], "w": np.linspace(1, 1.0005, 50)}}
    plain = bootstrap.thresholds(near[0]["p"], near[0]["w"], ("wilson",), 800, 0.1)["wilson"]
    assert calibrate.from_positives(near, 50, 800, "wilson_hash", Params()).tau == plain


def test_scores_of_many_networks_and_low_precision(spark):
    rng = np.random.default_rng(1)
    rows = [(str(k), *map(float, rng.random(16) * 10_000)) for k in range(50)]
    x = spark.createDataFrame(rows, "pair_id string, " + ", ".join(f"f{k:02d} double" for k in range(1, 17)))
    nets = [ranker.Network.init(seed) for seed in (1, 2, 3)]
    every = {r.pair_id: list(r.ps) for r in ranker.score_all(x, nets, batch=7).collect()}
    for j, net in enumerate(nets):
        assert {r.pair_id: r.p for r in ranker.score(x, net, batch=7).collect()} == {k: v[j] for k, v in every.items()}
    exact = {r.pair_id: r.p for r in ranker.score(x, nets[0], dtype="float64").collect()}
    gaps = {t: max(abs(r.p - exact[r.pair_id]) for r in ranker.score(x, nets[0], dtype=t).collect()) for t in ("float32", "bfloat16")}
    assert gaps["float32"] < 1e-5 < gaps["bfloat16"] < 0.05
    v = np.array([1.0, 1.00390625, 1.01171875, -3.14159, 0.0], np.float32)
    assert ranker._rounded(v, "bfloat16").tolist() == [1.0, 1.0, 1.015625, -3.140625, 0.0]


def test_targets_share_their_draws(spark):
    rows = spark.createDataFrame([(s, str(i), i / 100, 0, 1.0) for s in (0, 1) for i in range(60)], "subsample int, pair_id string, p double, d int, w double")
    both = bootstrap.hashed_replicates(rows, (700, 800), 6)
    for t in (700, 800):
        key = lambda r: (r.subsample, r.rule, r.replicate, r.rank, r.tau)
        assert sorted(map(key, both.where(F.col("target_mille") == t).collect())) == sorted(map(key, bootstrap.hashed_replicates(rows, t, 6).collect()))
