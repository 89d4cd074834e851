"""Queries without an SQL form: the learned ranker, general polygons, experiments over trials, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import polygons, strata
from .functions.kdop import relate
from .keep import kept, kept_in_slices
from .operators import features, grid, measures, sampler, vector_pairs, verify
from .params import METHODS, PUBLISHED, TARGETS, TRIALS, Params
from .plans import calibrate, experiment, objective, ranker, stages
from .queries import RELEVANT, candidate_pairs, labelled_documents, register, scored_pairs
from .sources.layers import BOX, ring, workload
from .streaming import monitor


#: Cells each way of the tiles in which the boxes of the large joins meet.
TILES = 3


def scaled_pairs(spark: SparkSession, sf_dir: str, w: str) -> DataFrame:
    """pair_id, y and the scaled features. Pairs are made twice, in slices: for the counts of the rows of S, which are few, and to be kept,
    once, with their ids, boxes and counts; features are computed from them whenever they are read."""
    s, t = workload(spark, sf_dir, w)
    rows, far_x, far_y = t.agg(F.count("*"), F.max(F.col("x1") - F.col("x0")), F.max(F.col("y1") - F.col("y0"))).first()
    theta, reach = grid.cell_size(s), (far_x or 0, far_y or 0)

    def ids(k: int, n: int) -> DataFrame:
        """The rows of S that the slice's pairs hold; one may be in several slices."""
        return grid.candidates(s, t, theta, part=(k, n), tiles=TILES).groupBy("s_id").agg(F.count("*").alias("n"))

    per = kept_in_slices(ids, rows).groupBy(F.col("s_id").alias("id")).agg(F.sum("n").alias("_ns"))
    counted = kept(s.select("id", *BOX).join(per, "id"))
    columns = ["s_id", "t_id", *[f"{a}_{c}" for a in "st" for c in BOX], "shared_cells", "_ns", "_nt"]
    x = kept_in_slices(lambda k, n: grid.counted(counted, t, theta, reach, TILES, (k, n)).select(*columns), rows)
    x = features.raw(grid.octagons(x)).select(grid.pair_id().alias("pair_id"), relate(RELEVANT).alias("y"), *features.NAMES)
    return features.scale(x, features.fit_minmax(x))


def network_scored(spark: SparkSession, sf_dir: str, w: str = "w4", net_seed: int = 42) -> DataFrame:
    """pair_id, p, d, y with the learned score; pairs are labelled as the balanced set asks."""
    x = scaled_pairs(spark, sf_dir, w)
    params = PUBLISHED.at_most(x.count())
    net, _ = ranker.learned(x, F.col("y"), params.pool, params.labels, params.base_seed, net_seed)
    return ranker.score(x, net, ("pair_id", "y"), batch=params.batch).withColumn("d", strata.equal_width(F.col("p"))).select("pair_id", "p", "d", "y")


def network_trials(spark: SparkSession, sf_dir: str, w: str, trials: int = TRIALS) -> DataFrame:
    """The runs of all methods under the learned score, over trials that differ in the network's initialisation alone: the labelled
    set, samples' seeds and bootstraps are the same in each. All networks score the pairs in one pass, and their last sums are kept,
    of 32 bits as they are computed, in a column each; a trial reads its own."""
    x = scaled_pairs(spark, sf_dir, w)
    params = PUBLISHED.at_most(x.count())
    features_, y, _ = ranker.balanced(x, F.col("y"), params.pool, params.labels // 2, params.labels // 2, params.base_seed)
    nets = [ranker.fit(features_, y, PUBLISHED.net_seed + trial) for trial in range(trials)]
    scored = kept(ranker.sums_all(x, nets, ("pair_id", "y"), batch=params.batch))
    del x  # the features' files can go
    out = None
    for trial in range(trials):
        one = scored.select("pair_id", ranker.sigmoid(F.col(f"z{trial}")).alias("p"), "y").withColumn("d", strata.equal_width(F.col("p")))
        runs = experiment.run_methods(spark, one, w, PUBLISHED, keep=False).withColumn("trial", F.lit(trial))
        out = runs if out is None else out.unionByName(runs)
    return out


@register("score_network_w4")
def score_network_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network_scored(spark, sf_dir)


@register("flagship_network_w4")
def flagship_network_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole pipeline with the learned score: all methods and targets."""
    return experiment.run_methods(spark, network_scored(spark, sf_dir), "w4", PUBLISHED)


for _kind in ("logistic", "perceptron"):

    @register(f"score_mllib_{_kind}_w1")
    def score_mllib(spark: SparkSession, sf_dir: str, kind: str = _kind) -> DataFrame:
        x = scaled_pairs(spark, sf_dir, "w1")
        return ranker.mllib_scores(x, F.col("y"), PUBLISHED.at_most(x.count()).pool, 2025, kind)


@register("relate_general")
def relate_general(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nine-cell matrix of the general path beside the interval path, on all candidates of W1."""
    pairs = candidate_pairs(spark, sf_dir, "w1").withColumns({"s_ring": ring("s_"), "t_ring": ring("t_"), "fast_covers": relate("covers"), "fast_touches": relate("touches")})
    x = polygons.related(pairs.select("pair_id", "fast_covers", "fast_touches", "s_ring", "t_ring"))
    return x.withColumn("covers", F.col("matrix").rlike("^(T|2).....FF|^.(T|1)....FF|^...(T|1)..FF|^....(T|0|1).FF"))


def _table(spark: SparkSession, sf_dir: str, names: tuple[str, ...], trials: int = TRIALS, **options) -> DataFrame:
    """All trials of the experiment on each workload."""
    return experiment.recall_table(spark, {w: scored_pairs(spark, sf_dir, w, tiles=TILES) for w in names}, PUBLISHED, trials, **options)


register("recall_table")(lambda spark, sf_dir: _table(spark, sf_dir, ("w1", "w2", "w3", "w4")))
register("plain_rules_w4")(lambda spark, sf_dir: _table(spark, sf_dir, ("w4",), methods=("exact_beta", "jeffreys", "wilson", "quantile")))


for _w in ("w1", "w2", "w3", "w4"):

    @register(f"recall_table_network_{_w}")
    def recall_table_network(spark: SparkSession, sf_dir: str, trials: int = TRIALS, w: str = _w) -> DataFrame:
        """Mean, spread, bias and cost of each method and target over the initialisations of the learned score."""
        return measures.recall_summary(network_trials(spark, sf_dir, w, trials))


@register("score_precision_drift_w4")
def score_precision_drift_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far scores in 32-bit and in brain floats of 16 bits are from those in 64-bit, and how many pairs change their stratum."""
    x = scaled_pairs(spark, sf_dir, "w4")
    net, _ = ranker.learned(x, F.col("y"), PUBLISHED.at_most(x.count()).pool, PUBLISHED.labels, PUBLISHED.base_seed)
    exact = ranker.score(x, net, dtype="float64")
    out = None
    for dtype in ("float32", "bfloat16"):
        both = exact.join(ranker.score(x, net, dtype=dtype).withColumnRenamed("p", "q"), "pair_id")
        gap = F.abs(F.col("p") - F.col("q"))
        row = both.agg(F.max(gap).alias("max_drift"), F.avg(gap).alias("mean_drift"), F.avg((strata.equal_width(F.col("p")) != strata.equal_width(F.col("q"))).cast("double")).alias("share_moved")).withColumn("dtype", F.lit(dtype))
        out = row if out is None else out.unionByName(row)
    return out


@register("ablation_equal_labels_w4")
def ablation_equal_labels_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One sample of nine k labels against nine samples of k: the same cost on either side."""
    pairs = kept(scored_pairs(spark, sf_dir, "w4"))
    k = max(1, PUBLISHED.at_most(pairs.count()).k // (2 * PUBLISHED.subsamples))
    one, nine = (Params(**{**PUBLISHED.__dict__, "k": n}) for n in (k * PUBLISHED.subsamples, k))
    rows = []
    for label, method, params in (("one_of_9k", "ivw_single", one), ("min_of_nine", "ivw_min", nine)):
        rows += [("w4", label, *r[2:]) for r in experiment.thresholds(pairs, "w4", params, methods=(method,), trials=4)]
    return measures.recall_summary(experiment.runs(spark, pairs, rows))


@register("stage_table_w4")
def stage_table_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds, share and pairs per second of each stage of the flagship workload."""
    timer, _ = stages.timed(spark, sf_dir)
    return spark.createDataFrame([(r["stage"], float(r["seconds"]), float(r["share"]), float(r["rows_per_s"])) for r in timer.table()], "stage string, seconds double, share double, rows_per_s double")


@register("ablation_sampling")
def ablation_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wilson on a random and on a hashed sample: spread of recall and their ratio."""
    table = _table(spark, sf_dir, ("w4",), methods=("wilson_random", "wilson_hash"))
    return measures.spread_ratio(table.where("workload IS NOT NULL AND method IS NOT NULL AND target_mille IS NOT NULL"), "wilson_hash", "wilson_random")


def _variants(spark: SparkSession, sf_dir: str, variants: dict[str, dict], trials: int = 4, w: str = "w4") -> DataFrame:
    """Named variants of one method in one table; the label replaces the method's name."""
    pairs = kept(scored_pairs(spark, sf_dir, w))
    n = sampler.sizes(pairs)
    rows = []
    for trial in range(trials):
        shared: dict = {}  # the samples and resamples of a trial serve all variants
        for label, options in variants.items():
            own = {"params": PUBLISHED} | options
            rows += [(w, label, *r[2:]) for r in experiment.thresholds(pairs, w, own.pop("params"), trials=1, first_trial=trial, n=n, shared=shared, **own)]
    return measures.recall_summary(experiment.runs(spark, pairs, rows))


@register("ablation_ensemble")
def ablation_ensemble(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One subsample against several, min, median and mean, bounds alone, quantile alone, and few bootstraps."""
    p = PUBLISHED
    few = Params(**{**p.__dict__, "n_boot": 20})
    return _variants(spark, sf_dir, {
        "single": {"methods": ("ivw_single",)}, "min": {"methods": ("ivw_min",)}, "median": {"methods": ("ivw_min",), "fuse": "median"}, "mean": {"methods": ("ivw_min",), "fuse": "mean"},
        "bounds": {"methods": ("ivw_min",), "rules": ("exact_beta", "jeffreys", "wilson")}, "quantile": {"methods": ("ivw_min",), "rules": ("quantile",)},
        "few_boot": {"methods": ("ivw_min",), "params": few}, "split": {"methods": ("ivw_min",), "mode": "split"}, "full_cov": {"methods": ("ivw_min",), "fusion_cov": "full"}, "analytic": {"methods": ("ivw_min",), "engine": "analytic", "weighting": "none"},
    })


@register("ablation_weights")
def ablation_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equal quotas with and without design weights, proportional quotas, and the whole as one stratum."""
    return _variants(spark, sf_dir, {
        "equal_unweighted": {"methods": ("ivw_single",), "quota": "equal", "weighting": "none"}, "equal_design": {"methods": ("ivw_single",), "quota": "equal"},
        "proportional": {"methods": ("ivw_single",)}, "global": {"methods": ("ivw_single",), "quota": "global"}, "by_stratum": {"methods": ("ivw_single",), "by_stratum": True},
    })


def _stress(spark: SparkSession, scored: DataFrame, name: str, params: Params, **options) -> DataFrame:
    x = scored.withColumn("d", strata.equal_width(F.col("p")))
    return experiment.run_methods(spark, x, name, params, **options)


register("stress_rare_w2")(lambda spark, sf_dir: _stress(spark, scored_pairs(spark, sf_dir, "w2"), "w2", PUBLISHED))
register("stress_tiny_w6")(lambda spark, sf_dir: _stress(spark, labelled_documents(spark, sf_dir), "w6", PUBLISHED))
register("stress_tied_w4")(lambda spark, sf_dir: _stress(spark, scored_pairs(spark, sf_dir, "w4").withColumn("p", F.lit(0.5)), "tied", PUBLISHED, methods=("ivw_single", "ivw_min")))


@register("stress_no_signal_w5")
def stress_no_signal_w5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs of vectors: the square of their number, so they are made anew for their counts, for the samples and for the recall."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    n = {r.d: r.n for r in vector_pairs.score_histogram(vectors).collect()}  # a row per stratum
    return experiment.run_methods_unkept(spark, vector_pairs.scored_pairs(vectors), n, lambda values: vector_pairs.counts_by_place(vectors, values), "w5", PUBLISHED)


@register("baseline_no_ranker_w4")
def baseline_no_ranker_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Review in hash order: cost comes near the target itself."""
    x = scored_pairs(spark, sf_dir, "w4").withColumn("p", (F.xxhash64("pair_id").cast("double") + float(1 << 63)) / float(1 << 64))
    return _stress(spark, x, "w4_hash_order", PUBLISHED, methods=("ivw_min",))


@register("variant_dynamic_bins")
def variant_dynamic_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strata with edges around the decision region, wide near it or narrow near it, beside equal widths and equal depths."""
    base = kept(scored_pairs(spark, sf_dir, "w4"))
    kinds = {"wide_near": strata.dynamic_edges(0.7), "narrow_near": strata.dynamic_edges(0.7, inverse=True), "equi_depth": strata.equi_depth_edges(base)}
    out = None
    for name, e in kinds.items():
        x = experiment.run_methods(spark, base.withColumn("d", strata.edges(F.col("p"), e)), name, PUBLISHED, methods=("wilson_hash", "ivw_single"), quota="equal", trials=2)
        out = x if out is None else out.unionByName(x)
    return out


@register("variant_gate")
def variant_gate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether one more sample would pay, per target."""
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    n = x.count()
    params = PUBLISHED.at_most(n)
    rows = []
    for t in TARGETS:
        r = calibrate.calibrate(x, F.col("y"), t, params=params)
        near = x.where(F.abs(F.col("p") - r.tau) < 0.01).count()
        rows.append((t, r.tau, float(r.ci[0]), float(r.ci[1]), objective.gate_marginal(r, n, near / n / 0.02, float(params.k))))
    return spark.createDataFrame(rows, "target_mille int, tau double, ci_low double, ci_high double, accepted boolean")


@register("variant_cost_objective")
def variant_cost_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    return objective.cheapest(sampler.sample(x, PUBLISHED.at_most(x.count()).k, 2026, "proportional"), 1.0, 20.0)


@register("review_within_budget")
def review_within_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calibrate, review within a fifth of the pairs, and report what was confirmed and missed."""
    plain = kept(scored_pairs(spark, sf_dir, "w4"))
    n = plain.count()
    r = calibrate.calibrate(plain, F.col("y"), 800, params=PUBLISHED.at_most(n))
    x = plain.withColumn("hash_key", F.xxhash64("pair_id"))
    done = verify.review(x, r.tau, n // 5, "split")
    return measures.budgeted(done.agg(F.count("*").alias("reviewed"), F.count_if("y").alias("confirmed")).crossJoin(verify.missed(x, done, F.col("y")).agg(F.count("*").alias("missed"))), n // 5)


@register("methods_compared")
def methods_compared(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, ("w4",), methods=METHODS)


@register("stream_bottom_k")
def stream_bottom_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hash sample of the stream: the k smallest of all updates per stratum."""
    from pyspark.sql import Window

    updates = monitor.run_to_end(monitor.bottom_k(monitor.replay(spark, sf_dir), 50, 2026), "stream_bottom_k", "append")
    rank = F.row_number().over(Window.partitionBy("d").orderBy("hash_key"))
    return updates.distinct().withColumn("r", rank).where("r <= 50").drop("r")
