"""The experiment runner: methods by targets by trials on one workload, against complete truth."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..keep import kept
from ..operators import measures, sampler
from ..params import METHODS, TARGETS, TRIALS, Params
from . import bootstrap, calibrate, ensemble

RUN_COLUMNS = "workload string, method string, target_mille int, trial int, tau double, ci_low double, ci_high double, feasible boolean, positives long, label_cost long"


def thresholds(scored: DataFrame, workload: str, params: Params, methods: tuple[str, ...] = METHODS, targets: tuple[int, ...] = TARGETS, trials: int = 1, first_trial: int = 0, n: dict[int, int] | None = None, shared: dict | None = None, unkept: bool = False, **options) -> list[tuple]:
    """A row per method, target and trial. A sample is drawn and labelled once per trial and kind, and serves all targets and rules,
    and so do its resamples. ``shared`` carries both on to further calls on the same pairs. ``unkept`` pairs are made again whenever
    they are read: those that can be in a sample are kept from one pass, if all samples are drawn together."""
    n = sampler.sizes(scored) if n is None else n
    params = params.at_most(sum(n.values()))
    quota, mode = options.get("quota", "proportional"), options.get("mode", "reseed")
    more = {k: v for k, v in options.items() if k not in ("quota", "mode")}
    if shared is None and mode == "reseed" and quota in ("equal", "proportional"):
        return _together(scored, workload, params, methods, targets, range(first_trial, first_trial + trials), n, quota, more, unkept)
    rows = []
    for trial in range(first_trial, first_trial + trials):
        drawn = {} if shared is None else shared
        resamples = drawn.setdefault("resamples", bootstrap.Resamples(targets))
        for method in methods:
            kind = _kind(method)
            # What a sample of its kind depends on.
            by = {"random": (), "single": (quota,), "many": (quota, mode, params.subsamples)}[kind]
            key = (kind, trial, params.k, params.base_seed, *by)
            if key not in drawn:
                drawn[key] = calibrate._positives(calibrate.draw(scored, method, params, quota, mode, trial=trial, n=n))
            groups, cost = drawn[key]
            for target in targets:
                r = calibrate.from_positives(groups, cost, target, method, params, boot_seed=7 + 100 * trial, resamples=resamples, **more)
                rows.append((workload, method, target, trial, r.tau, float(r.ci[0]), float(r.ci[1]), r.feasible, r.positives, r.label_cost))
    return rows


def _kind(method: str) -> str:
    """What a method draws: a simple random sample, one stratified by score, or several of these."""
    return "random" if method in ("ht_lower", "wilson_random", "exact_beta", "jeffreys", "wilson", "quantile") else "single" if method in ("wilson_hash", "ivw_single") else "many"


def _together(scored: DataFrame, workload: str, params: Params, methods: tuple[str, ...], targets: tuple[int, ...], trials: range, n: dict[int, int], quota: str, more: dict, unkept: bool) -> list[tuple]:
    """The same for all trials at once: two passes over the pairs find every sample's cuts and its positives, and the tasks that
    get a sample's positives compute its thresholds and resamples. A sample that several methods draw alike is there once."""
    total = sum(n.values())
    q = sampler.quotas(n, params.k, quota)
    draws, place, reads = [], {}, {}  # reads: of a trial and kind the draws, in the order of its subsamples
    for trial in trials:
        seed = params.base_seed + 1 + 1000 * trial
        for kind in dict.fromkeys(map(_kind, methods)):
            if kind == "random":
                wanted = [sampler.Draw(seed ^ sampler.RANDOM, True, {0: total}, {0: min(params.k, total)})]
            else:
                wanted = [sampler.Draw(seed + j, False, n, q) for j in range(params.subsamples if kind == "many" else 1)]
            for x in wanted:
                if (x.seed, x.plain) not in place:
                    place[x.seed, x.plain] = len(draws)
                    draws.append(x)
            reads[trial, kind] = [place[x.seed, x.plain] for x in wanted]
    groups = list(reads)
    # What a sample's positives are asked for: (method, boot seed) of each trial and subsample that reads it.
    asked: dict[int, list[tuple]] = {}
    for (trial, kind), at in reads.items():
        for s, i in enumerate(at):
            asked.setdefault(i, []).extend((m, kind, trial, s, 7 + 100 * trial) for m in methods if _kind(m) == kind)
    defaults = {"rules": bootstrap.RULES, "weighting": "design", "engine": "numpy", "fusion_cov": "diag", "by_stratum": False, "form": "standard"}
    fuse, center = more.get("fuse", "min"), more.get("center", "fused")
    how = defaults | {k: v for k, v in more.items() if k in defaults}

    def of_draw(frame: pd.DataFrame) -> pd.DataFrame:
        i = int(frame["draw"].iloc[0])
        out = []
        if i < 0:
            out.append((i, "", 0, 0, 0, None, None, None, False, int(frame["pairs"].sum())))
        else:
            g = np.frombuffer(b"".join(frame["packed"]), sampler.PACKED)
            g = g[np.lexsort((g["hash_key"], -g["p"]))]
            g = {c: np.ascontiguousarray(g[c]) for c in sampler.PACKED.names}
            g["w"] = draws[i].weight(g["d"])
            resamples = bootstrap.Resamples(targets)
            for method, kind, trial, s, boot_seed in asked[i]:
                for target in targets:
                    if kind == "many":
                        found = calibrate.of_subsample(g, calibrate.weight_of(g, how["weighting"]), target, params, how["rules"], how["engine"], how["fusion_cov"], how["by_stratum"], how["form"], boot_seed + s, resamples)
                        tau, ci = (None, (None, None)) if found is None else (float(found[0]), (None, None))
                    else:
                        r = calibrate.from_positives({0: g}, 0, target, method, params, boot_seed=boot_seed, resamples=resamples, **more)
                        tau, ci = r.tau if r.feasible else None, r.ci
                    out.append((i, method, target, trial, s, tau, *(None if c is None else float(c) for c in ci), tau is not None, len(g["p"])))
        return pd.DataFrame(out, columns=[c.split()[0] for c in _OF_DRAW.split(", ")]).astype({"tau": "float64", "ci_low": "float64", "ci_high": "float64"})

    together = [reads[x] for x in groups]
    try:
        members = sampler.taken(kept(sampler.near(scored, draws)) if unkept else scored, draws, together)
    except sampler.TooFew:
        if not unkept:
            raise
        members = sampler.taken(scored, draws, together)
    found: dict[tuple, dict] = {}
    cost = dict.fromkeys(groups, 0)
    for r in members.groupBy("draw").applyInPandas(of_draw, _OF_DRAW).collect():  # draws times methods times targets rows
        if r.draw < 0:
            cost[groups[-1 - r.draw]] = r.rows
        else:
            found.setdefault((r.trial, r.method, r.target), {})[r.subsample] = r
    rows = []
    for trial in trials:
        for method in methods:
            for target in targets:
                per = [r for _, r in sorted(found.get((trial, method, target), {}).items())]
                taus = [r.tau for r in per if r.feasible]
                tau, ci = (taus[0], (per[0].ci_low, per[0].ci_high)) if taus else (0.0, (0.0, 0.0))
                if taus and _kind(method) == "many":
                    tau = ensemble.fuse(taus, fuse)
                    ci = ensemble.student_interval(taus, tau, center=center)
                rows.append((workload, method, target, trial, float(tau), float(ci[0]), float(ci[1]), bool(taus), sum(r.rows for r in per), cost[trial, _kind(method)]))
    return rows


_OF_DRAW = "draw int, method string, target int, trial int, subsample int, tau double, ci_low double, ci_high double, feasible boolean, rows long"


def runs(spark: SparkSession, scored: DataFrame, rows: list[tuple]) -> DataFrame:
    """Thresholds with what they achieve, evaluated in one pass over the pairs."""
    taus = spark.createDataFrame(rows, RUN_COLUMNS)
    return measures.recall_error(measures.evaluated_many(scored, taus))


def run_methods(spark: SparkSession, scored: DataFrame, workload: str, params: Params, keep: bool = True, **options) -> DataFrame:
    """Scored pairs are kept once (columns p, y and what samples need), unless they are so already; every step after reads them."""
    pairs = scored.select("pair_id", "p", "d", "y")
    pairs = kept(pairs) if keep else pairs
    return runs(spark, pairs, thresholds(pairs, workload, params, **options))


def run_methods_unkept(spark: SparkSession, scored: DataFrame, n: dict[int, int], counts_by_place: Callable[[list[float]], DataFrame], workload: str, params: Params, **options) -> DataFrame:
    """The same for pairs that are too many to be kept and are made again instead: ``n`` has their number by stratum, and
    ``counts_by_place`` counts them between thresholds. One pass over them serves all samples."""
    rows = thresholds(scored.select("pair_id", "p", "d", "y"), workload, params, n=n, unkept=True, **options)
    taus = spark.createDataFrame(rows, RUN_COLUMNS)
    return measures.recall_error(measures.evaluated_many(scored, taus, counts_by_place))


def recall_table(spark: SparkSession, per_workload: dict[str, DataFrame], params: Params, trials: int = TRIALS, **options) -> DataFrame:
    """Mean and spread of recall by workload, method and target."""
    out = None
    for name, scored in per_workload.items():
        x = run_methods(spark, scored, name, params, trials=trials, **options)
        out = x if out is None else out.unionByName(x)
    return measures.recall_summary(out)


def as_of(rows: DataFrame, versions: DataFrame, at: str, since: str, values: list[str], buckets: str = "day") -> DataFrame:
    """Each row with the values of the last version not after it.

    Versions and rows are laid out in one timeline, cut into buckets; the last version before a bucket comes from the
    versions alone, the rest from a window inside the bucket. No bucket sees all rows.
    """
    b = F.date_trunc(buckets, F.col(since))
    v = versions.withColumn("_b", b)
    carried = F.struct(F.col(since).alias("_since"), *values)
    last = v.groupBy("_b").agg(F.max(carried).alias("_v"))
    spans = rows.select(F.date_trunc(buckets, F.col(at)).alias("_b")).distinct().join(last, "_b", "full")
    before = Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)  # one row per bucket
    spans = spans.select("_b", F.last("_v", ignorenulls=True).over(before).alias("_earlier"))
    line = rows.withColumn("_b", F.date_trunc(buckets, F.col(at))).select("_b", F.col(at).alias("_t"), F.lit(1).alias("_kind"), F.struct(*rows.columns).alias("_row"), F.lit(None).cast(v.select(carried.alias("c")).schema["c"].dataType).alias("_v"))
    marks = v.select("_b", F.col(since).alias("_t"), F.lit(0).alias("_kind"), F.lit(None).cast(rows.select(F.struct(*rows.columns).alias("r")).schema["r"].dataType).alias("_row"), carried.alias("_v"))
    window = Window.partitionBy("_b").orderBy("_t", "_kind").rowsBetween(Window.unboundedPreceding, 0)
    filled = line.unionByName(marks).withColumn("_v", F.last("_v", ignorenulls=True).over(window)).where("_kind = 1")
    joined = filled.join(spans, "_b", "left").withColumn("_v", F.coalesce("_v", "_earlier"))
    return joined.select("_row.*", *[F.col(f"_v.{c}").alias(c) for c in values])
