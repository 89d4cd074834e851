"""Recall, cost and spread."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def evaluated(scored: DataFrame, tau: float | Column) -> DataFrame:
    """One row over pairs with score p and truth y: relevant, reviewed, hits, recall, precision and cost_fraction."""
    t = tau if isinstance(tau, Column) else F.lit(float(tau))
    above = F.col("p") >= t
    counts = scored.agg(F.count("*").alias("candidates"), F.count_if("y").alias("relevant"), F.count_if(above).alias("reviewed"), F.count_if(above & F.col("y")).alias("hits"))
    return counts.withColumns({"recall": F.try_divide("hits", "relevant"), "precision": F.try_divide("hits", "reviewed"), "cost_fraction": F.try_divide("reviewed", "candidates")})


def evaluated_many(scored: DataFrame, taus: DataFrame, counts_by_place: Callable[[list[float]], DataFrame] | None = None) -> DataFrame:
    """The same for every row of a small table of thresholds (tau), in one pass over the pairs. ``counts_by_place`` makes that pass in
    another way: (place, n, pos) of the pairs by the number of the sorted thresholds that their score is not below."""
    values = sorted({float(r.tau) for r in taus.select("tau").distinct().collect() if r.tau is not None})  # a table of methods and targets
    # Each pair's place among the sorted thresholds, by halving; counts per place, and sums of them from above.
    by_place = counts_by_place(values) if counts_by_place else scored.groupBy(F.expr(_place("p", values)).alias("place")).agg(F.count("*").alias("n"), F.count_if("y").alias("pos"))
    n, pos = [0] * (len(values) + 1), [0] * (len(values) + 1)
    for r in by_place.collect():  # a row per threshold
        n[r.place], pos[r.place] = r.n, r.pos
    rows = [(t, sum(n), sum(pos), sum(n[k + 1 :]), sum(pos[k + 1 :])) for k, t in enumerate(values)]
    counts = scored.sparkSession.createDataFrame(rows, "_tau double, candidates long, relevant long, reviewed long, hits long")
    joined = taus.join(F.broadcast(counts), F.col("tau") == F.col("_tau")).drop("_tau")  # a row per threshold
    return joined.withColumns({"recall": F.try_divide("hits", "relevant"), "cost_fraction": F.try_divide("reviewed", "candidates")})


def _place(p: str, values: list[float], lo: int = 0, hi: int | None = None) -> str:
    """SQL of how many of the sorted ``values`` are at most ``p``."""
    hi = len(values) if hi is None else hi
    if lo == hi:
        return str(lo)
    mid = (lo + hi) // 2
    return f"CASE WHEN {p} >= {values[mid]!r}D THEN {_place(p, values, mid + 1, hi)} ELSE {_place(p, values, lo, mid)} END"


def recall_error(runs: DataFrame) -> DataFrame:
    """Adds abs_error, overshoot (signed) and whether the run is within a point."""
    over = F.col("recall") - F.col("target_mille") / 1000
    return runs.withColumns({"overshoot": over, "abs_error": F.abs(over), "within_point": F.abs(over) <= 0.01 + 1e-12})


def budgeted(runs: DataFrame, budget: int) -> DataFrame:
    return runs.withColumns({"over_budget": F.col("reviewed") > budget, "budget_excess": F.greatest(F.lit(0), F.col("reviewed") - budget)})


def recall_summary(runs: DataFrame) -> DataFrame:
    """Mean and spread of recall by workload, method and target, with totals by grouping sets."""
    runs = recall_error(runs)
    return runs.cube("workload", "method", "target_mille").agg(
        F.count("*").alias("runs"), F.avg("recall").alias("mean_recall"), F.stddev_samp("recall").alias("sd_recall"), F.avg("abs_error").alias("mean_abs_error"),
        F.avg("overshoot").alias("bias"), F.avg(F.col("within_point").cast("double")).alias("share_within_point"), F.avg("cost_fraction").alias("mean_cost"),
    )


def threshold_spread(taus: DataFrame, by: list[str]) -> DataFrame:
    """Standard deviation and coefficient of variation of tau."""
    return taus.groupBy(*by).agg(F.stddev_samp("tau").alias("sd_tau"), (F.stddev_samp("tau") / F.avg("tau")).alias("cv_tau"))


def spread_ratio(summary: DataFrame, method: str, against: str) -> DataFrame:
    """Recall SD of one method over another's, per workload and target."""
    a = summary.where(F.col("method") == method).select("workload", "target_mille", F.col("sd_recall").alias("sd"))
    b = summary.where(F.col("method") == against).select("workload", "target_mille", F.col("sd_recall").alias("sd_against"))
    return a.join(b, ["workload", "target_mille"]).withColumn("sd_ratio", F.try_divide("sd", "sd_against"))


def recall_curve(scored: DataFrame, bins: int = 100) -> DataFrame:
    """Recall and cost at thresholds 0, 1/bins, ...: a histogram of fixed size, then sums over it from above."""
    b = F.least(F.lit(bins - 1), F.floor(F.col("p") * bins)).cast("int")
    h = scored.groupBy(b.alias("bin")).agg(F.count("*").alias("n"), F.count_if("y").alias("pos"))
    above = Window.orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, 0)  # bins rows
    whole = Window.partitionBy()
    return h.select(
        "bin", (F.col("bin") / F.lit(bins)).alias("tau"), F.sum("n").over(above).alias("reviewed"), F.sum("pos").over(above).alias("hits"),
        F.try_divide(F.sum("pos").over(above), F.sum("pos").over(whole)).alias("recall"), (F.sum("n").over(above) / F.sum("n").over(whole)).alias("cost_fraction"),
    )


def ideal_threshold(scored: DataFrame, target_mille: int, budget: int | None = None) -> dict[str, object]:
    """With full truth: the largest threshold that reaches the target, and what it costs. A histogram finds the bin, one more pass the score."""
    positives = scored.where("y")
    n = positives.count()
    need = max(1, -(-n * target_mille // 1000))
    if not n:
        return {"tau": 0.0, "reviewed": scored.count(), "feasible": False}
    from .verify import cut_score

    tau, _ = cut_score(positives, need)
    reviewed = scored.where(F.col("p") >= tau).count()
    return {"tau": tau, "reviewed": reviewed, "feasible": budget is None or reviewed <= budget}


def variance_bound(k: int, sigma_max: float, strata: int = 10) -> float:
    """The printed bound of the variance of a stratified quantile: sigma_max^2 over k / strata."""
    return sigma_max**2 / (k / strata)


def stratified_variance(weights: list[float], sigmas: list[float], quotas: list[int]) -> float:
    """The classical one: sum of W^2 sigma^2 / n."""
    return math.fsum(w * w * s * s / q for w, s, q in zip(weights, sigmas, quotas, strict=True) if q)


def score_profile(scored: DataFrame) -> DataFrame:
    """Pairs, positives and score moments by stratum."""
    return scored.groupBy("d").agg(F.count("*").alias("n"), F.count_if("y").alias("pos"), F.avg("p").alias("mean_p"), F.coalesce(F.stddev_samp("p"), F.lit(0.0)).alias("sd_p"))


def review_money(scored: DataFrame, tau: float, c_geom: float, c_feat: float) -> float:
    """Cost of checking what is reviewed and of the features of all."""
    row = evaluated(scored, tau).first()
    return row["reviewed"] * c_geom + row["candidates"] * c_feat


def state_bytes(subsamples: int, positives: int, rules: int, n_boot: int) -> int:
    """Doubles that calibration keeps: sorted positives and replicates."""
    return 8 * (subsamples * positives + subsamples * rules * n_boot)


class StageTimer:
    """Seconds, share and rows per second of named stages."""

    def __init__(self) -> None:
        self.seconds: dict[str, float] = {}
        self.rows: dict[str, int] = {}

    @contextmanager
    def stage(self, name: str, rows: int = 0):
        began = time.perf_counter()
        yield
        self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
        self.rows[name] = self.rows.get(name, 0) + rows

    def table(self) -> list[dict[str, object]]:
        total = sum(self.seconds.values()) or 1.0
        return [{"stage": k, "seconds": s, "share": s / total, "rows_per_s": self.rows[k] / s if s else 0.0} for k, s in self.seconds.items()]
