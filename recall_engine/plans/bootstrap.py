"""Bootstrap of the threshold rules: replicates of each rule's threshold per subsample."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rules, special
from ..params import RULES

SCHEMA = "subsample int, rule string, replicate int, rank long, tau double, feasible boolean"


def effective(w: np.ndarray) -> float:
    return float(w.sum() ** 2 / (w**2).sum()) if len(w) else 0.0


def places(n: int, w: np.ndarray | None, rule_names: tuple[str, ...], target_mille: int, alpha: float, form: str = "standard") -> dict[str, float | None]:
    """Per rule the rank (unweighted) or the share of weight to keep (weighted); None where the rule can't reach the target."""
    if w is None:
        return {r: rules.rank(r, n, target_mille, alpha, form) for r in rule_names}
    n_eff = effective(w)
    return {r: rules.share(r, n_eff, target_mille, alpha, form) for r in rule_names}


def thresholds(p: np.ndarray, w: np.ndarray | None, rule_names: tuple[str, ...], target_mille: int, alpha: float, form: str = "standard") -> dict[str, float | None]:
    """Each rule's threshold on one sample's positives."""
    order = np.argsort(-p, kind="stable")
    p = p[order]
    at = places(len(p), None if w is None else w[order], rule_names, target_mille, alpha, form)
    if w is None:
        return {r: None if k is None else float(p[int(k) - 1]) for r, k in at.items()}
    c = np.cumsum(w[order])
    return {r: None if k is None else float(p[int(rules.weighted_place(c, c[-1], r, k))]) for r, k in at.items()}


def resample(p: np.ndarray, w: np.ndarray | None, d: np.ndarray | None, n_boot: int, seed: int, rule_names: tuple[str, ...], target_mille: int, alpha: float, form: str = "standard", by_stratum: bool = False) -> dict[str, np.ndarray]:
    """``n_boot`` thresholds of every rule. All rules read the same resamples; infeasible rules are left out."""
    return resample_targets(p, w, d, n_boot, seed, rule_names, (target_mille,), alpha, form, by_stratum)[target_mille]


def resample_targets(p: np.ndarray, w: np.ndarray | None, d: np.ndarray | None, n_boot: int, seed: int, rule_names: tuple[str, ...], targets: tuple[int, ...], alpha: float, form: str = "standard", by_stratum: bool = False) -> dict[int, dict[str, np.ndarray]]:
    """The same for several targets, all of which read the same resamples.

    A resample is drawn as counts of the sorted positives, so no scores are copied; ``by_stratum`` draws within strata.
    """
    n = len(p)
    order = np.argsort(-p, kind="stable")
    p = p[order]
    weights = None if w is None else w[order]
    at = {(t, r): k for t in targets for r, k in places(n, weights, rule_names, t, alpha, form).items() if k is not None}
    out = {t: {r: np.empty(n_boot) for s, r in at if s == t} for t in targets}
    if not at:
        return out
    rng = np.random.default_rng(seed)
    groups = [np.arange(n)] if not by_stratum or d is None else [np.flatnonzero(d[order] == h) for h in np.unique(d)]
    for b in range(n_boot):
        if len(groups) == 1:
            counts = np.bincount(rng.integers(0, n, n), minlength=n)
        else:
            counts = np.zeros(n, np.int64)
            for g in groups:
                counts[g] = np.bincount(rng.integers(0, len(g), len(g)), minlength=len(g))
        c = np.cumsum(counts if weights is None else counts * weights)
        for (t, r), k in at.items():
            i = np.searchsorted(c, k, side="left") if weights is None else rules.weighted_place(c, c[-1], r, k)
            out[t][r][b] = p[int(i)]
    return out


class Resamples:
    """Replicates by what they depend on, so that targets, rules and variants of one sample's positives share their draws."""

    def __init__(self, targets: tuple[int, ...], rule_names: tuple[str, ...] = RULES) -> None:
        self.targets, self.rules = targets, rule_names
        self.found: dict[tuple, tuple] = {}

    def of(self, g: dict[str, np.ndarray], w: np.ndarray | None, n_boot: int, seed: int, rule_names: tuple[str, ...], target_mille: int, alpha: float, form: str, by_stratum: bool) -> dict[str, np.ndarray]:
        if target_mille not in self.targets or not set(rule_names) <= set(self.rules):
            return resample(g["p"], w, g["d"], n_boot, seed, rule_names, target_mille, alpha, form, by_stratum)
        key = (id(g), w is None, n_boot, seed, alpha, form, by_stratum)
        if key not in self.found:  # ``g`` is held beside its replicates, so its id stays its own
            self.found[key] = g, resample_targets(g["p"], w, g["d"], n_boot, seed, self.rules, self.targets, alpha, form, by_stratum)
        every = self.found[key][1][target_mille]
        return {r: every[r] for r in rule_names if r in every}


def analytic(p: np.ndarray, rule_names: tuple[str, ...], target_mille: int, alpha: float, form: str = "standard") -> dict[str, tuple[float, float]]:
    """Mean and variance of each rule's threshold over all resamples, without resampling.

    The r-th of a resample is the j-th positive or a higher one with probability P(Bin(n, j/n) >= r).
    """
    p = np.sort(p)[::-1]
    n = len(p)
    out = {}
    for rule, r in places(n, None, rule_names, target_mille, alpha, form).items():
        if r is None:
            continue
        spread = 12 * np.sqrt(r * (1 - r / (n + 1)) + 1) + 12
        lo, hi = max(0, int(r - spread)), min(n, int(r + spread))
        tail = special.binomial_tails(n, np.arange(lo, hi + 1) / n, int(r))
        mass = np.diff(tail)
        q = p[lo:hi]
        mean = float((mass * q).sum() / mass.sum())
        out[rule] = (mean, float((mass * (q - mean) ** 2).sum() / mass.sum()))
    return out


def replicates(positives: DataFrame, target_mille: int, n_boot: int = 200, seed: int = 7, alpha: float = 0.10, rule_names: tuple[str, ...] = ("exact_beta", "jeffreys", "wilson", "quantile"), weighted: bool = True, form: str = "standard", by_stratum: bool = False) -> DataFrame:
    """(subsample, d, p, w) to the thresholds table. A group is one subsample's positives, at most k rows whatever the corpus."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        s = int(frame["subsample"].iloc[0])
        frame = frame.sort_values(["p", "d", "w"], ascending=False, kind="stable")
        w = frame["w"].to_numpy() if weighted else None
        got = resample(frame["p"].to_numpy(), w, frame["d"].to_numpy(), n_boot, seed + s, rule_names, target_mille, alpha, form, by_stratum)
        rows = []
        for r in rule_names:
            if r in got:
                rows.append(pd.DataFrame({"subsample": s, "rule": r, "replicate": range(n_boot), "rank": None, "tau": got[r], "feasible": True}))
            else:
                rows.append(pd.DataFrame({"subsample": [s], "rule": [r], "replicate": [0], "rank": [None], "tau": [None], "feasible": [False]}))
        return pd.concat(rows, ignore_index=True)

    return positives.select("subsample", "d", "p", "w").groupBy("subsample").applyInPandas(run, SCHEMA)


def hashed_replicates(positives: DataFrame, target_mille: int | tuple[int, ...], n_boot: int, seed: int = 7, alpha: float = 0.10, rule_names: tuple[str, ...] = ("exact_beta", "jeffreys", "wilson", "quantile"), sizes: dict[int, int] | None = None) -> DataFrame:
    """The same with draws from a hash of (seed, subsample, replicate, draw), in DataFrame operations only: any engine gets the same
    replicates. Several targets read the same draws, and add the column target_mille."""
    order = Window.partitionBy("subsample").orderBy(F.desc("p"), "pair_id")
    ranked = positives.select("subsample", "pair_id", "p").withColumn("place", F.row_number().over(order))
    sizes = sizes or {r["subsample"]: r["count"] for r in positives.groupBy("subsample").count().collect()}  # one row per subsample
    spark = positives.sparkSession
    per = spark.createDataFrame([(s, n) for s, n in sizes.items()], "subsample int, n int")
    draws = per.select("subsample", "n", F.explode(F.sequence(F.lit(0), F.lit(n_boot - 1))).alias("replicate")).repartition("subsample", "replicate").select("subsample", "n", "replicate", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("i"))
    hashed = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.col(c).cast("string") for c in ("subsample", "replicate", "i")])), 1, 8), 16, 10).cast("long")
    drawn = draws.withColumn("place", (hashed % F.col("n") + 1).cast("int"))
    within = Window.partitionBy("subsample", "replicate").orderBy("place", "i")
    drawn = drawn.withColumn("rank", F.row_number().over(within).cast("long"))
    targets = (target_mille,) if isinstance(target_mille, int) else target_mille
    wanted = [(s, t, r, k) for s, n in sizes.items() for t in targets for r in rule_names if (k := rules.rank(r, n, t, alpha)) is not None]
    picks = spark.createDataFrame(wanted or [(-1, -1, "", -1)], "_s int, target_mille int, rule string, _rank long")
    hit = drawn.join(F.broadcast(picks), (F.col("subsample") == F.col("_s")) & (F.col("rank") == F.col("_rank")))  # subsamples times targets times rules rows
    more = [] if isinstance(target_mille, int) else ["target_mille"]
    return hit.join(ranked, ["subsample", "place"]).select(*more, "subsample", "rule", "replicate", "rank", F.col("p").alias("tau"), F.lit(True).alias("feasible"))
