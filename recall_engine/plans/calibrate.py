"""From scored candidates and an oracle for labels to a threshold for a wanted recall."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..keep import kept
from ..operators import sampler
from ..params import RULES, Params
from . import bootstrap, ensemble, inverse_prob


@dataclass
class CalibrationResult:
    """``tau`` 0 with ``feasible`` false means: review everything. ``guaranteed`` holds for the exact bound alone on a simple random sample."""

    method: str
    target_mille: int
    tau: float
    feasible: bool
    guaranteed: bool
    ci: tuple[float, float]
    per_subsample: list[float] = field(default_factory=list)
    per_rule: dict[str, float | None] = field(default_factory=dict)
    positives: int = 0
    label_cost: int = 0
    hash_cut: object = None


def _positives(sample: DataFrame) -> tuple[dict[int, dict[str, np.ndarray]], int]:
    """The positives of each subsample (at most k rows each) and the number of labels asked for. The sample is made once."""
    rows = kept(sample.select("subsample", "pair_id", "d", "p", "w", "hash_key", "y"))
    cost = rows.select("pair_id").distinct().count()
    frame = rows.where("y").select("subsample", "d", "p", "w", "hash_key").toArrow().to_pandas()
    frame = frame.sort_values(["subsample", "p", "hash_key"], ascending=[True, False, True], kind="stable")
    return {int(s): {c: g[c].to_numpy() for c in ("p", "w", "d", "hash_key")} for s, g in frame.groupby("subsample", sort=True)}, cost


def draw(scored: DataFrame, method: str, params: Params, quota: str, mode: str = "reseed", family: str = "xxhash64", trial: int = 0, n: dict[int, int] | None = None) -> DataFrame:
    """The calibration sample that a method needs, with column ``subsample``."""
    seed = params.base_seed + 1 + 1000 * trial
    if method in ("ht_lower", "wilson_random", "exact_beta", "jeffreys", "wilson", "quantile"):
        return sampler.random(scored, params.k, seed, family).withColumn("subsample", F.lit(0))
    if method in ("wilson_hash", "ivw_single"):
        return sampler.sample(scored, params.k, seed, quota, family, n=n).withColumn("subsample", F.lit(0))
    return sampler.subsamples(scored, params.subsamples, params.k, seed, mode, quota, family, n)


def calibrate(scored: DataFrame, relevant: Column, target_mille: int, method: str = "ivw_min", params: Params = Params(), rules: tuple[str, ...] = RULES, fuse: str = "min", weighting: str = "design", quota: str = "proportional", engine: str = "numpy", fusion_cov: str = "diag", by_stratum: bool = False, form: str = "standard", center: str = "fused", mode: str = "reseed", family: str = "xxhash64", trial: int = 0, boot_seed: int = 7, n: dict[int, int] | None = None) -> CalibrationResult:
    """``scored`` has pair_id, p and stratum d; ``relevant`` is the expensive predicate, asked of the sample only."""
    sample = draw(scored, method, params, quota, mode, family, trial, n).withColumn("y", relevant)
    groups, cost = _positives(sample)
    return from_positives(groups, cost, target_mille, method, params, rules, fuse, weighting, engine, fusion_cov, by_stratum, form, center, boot_seed)


def weight_of(g: dict[str, np.ndarray], weighting: str) -> np.ndarray | None:
    """Equal weights need no weighting: then the integer ranks are exact."""
    return g["w"] if weighting == "design" and len(g["w"]) and np.ptp(g["w"]) > 1e-12 * g["w"].mean() else None


def from_positives(groups: dict[int, dict[str, np.ndarray]], cost: int, target_mille: int, method: str, params: Params, rules: tuple[str, ...] = RULES, fuse: str = "min", weighting: str = "design", engine: str = "numpy", fusion_cov: str = "diag", by_stratum: bool = False, form: str = "standard", center: str = "fused", boot_seed: int = 7, resamples: bootstrap.Resamples | None = None) -> CalibrationResult:
    """The driver's part: a few sorted arrays of positives to one threshold. ``resamples`` holds the draws that calls share."""
    resamples = resamples or bootstrap.Resamples((target_mille,), rules)
    total = sum(len(g["p"]) for g in groups.values())

    def made(tau: float | None, ci: tuple[float, float] | None = None, **more) -> CalibrationResult:
        t = 0.0 if tau is None else float(tau)
        return CalibrationResult(method, target_mille, t, tau is not None, method == "exact_beta" and tau is not None, ci or (t, t), positives=total, label_cost=cost, **more)

    if not total:
        return made(None)
    first = groups[min(groups)]
    if engine not in ("numpy", "analytic"):
        raise ValueError(f"calibrate has the engines numpy and analytic, not {engine}")

    if method == "ht_lower":
        return made(inverse_prob.threshold(first["p"], first["w"], target_mille, params.alpha))
    single = {"wilson_random": "wilson", "wilson_hash": "wilson"}.get(method, method)
    if single in RULES:
        per = bootstrap.thresholds(first["p"], weight_of(first, weighting), (single,), target_mille, params.alpha, form)
        return made(per[single], per_rule=per)
    taus, per_rule = [], {}
    for s, g in sorted(groups.items()):
        found = of_subsample(g, weight_of(g, weighting), target_mille, params, rules, engine, fusion_cov, by_stratum, form, boot_seed + s, resamples)
        if found is not None:
            taus.append(found[0])
            per_rule = per_rule or found[1]
    if not taus:
        return made(None)
    tau = ensemble.fuse(taus, fuse)
    return made(tau, ensemble.student_interval(taus, tau, center=center), per_subsample=taus, per_rule=per_rule)


def of_subsample(g: dict[str, np.ndarray], w: np.ndarray | None, target_mille: int, params: Params, rules: tuple[str, ...], engine: str, fusion_cov: str, by_stratum: bool, form: str, seed: int, resamples: bootstrap.Resamples) -> tuple[float, dict[str, float]] | None:
    """One subsample's threshold, its rules fused by their spread, and the rules' means; None if no rule reaches the target."""
    if engine == "analytic":
        if w is not None:
            raise ValueError("the closed form holds for equal weights; use weighting='none' or the engine numpy")
        m = bootstrap.analytic(g["p"], rules, target_mille, params.alpha, form)
    else:
        got = resamples.of(g, w, params.n_boot, seed, rules, target_mille, params.alpha, form, by_stratum)
        if fusion_cov == "full" and len(got) > 1:
            return ensemble.gls(got), {}
        m = {r: (float(x.mean()), float(x.var(ddof=1)) if len(x) > 1 else 0.0) for r, x in got.items()}
    if not m:
        return None
    inverse = {r: 1 / max(v, ensemble.EPS) for r, (_, v) in m.items()}
    return sum(inverse[r] * m[r][0] for r in m) / sum(inverse.values()), {r: m[r][0] for r in m}
