"""Fusing thresholds: inverse-variance weights within a subsample, then one value from all subsamples, and an interval."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import special

EPS = 1e-12


def moments(replicates: DataFrame, sample_variance: bool = True) -> DataFrame:
    """(subsample, rule) with mean_tau, var_tau and the number of replicates, from feasible ones."""
    var = F.var_samp if sample_variance else F.var_pop
    return replicates.where("feasible").groupBy("subsample", "rule").agg(F.avg("tau").alias("mean_tau"), F.coalesce(var("tau"), F.lit(0.0)).alias("var_tau"), F.count("*").alias("replicates"))


def weights(m: DataFrame, eps: float = EPS) -> DataFrame:
    """Adds ``weight``: inverse variances, floored at ``eps``, as shares of their subsample. All at the floor means equal weights."""
    inverse = 1.0 / F.greatest(F.col("var_tau"), F.lit(eps))
    return m.withColumn("weight", inverse / F.sum(inverse).over(Window.partitionBy("subsample")))


def ivw(m: DataFrame, eps: float = EPS) -> DataFrame:
    """(subsample, tau_ens)."""
    return weights(m, eps).groupBy("subsample").agg(F.sum(F.col("weight") * F.col("mean_tau")).alias("tau_ens"))


def gls(values: dict[str, np.ndarray], eps: float = EPS) -> float:
    """Fusion of one subsample's replicates with their full covariance instead of the variances alone."""
    x = np.stack(list(values.values()))
    cov = np.atleast_2d(np.cov(x)) + eps * np.eye(len(x))
    one = np.linalg.solve(cov, np.ones(len(x)))
    return float(one @ x.mean(axis=1) / one.sum())


def fuse_taus(taus: DataFrame, how: str = "min") -> DataFrame:
    """One row with tau."""
    pick = {"min": F.min("tau_ens"), "median": F.percentile("tau_ens", F.lit(0.5)), "mean": F.avg("tau_ens")}[how]
    return taus.agg(pick.alias("tau"))


def fuse(taus: list[float], how: str = "min") -> float:
    return float({"min": np.min, "median": np.median, "mean": np.mean}[how](taus)) if len(taus) else 0.0


def student_interval(taus: list[float], fused: float, level: float = 0.90, center: str = "fused") -> tuple[float, float]:
    """Student-t interval over the subsamples' thresholds; squares around the fused value as printed, or around the mean."""
    n = len(taus)
    if n < 2:
        return fused, fused
    middle = fused if center == "fused" else float(np.mean(taus))
    half = special.student_quantile(0.5 + level / 2, n - 1) * math.sqrt(sum((t - middle) ** 2 for t in taus) / (n * (n - 1)))
    return middle - half, middle + half
