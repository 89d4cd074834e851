"""Other objectives than recall, and a gate on what one more sample would bring."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .calibrate import CalibrationResult


def curve(sample: DataFrame) -> DataFrame:
    """For each distinct score of a labelled sample (p, y, w): weighted true and false positives at and above it."""
    by = sample.groupBy("p").agg(F.sum(F.when(F.col("y"), F.col("w")).otherwise(0.0)).alias("tp_at"), F.sum(F.when(~F.col("y"), F.col("w")).otherwise(0.0)).alias("fp_at"))
    above = Window.orderBy(F.desc("p")).rowsBetween(Window.unboundedPreceding, 0)  # a sample, at most k rows
    whole = Window.partitionBy()
    return by.select("p", F.sum("tp_at").over(above).alias("tp"), F.sum("fp_at").over(above).alias("fp"), F.sum("tp_at").over(whole).alias("positives"))


def f_beta(sample: DataFrame, beta: float = 1.0) -> DataFrame:
    """The threshold with the largest F_beta: tau, f_beta, precision, recall."""
    b2 = beta * beta
    scored = curve(sample).withColumns({"precision": F.try_divide("tp", F.col("tp") + F.col("fp")), "recall": F.try_divide("tp", "positives"), "f_beta": F.try_divide((1 + b2) * F.col("tp"), (1 + b2) * F.col("tp") + b2 * (F.col("positives") - F.col("tp")) + F.col("fp"))})
    best = scored.agg(F.max(F.struct(F.round("f_beta", 12).alias("f_beta"), F.col("p").alias("tau"), "precision", "recall")).alias("m"))
    return best.select("m.tau", "m.f_beta", "m.precision", "m.recall")


def cheapest(sample: DataFrame, review_price: float, miss_price: float) -> DataFrame:
    """The threshold with the smallest cost of reviews and of missed matches."""
    cost = (F.col("tp") + F.col("fp")) * review_price + (F.col("positives") - F.col("tp")) * miss_price
    return curve(sample).withColumn("cost", cost).agg(F.min_by("p", "cost").alias("tau"), F.min("cost").alias("cost"))


def gate_marginal(result: CalibrationResult, candidates: int, density: float, sample_cost: float, review_price: float = 1.0) -> bool:
    """Whether to accept the threshold: one more sample would narrow the interval by 1 - sqrt(K / (K + 1)), which saves
    reviews in proportion to the score density around it; accept if that is worth less than the sample."""
    k = len(result.per_subsample)
    if k < 2:
        return False
    width = (result.ci[1] - result.ci[0]) / 2
    saved = width * (1 - (k / (k + 1)) ** 0.5) * density * candidates * review_price
    return saved <= sample_cost
