"""Reviewing the pairs above a threshold, within a budget."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BINS = 1024


def cut_score(scored: DataFrame, budget: int) -> tuple[float, int]:
    """The score at which the ``budget`` best pairs end, and how many of that score's pairs are among them.

    A histogram of fixed size narrows the cut to one bin, another to one bin of that, until the bin has one score: a few
    passes of fixed-size results, however the scores are spread.
    """
    above, inside = 0, scored
    lo, hi = 0.0, 1.0
    while True:
        place = F.least(F.lit(BINS - 1), F.greatest(F.lit(0), F.floor((F.col("p") - F.lit(lo)) * F.lit(BINS / (hi - lo))))).cast("int")
        rows = inside.where(F.col("p").isNotNull()).groupBy(place.alias("b")).agg(F.count("*").alias("n"), F.min("p").alias("lo"), F.max("p").alias("hi")).collect()  # BINS rows
        for r in sorted(rows, key=lambda r: -r["b"]):
            if above + r["n"] >= budget:
                break
            above += r["n"]
        else:
            return 0.0, budget
        lo, hi = float(r["lo"]), float(r["hi"])
        if lo == hi:
            return lo, budget - above
        inside = scored.where((F.col("p") >= F.lit(lo)) & (F.col("p") <= F.lit(hi)))


def review(scored: DataFrame, tau: float, budget: int | None = None, ties: str = "include", key: str = "hash_key") -> DataFrame:
    """The pairs with p >= tau, the best ``budget`` of them if there are more. ``ties="split"`` cuts among equal scores by key."""
    chosen = scored.where(F.col("p") >= F.lit(tau))
    if budget is None:
        return chosen
    n = chosen.count()
    if n <= budget:
        return chosen
    score, of_tie = cut_score(chosen, budget)
    if ties != "split":
        # Whole ties only, and never above the budget.
        tied = chosen.where(F.col("p") == score).count()
        return chosen.where(F.col("p") >= score) if tied == of_tie else chosen.where(F.col("p") > score)
    best = chosen.where(F.col("p") > score)
    return best.unionByName(chosen.where(F.col("p") == score).orderBy(key).limit(of_tie))


def split_at_recall(scored: DataFrame, tau: float, keep_of_tie: float, key: Column) -> DataFrame:
    """Pairs above tau and, of those at tau, the share with the smallest keys: reproducible cuts inside a tie."""
    from ..functions import hashing

    return scored.where((F.col("p") > tau) | ((F.col("p") == tau) & hashing.below(key, F.lit(keep_of_tie))))


def missed(scored: DataFrame, reviewed: DataFrame, relevant: Column) -> DataFrame:
    """Relevant pairs that the review does not hold."""
    return scored.where(relevant).join(reviewed.select("pair_id"), "pair_id", "left_anti")


def confirmed(reviewed: DataFrame, relevant: Column) -> DataFrame:
    return reviewed.where(relevant)


def with_rings(pairs: DataFrame, s: DataFrame, t: DataFrame) -> DataFrame:
    """Rings joined late, by id, to the pairs that need the general predicate."""
    a = s.select(F.col("id").alias("s_id"), F.col("ring").alias("s_ring"))
    b = t.select(F.col("id").alias("t_id"), F.col("ring").alias("t_ring"))
    return pairs.join(a, "s_id").join(b, "t_id")
