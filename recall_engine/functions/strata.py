"""Strata of a score in [0, 1]."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def equal_width(p: Column, bins: int = 10) -> Column:
    return F.least(F.lit(bins - 1), F.floor(p * bins)).cast("int")


def edges(p: Column, inner: list[float]) -> Column:
    """Stratum by inner edges in rising order; an edge belongs to the stratum above it."""
    return reduce(lambda a, e: a + F.when(p >= e, 1).otherwise(0), inner, F.lit(0)).cast("int")


def equi_depth_edges(df: DataFrame, bins: int = 10, accuracy: int = 100_000) -> list[float]:
    """Inner edges that leave about as many rows in each stratum, from one sketch; equal edges are merged."""
    row = df.agg(F.percentile_approx("p", [k / bins for k in range(1, bins)], accuracy).alias("e")).first()
    return sorted(set(row["e"] or []))


def dynamic_edges(focus: float, wide: float = 0.20, narrow: float = 0.05, inverse: bool = False) -> list[float]:
    """Edges around a decision region: bins of width ``wide`` near ``focus`` and ``narrow`` elsewhere, or the reverse."""
    near, far = (narrow, wide) if inverse else (wide, narrow)
    lo, hi = max(0.0, focus - near), min(1.0, focus + near)
    found, at = [], 0.0
    while at < 1.0 - 1e-9:
        step = near if lo - 1e-9 <= at < hi - 1e-9 else far
        at = min(1.0, at + step)
        if lo - 1e-9 > at - step and at > lo:
            at = lo
        found.append(round(at, 9))
    return [e for e in found if 0.0 < e < 1.0]
