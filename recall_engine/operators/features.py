"""Sixteen pair features, scaling into [0, 10000], and static scores."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NAMES = tuple(f"f{k:02d}" for k in range(1, 17))
TOP = 10_000.0


def _extent(side: str, axis: str) -> Column:
    return (F.col(f"{side}_{axis}1") - F.col(f"{side}_{axis}0")).cast("double")


def _ratio(a: Column, b: Column) -> Column:
    """Smaller over larger; 1 for two zeros."""
    return F.when(F.greatest(a, b) == 0, 1.0).otherwise(F.least(a, b) / F.greatest(a, b))


def _area(side: str) -> Column:
    return _extent(side, "x") * _extent(side, "y") - 2.0 * F.col(f"{side}_c") * F.col(f"{side}_c")


def _perimeter(side: str) -> Column:
    return 2.0 * (_extent(side, "x") + _extent(side, "y")) - F.lit(8 - 4 * math.sqrt(2)) * F.col(f"{side}_c")


def _corners(side: str) -> Column:
    """Corners of the ring; a box whose corners are not cut has four."""
    return F.when(F.col(f"{side}_c") == 0, 4.0).otherwise(8.0)


def _overlap(axis: str) -> Column:
    return (F.least(f"s_{axis}1", f"t_{axis}1") - F.greatest(f"s_{axis}0", f"t_{axis}0")).cast("double")


def _centre_gap(axis: str) -> Column:
    """Twice the distance of the centres along one axis."""
    return F.abs(F.col(f"s_{axis}0") + F.col(f"s_{axis}1") - F.col(f"t_{axis}0") - F.col(f"t_{axis}1")).cast("double")


def _over(a: Column, b: Column) -> Column:
    return F.when(b == 0, 0.0).otherwise(a / b)


def margin() -> Column:
    """How far T stays inside S on the tightest side; negative outside."""
    return F.least(F.col("t_x0") - F.col("s_x0"), F.col("s_x1") - F.col("t_x1"), F.col("t_y0") - F.col("s_y0"), F.col("s_y1") - F.col("t_y1"))


def counted(pairs: DataFrame, side: str) -> DataFrame:
    """``pairs`` with the number of pairs of their row of one side, as _ns or _nt."""
    per = pairs.groupBy(F.col(f"{side}_id").alias("_id")).agg(F.count("*").alias(f"_n{side}"))
    return pairs.join(per, F.col(f"{side}_id") == F.col("_id")).drop("_id")


def raw(pairs: DataFrame) -> DataFrame:
    """``pairs`` with f01 to f16. Without the counts of ``counted`` they are read three times, so give them kept."""
    x = pairs if {"_ns", "_nt"} <= set(pairs.columns) else counted(counted(pairs, "s"), "t")
    both = _overlap("x") * _overlap("y")
    box_s, box_t = _extent("s", "x") * _extent("s", "y"), _extent("t", "x") * _extent("t", "y")
    gx, gy = _centre_gap("x"), _centre_gap("y")
    columns = [
        _ratio(_area("s"), _area("t")), _ratio(_perimeter("s"), _perimeter("t")), F.col("shared_cells").cast("double"), both,
        _over(both, box_s + box_t - both), _over(both, box_s), _over(both, box_t), F.sqrt(gx * gx + gy * gy) / 2.0,
        gx / 2.0, gy / 2.0, _ratio(_extent("s", "x"), _extent("t", "x")), _ratio(_extent("s", "y"), _extent("t", "y")),
        F.col("_ns").cast("double"), F.col("_nt").cast("double"), margin().cast("double"), _ratio(_corners("s"), _corners("t")),
    ]
    return x.withColumns(dict(zip(NAMES, columns, strict=True))).drop("_ns", "_nt")


def fit_minmax(df: DataFrame) -> dict[str, tuple[float, float]]:
    """Smallest and largest value of each feature, in one pass."""
    row = df.agg(*[f(n).alias(f"{n}_{k}") for n in NAMES for k, f in (("lo", F.min), ("hi", F.max))]).first()
    return {n: (row[f"{n}_lo"] or 0.0, row[f"{n}_hi"] or 0.0) for n in NAMES}


def scale(df: DataFrame, ranges: dict[str, tuple[float, float]]) -> DataFrame:
    """Features in [0, 10000]; a constant one is 0."""
    return df.withColumns({n: F.lit(0.0) if hi <= lo else F.least(F.lit(TOP), F.greatest(F.lit(0.0), (F.col(n) - lo) / F.lit(hi - lo) * TOP)) for n, (lo, hi) in ranges.items()})


def heuristic(kind: str = "blend") -> Column:
    """A score in [0, 1] from the boxes alone: ``blend``, ``overlap``, ``margin`` or ``centre``."""
    near = F.lit(1.0) - (_over(_centre_gap("x"), _extent("s", "x") + _extent("t", "x")) + _over(_centre_gap("y"), _extent("s", "y") + _extent("t", "y"))) / 2.0
    inside = _over(_overlap("x") * _overlap("y"), _extent("t", "x") * _extent("t", "y"))
    score = {"blend": 0.5 * inside + 0.5 * near, "overlap": inside, "centre": near, "margin": (margin() + 128.0) / 256.0}[kind]
    return F.least(F.lit(1.0), F.greatest(F.lit(0.0), score))


def scored(pairs: DataFrame, kind: str = "blend") -> DataFrame:
    return pairs.withColumn("p", heuristic(kind))
