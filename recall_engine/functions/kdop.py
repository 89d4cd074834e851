"""Topological predicates of two octagons, exact in integers and inside code generation."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

PREDICATES = ("intersects", "disjoint", "contains", "within", "covers", "covered_by", "touches", "overlaps", "equals")
AXES = ("x", "y", "u", "v")


def _all(conditions: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, conditions)


def _col(side: str, axis: str, end: int) -> Column:
    return F.col(f"{side}_{axis}{end}")


def _inside(outer: str, inner: str) -> Column:
    return _all([(_col(outer, a, 0) <= _col(inner, a, 0)) & (_col(inner, a, 1) <= _col(outer, a, 1)) for a in AXES])


def relate(pred: str, s: str = "s", t: str = "t") -> Column:
    """The predicate between the octagons in columns ``s_*`` and ``t_*``.

    Two octagons with these eight directions meet if and only if their intervals meet on all four axes. Octagons have an
    interior, so covers and contains agree.
    """
    closed = _all([(_col(s, a, 0) <= _col(t, a, 1)) & (_col(t, a, 0) <= _col(s, a, 1)) for a in AXES])
    opened = _all([(_col(s, a, 0) < _col(t, a, 1)) & (_col(t, a, 0) < _col(s, a, 1)) for a in AXES])
    covers, covered = _inside(s, t), _inside(t, s)
    return {
        "intersects": closed, "disjoint": ~closed, "contains": covers, "covers": covers, "within": covered, "covered_by": covered,
        "touches": closed & ~opened, "overlaps": opened & ~covers & ~covered, "equals": covers & covered, "crosses": F.lit(False),
    }[pred]
