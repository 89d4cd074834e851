"""Threshold rules: which of n positives, sorted by falling score, sets the threshold. Ranks depend on n, target and alpha, not on scores."""

from __future__ import annotations

import functools
import math

from . import special


def lower_bound(rule: str, k: float, n: float, alpha: float = 0.10, form: str = "standard") -> float:
    """The rule's lower bound of recall when k of n positives are kept. k and n may be effective counts."""
    if n <= 0 or k <= 0:
        return 0.0
    if rule == "exact_beta":
        return special.beta_quantile(alpha, k, n - k + 1)
    if rule == "jeffreys":
        return special.beta_quantile(alpha, k + 0.5, n - k + 0.5)
    if rule == "wilson":
        z = special.normal_quantile(1 - alpha)
        r = k / n
        spread = r * (1 - r) / n + z * z / (4 * n * n) if form == "standard" else r * (1 - r) + z * z / (4 * n)
        return (r + z * z / (2 * n) - z * math.sqrt(spread)) / (1 + z * z / n)
    raise ValueError(rule)


def reaches(rule: str, k: float, n: float, target: float, alpha: float = 0.10, form: str = "standard") -> bool:
    """Whether the lower bound at k is at least the target; no inverse is needed for the beta rules."""
    if n <= 0 or k <= 0:
        return False
    if rule == "exact_beta":
        return special.betainc(k, n - k + 1, target) <= alpha
    if rule == "jeffreys":
        return special.betainc(k + 0.5, n - k + 0.5, target) <= alpha
    return lower_bound(rule, k, n, alpha, form) >= target


@functools.lru_cache(4096)
def rank(rule: str, n: int, target_mille: int, alpha: float = 0.10, form: str = "standard") -> int | None:
    """The smallest rank whose bound reaches the target, or None if none does."""
    if n <= 0:
        return None
    if rule == "quantile":
        # Ascending place ceil((1 - R) n) by integers; at the target 1 the lowest positive counts.
        low = max(1, (n * (1000 - target_mille) + 999) // 1000)
        return n - low + 1
    target = target_mille / 1000
    if not reaches(rule, n, n, target, alpha, form):
        return None
    lo, hi = 0, n  # the bound rises with k
    while hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if reaches(rule, mid, n, target, alpha, form) else (mid, hi)
    return hi


@functools.lru_cache(4096)
def share(rule: str, n_eff: float, target_mille: int, alpha: float = 0.10, form: str = "standard") -> float | None:
    """For weighted positives: the share of weight to keep so that the bound, with n_eff effective positives, reaches the target."""
    if n_eff <= 0:
        return None
    target = target_mille / 1000
    if rule == "quantile":
        return target
    if not reaches(rule, n_eff, n_eff, target, alpha, form):
        return None
    lo, hi = 0.0, 1.0
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (lo, mid) if reaches(rule, mid * n_eff, n_eff, target, alpha, form) else (mid, hi)
    return hi


def weighted_place(cumulative, total: float, rule: str, kept: float):
    """The index of the first positive, in falling score, at which the kept weight suffices. The quantile rule keeps more than its share."""
    import numpy as np

    want = kept * total
    at = np.searchsorted(cumulative, want * (1 + 1e-12), side="right") if rule == "quantile" else np.searchsorted(cumulative, want * (1 - 1e-12), side="left")
    return np.minimum(at, len(cumulative) - 1)
