"""Special functions on the driver: incomplete beta, its inverse, normal and Student quantiles."""

from __future__ import annotations

import math
from statistics import NormalDist

import numpy as np


def betainc(a: float, b: float, x: float) -> float:
    """The regularised incomplete beta function, by its continued fraction."""
    if x <= 0.0 or x >= 1.0:
        return 0.0 if x <= 0.0 else 1.0
    if x > (a + 1) / (a + b + 2):
        return 1.0 - betainc(b, a, 1.0 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    return min(1.0, front / _fraction(a, b, x))


def _fraction(a: float, b: float, x: float) -> float:
    """The continued fraction of the incomplete beta function."""
    tiny = 1e-300
    f, c, d = 1.0, 1.0, 0.0
    for i in range(1, 400_000):
        m = i // 2
        if i % 2:
            term = -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))
        else:
            term = m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m))
        d = 1.0 + term * d
        d = 1.0 / (d if abs(d) > tiny else tiny)
        c = 1.0 + term / c
        c = c if abs(c) > tiny else tiny
        f *= c * d
        if abs(c * d - 1.0) < 1e-15:
            break
    return f


def binomial_tail(n: int, p: float, k: int) -> float:
    """P(Binomial(n, p) >= k)."""
    return 1.0 if k <= 0 else 0.0 if k > n else betainc(k, n - k + 1, p)


def binomial_tails(n: int, p: np.ndarray, k: int) -> np.ndarray:
    """The same for many p at once."""
    if k <= 0 or k > n:
        return np.full(len(p), 1.0 if k <= 0 else 0.0)
    return _betaincs(float(k), float(n - k + 1), np.asarray(p, float))


def _betaincs(a: float, b: float, x: np.ndarray) -> np.ndarray:
    out = np.where(x >= 1.0, 1.0, 0.0)
    inner = (x > 0.0) & (x < 1.0)
    turned = inner & (x > (a + 1) / (a + b + 2))
    if turned.any():
        out[turned] = 1.0 - _below_turn(b, a, 1.0 - x[turned])
    plain = inner & ~turned
    if plain.any():
        out[plain] = _below_turn(a, b, x[plain])
    return out


def _below_turn(a: float, b: float, x: np.ndarray) -> np.ndarray:
    """``betainc`` where its continued fraction converges fast; an element stops changing once it has converged."""
    tiny = 1e-300
    f, c, d = np.ones_like(x), np.ones_like(x), np.zeros_like(x)
    going = np.ones(len(x), bool)
    for i in range(1, 400_000):
        m = i // 2
        term = (-(a + m) * (a + b + m) / ((a + 2 * m) * (a + 2 * m + 1)) if i % 2 else m * (b - m) / ((a + 2 * m - 1) * (a + 2 * m))) * x
        d = 1.0 + term * d
        d = 1.0 / np.where(np.abs(d) > tiny, d, tiny)
        c = 1.0 + term / c
        c = np.where(np.abs(c) > tiny, c, tiny)
        f = np.where(going, f * c * d, f)
        going &= np.abs(c * d - 1.0) >= 1e-15
        if not going.any():
            break
    front = np.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * np.log(x) + b * np.log1p(-x)) / a
    return np.minimum(1.0, front / f)


def beta_quantile(q: float, a: float, b: float) -> float:
    lo, hi = 0.0, 1.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if betainc(a, b, mid) < q else (lo, mid)
        if hi - lo < 1e-15:
            break
    return (lo + hi) / 2


def normal_quantile(q: float) -> float:
    return NormalDist().inv_cdf(q)


def student_quantile(q: float, df: int) -> float:
    """The quantile of Student's t, for q of one half and more."""
    if q == 0.5:
        return 0.0
    x = beta_quantile(2 * (1 - q), df / 2, 0.5)
    return math.sqrt(df * (1 - x) / x)
