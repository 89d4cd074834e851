"""Baseline: an inverse-probability estimate of recall with an interval, used as a lower bound."""

from __future__ import annotations

import numpy as np

from ..functions import special


def threshold(p: np.ndarray, w: np.ndarray, target_mille: int, alpha: float = 0.10) -> float | None:
    """The largest threshold whose estimated recall, less z standard errors, reaches the target; None if there is none.

    ``p`` are the scores of the sampled positives and ``w`` their inverse inclusion probabilities. The standard error is
    that of a linearised ratio of two weighted totals.
    """
    if not len(p):
        return None
    order = np.argsort(-p, kind="stable")
    p, w = p[order], w[order]
    total = w.sum()
    share = np.cumsum(w) / total
    # Sum over all positives of (w (1[kept] - share) / total)^2, from cumulated squares.
    kept, every = np.cumsum(w**2), (w**2).sum()
    variance = (kept * (1 - share) ** 2 + (every - kept) * share**2) / total**2
    bound = share - special.normal_quantile(1 - alpha) * np.sqrt(variance)
    ok = np.flatnonzero(bound >= target_mille / 1000 - 1e-15)
    return float(p[ok[0]]) if len(ok) else None
