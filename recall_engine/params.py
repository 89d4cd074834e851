"""Parameters of the calibration pipeline, by scale. Recall targets are integers in thousandths, so that ranks are exact."""

from __future__ import annotations

from dataclasses import dataclass, replace

TARGETS = (700, 800, 900)
RULES = ("exact_beta", "jeffreys", "wilson", "quantile")
#: Runs of the whole experiment on a workload.
TRIALS = 10
METHODS = ("ht_lower", "wilson_random", "wilson_hash", "ivw_single", "ivw_min")


@dataclass(frozen=True)
class Params:
    """``pool`` unstratified pairs, ``labels`` of them balanced for training; ``k`` calibration pairs in each of ``subsamples`` samples."""

    pool: int = 50_000
    labels: int = 1_000
    k: int = 250_000
    subsamples: int = 9
    n_boot: int = 200
    alpha: float = 0.10
    bins: int = 10
    base_seed: int = 2025
    net_seed: int = 42
    batch: int = 8_192

    def at_most(self, n: int) -> Params:
        """The same for ``n`` candidates: the pool is capped at n, a sample at half of n."""
        return replace(self, pool=min(self.pool, n), k=max(1, min(self.k, n // 2)))


PUBLISHED = Params()
