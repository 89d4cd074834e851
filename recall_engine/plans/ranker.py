"""The learned ranker: a small network trained on the driver from a balanced set of labels, applied to all pairs by Arrow batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import features, sampler

WIDTHS = (16, 128, 64, 1)
DROPOUT = (0.30, 0.50)
MOMENTUM, NORM_EPS = 0.1, 1e-5


@dataclass
class Network:
    """Dense layers with batch normalisation and dropout on the hidden ones: dense, norm, ReLU, dropout; a sigmoid ends it."""

    w: list[np.ndarray]
    b: list[np.ndarray]
    gamma: list[np.ndarray] = field(default_factory=list)
    beta: list[np.ndarray] = field(default_factory=list)
    mean: list[np.ndarray] = field(default_factory=list)
    var: list[np.ndarray] = field(default_factory=list)

    @staticmethod
    def init(seed: int = 42, widths: tuple[int, ...] = WIDTHS) -> Network:
        rng = np.random.default_rng(seed)
        pairs = list(zip(widths, widths[1:], strict=False))
        hidden = widths[1:-1]
        return Network(
            [rng.normal(0, np.sqrt(2 / a), (a, c)) for a, c in pairs], [np.zeros(c) for _, c in pairs],
            [np.ones(h) for h in hidden], [np.zeros(h) for h in hidden], [np.zeros(h) for h in hidden], [np.ones(h) for h in hidden],
        )

    def forward(self, x: np.ndarray, rng: np.random.Generator | None = None) -> tuple[np.ndarray, list[dict]]:
        """Scores and what the backward pass needs. With ``rng`` in training mode: batch statistics and dropout."""
        memory, h = [], x
        for k in range(len(self.w) - 1):
            z = h @ self.w[k] + self.b[k]
            if rng is None:
                m, v = self.mean[k], self.var[k]
            else:
                m, v = z.mean(axis=0), z.var(axis=0)
                self.mean[k] = (1 - MOMENTUM) * self.mean[k] + MOMENTUM * m
                self.var[k] = (1 - MOMENTUM) * self.var[k] + MOMENTUM * v * len(z) / max(1, len(z) - 1)
            scale = 1 / np.sqrt(v + NORM_EPS)
            unit = (z - m) * scale
            pre = unit * self.gamma[k] + self.beta[k]
            keep = np.ones_like(pre) if rng is None else (rng.random(pre.shape) >= DROPOUT[k]) / (1 - DROPOUT[k])
            memory.append({"in": h, "unit": unit, "scale": scale, "on": pre > 0, "keep": keep})
            h = np.where(pre > 0, pre, 0) * keep
        memory.append({"in": h})
        return 1 / (1 + np.exp(-np.clip((h @ self.w[-1] + self.b[-1])[:, 0], -60, 60))), memory

    def backward(self, p: np.ndarray, y: np.ndarray, memory: list[dict]) -> dict[str, list[np.ndarray]]:
        """Gradients of the mean binary cross-entropy."""
        g = {n: [None] * len(getattr(self, n)) for n in ("w", "b", "gamma", "beta")}
        d = ((p - y) / len(y))[:, None]
        g["w"][-1], g["b"][-1] = memory[-1]["in"].T @ d, d.sum(axis=0)
        d = d @ self.w[-1].T
        for k in range(len(self.w) - 2, -1, -1):
            m = memory[k]
            d = d * m["keep"] * m["on"]
            g["gamma"][k], g["beta"][k] = (d * m["unit"]).sum(axis=0), d.sum(axis=0)
            du = d * self.gamma[k]
            dz = m["scale"] * (du - du.mean(axis=0) - m["unit"] * (du * m["unit"]).mean(axis=0))
            g["w"][k], g["b"][k] = m["in"].T @ dz, dz.sum(axis=0)
            d = dz @ self.w[k].T
        return g

    def folded(self) -> tuple[list[np.ndarray], list[np.ndarray]]:
        """Weights and biases with the normalisation folded in, for inference."""
        w, b = [], []
        for k in range(len(self.w) - 1):
            s = self.gamma[k] / np.sqrt(self.var[k] + NORM_EPS)
            w.append(self.w[k] * s)
            b.append((self.b[k] - self.mean[k]) * s + self.beta[k])
        return [*w, self.w[-1]], [*b, self.b[-1]]

    def copy(self) -> Network:
        return Network(*[[a.copy() for a in getattr(self, n)] for n in ("w", "b", "gamma", "beta", "mean", "var")])

    def table(self, spark: SparkSession) -> DataFrame:
        """The folded weights as rows (layer, row, col, value); biases have row -1."""
        w, b = self.folded()
        rows = [(k, i, j, float(v)) for k, m in enumerate(w) for (i, j), v in np.ndenumerate(m)] + [(k, -1, j, float(v)) for k, m in enumerate(b) for j, v in enumerate(m)]
        return spark.createDataFrame(rows, "layer int, row int, col int, value double")


def cross_entropy(p: np.ndarray, y: np.ndarray) -> float:
    q = np.clip(p, 1e-12, 1 - 1e-12)
    return float(-(y * np.log(q) + (1 - y) * np.log(1 - q)).mean())


def fit(x: np.ndarray, y: np.ndarray, seed: int = 42, epochs: int = 30, patience: int = 3, rate: float = 1e-3, betas: tuple[float, float] = (0.9, 0.999), batch: int = 64, held: float = 0.2) -> Network:
    """Adam on binary cross-entropy, stopped when the held-out loss has not fallen for ``patience`` epochs. ``x`` in [0, 1]."""
    rng = np.random.default_rng(seed)
    net = Network.init(seed, (x.shape[1], *WIDTHS[1:]))
    order = rng.permutation(len(x))
    n_held = int(len(x) * held)
    test, train = order[:n_held], order[n_held:]
    names = ("w", "b", "gamma", "beta")
    first = {n: [np.zeros_like(a) for a in getattr(net, n)] for n in names}
    second = {n: [np.zeros_like(a) for a in getattr(net, n)] for n in names}
    best, best_loss, waited, step = net.copy(), np.inf, 0, 0
    for _ in range(epochs):
        shuffled = rng.permutation(train)
        for lo in range(0, len(shuffled), batch):
            part = shuffled[lo : lo + batch]
            if len(part) < 2:
                continue
            p, memory = net.forward(x[part], rng)
            g = net.backward(p, y[part], memory)
            step += 1
            for n in names:
                for k, a in enumerate(getattr(net, n)):
                    first[n][k] = betas[0] * first[n][k] + (1 - betas[0]) * g[n][k]
                    second[n][k] = betas[1] * second[n][k] + (1 - betas[1]) * g[n][k] ** 2
                    a -= rate * (first[n][k] / (1 - betas[0] ** step)) / (np.sqrt(second[n][k] / (1 - betas[1] ** step)) + 1e-8)
        at = test if len(test) else train
        loss = cross_entropy(net.forward(x[at])[0], y[at])
        if loss < best_loss - 1e-6:
            best, best_loss, waited = net.copy(), loss, 0
        else:
            waited += 1
            if waited >= patience:
                break
    return best


def _rounded(x: np.ndarray, dtype: str) -> np.ndarray:
    """``x`` as the nearest brain floats of 16 bits, kept in 32, if ``dtype`` asks for them; else as ``dtype``."""
    if dtype != "bfloat16":
        return x.astype(dtype)
    bits = np.ascontiguousarray(x, np.float32).view(np.uint32)
    return ((bits + 0x7FFF + ((bits >> 16) & 1)) & 0xFFFF0000).astype(np.uint32).view(np.float32)


def _applied(net: Network, dtype: str) -> Callable[[np.ndarray], np.ndarray]:
    """Features in [0, 1] to the last layer's sums, through the folded network."""
    w, b = net.folded()
    w, b = [_rounded(m, dtype) for m in w], [_rounded(m, dtype) for m in b]

    def run(x: np.ndarray) -> np.ndarray:
        h = _rounded(x, dtype)
        for k in range(len(w) - 1):
            h = _rounded(np.maximum(h @ w[k] + b[k], 0), dtype)
        return (h @ w[-1] + b[-1])[:, 0]

    return run


def sigmoid(z: Column) -> Column:
    """The score of a last sum."""
    return 1.0 / (1.0 + F.exp(-F.greatest(F.lit(-60.0), F.least(F.lit(60.0), z.cast("double")))))


def _over_features(df: DataFrame, keep: tuple[str, ...], batch: int, types: str, made: Callable[[np.ndarray], list[pa.Array]]) -> DataFrame:
    """``keep`` and what ``made`` makes of the scaled features f01..f16, in [0, 1], which are read once, in batches of at most ``batch`` rows."""
    n = len(keep)
    source = df.select(*keep, *features.NAMES)
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in source.schema.fields[:n]] + [types])
    names = [*keep, *[c.split()[0] for c in types.split(", ")]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, batch):
                r = whole.slice(lo, batch)
                x = np.stack([r.column(k).to_numpy(zero_copy_only=False) for k in range(n, r.num_columns)], axis=1) / features.TOP
                yield pa.RecordBatch.from_arrays([*r.columns[:n], *made(x)], names=names)

    return source.mapInArrow(run, schema)


def score_all(df: DataFrame, nets: list[Network], keep: tuple[str, ...] = ("pair_id",), dtype: str = "float32", batch: int = 8_192) -> DataFrame:
    """``keep`` and ps, the score of each network."""
    each = [_applied(net, dtype) for net in nets]

    def made(x: np.ndarray) -> list[pa.Array]:
        p = np.stack([1 / (1 + np.exp(-np.clip(f(x).astype(np.float64), -60, 60))) for f in each], axis=1)
        ends = pa.array(np.arange(0, p.size + 1, len(each), dtype=np.int32))
        return [pa.ListArray.from_arrays(ends, pa.array(p.ravel()))]

    return _over_features(df, keep, batch, "ps array<double>", made)


def sums_all(df: DataFrame, nets: list[Network], keep: tuple[str, ...] = ("pair_id",), batch: int = 8_192) -> DataFrame:
    """``keep`` and z0, z1, ..., each network's last sums in 32 bits; ``sigmoid`` makes them scores."""
    each = [_applied(net, "float32") for net in nets]
    return _over_features(df, keep, batch, ", ".join(f"z{k} float" for k in range(len(each))), lambda x: [pa.array(f(x)) for f in each])


def score(df: DataFrame, net: Network, keep: tuple[str, ...] = ("pair_id",), dtype: str = "float32", batch: int = 8_192) -> DataFrame:
    """``keep`` and p. ``dtype`` float64, float32 or bfloat16 is the precision of weights and activations."""
    return score_all(df, [net], keep, dtype, batch).select(*keep, F.col("ps")[0].alias("p"))


def balanced(scaled: DataFrame, relevant: Column, pool: int, n_pos: int, n_neg: int, seed: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Features in [0, 1], labels, and how many labels were asked for.

    The pool is labelled in key order until both classes are full or it ends; every check counts.
    """
    drawn = sampler.pool(scaled, pool, seed).select("hash_key", relevant.cast("int").alias("y"), *features.NAMES).orderBy("hash_key")
    rows = drawn.select("y", *features.NAMES).toPandas()  # at most ``pool`` rows
    y = rows["y"].to_numpy()
    place = np.where(y == 1, np.cumsum(y), np.cumsum(1 - y))
    use = place <= np.where(y == 1, n_pos, n_neg)
    full = np.flatnonzero((np.cumsum(y) >= n_pos) & (np.cumsum(1 - y) >= n_neg))
    cost = int(full[0]) + 1 if len(full) else len(y)
    use &= np.arange(len(y)) < cost
    return rows[list(features.NAMES)].to_numpy()[use] / features.TOP, y[use].astype(float), cost


def learned(scaled: DataFrame, relevant: Column, pool: int, labels: int, seed: int, net_seed: int = 42) -> tuple[Network, int]:
    x, y, cost = balanced(scaled, relevant, pool, labels // 2, labels // 2, seed)
    return fit(x, y, net_seed), cost


def mllib_scores(scaled: DataFrame, relevant: Column, pool: int, seed: int, kind: str = "logistic") -> DataFrame:
    """Alternative rankers of the standard library: ``logistic`` or ``perceptron``; pair_id and p of all pairs."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression, MultilayerPerceptronClassifier
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    train = sampler.pool(scaled, pool, seed).withColumn("label", relevant.cast("double"))
    model = LogisticRegression(maxIter=30) if kind == "logistic" else MultilayerPerceptronClassifier(layers=[16, 16, 2], seed=seed, maxIter=50)
    fitted = Pipeline(stages=[VectorAssembler(inputCols=list(features.NAMES), outputCol="features"), model]).fit(train)
    return fitted.transform(scaled).select("pair_id", vector_to_array("probability")[1].alias("p"))
