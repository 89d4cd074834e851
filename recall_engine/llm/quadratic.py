"""Regularised quadratic discriminant for text quality.

Each text becomes a vector of statistics, transformed so that their distributions are nearer to normal. Per class the
mean and covariance are fitted from sums that every task pre-aggregates (one row of fixed size per class reaches the
driver). A covariance is shrunk twice, towards the pooled covariance and towards a multiple of the identity, and its
Cholesky factor is kept; a score is the logistic of the difference of the two classes' log densities, each a Mahalanobis
distance through the inverse of the kept factor, plus the log determinant.

Defined results: null text counts as empty and gets a score as any other; labels of a document are averaged if repeated;
with no labels, or of one class only, every score is the share of label 1 (0.5 without labels); a very long text is one
slice of its own in a worker, in memory of a few times its length; other columns, whatever their names, are not read; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import host_rules, textkit
from .scratch import cut

POOLED_SHRINKAGE = 0.3
RIDGE = 0.05
#: Log-density differences are divided by this before the logistic; statistics of one text are not independent.
TEMPERATURE = 4.0

STATISTICS = (
    "words", "word_length", "symbols", "dup_lines", "repeated", "upper", "digits", "exclamations", "bars", "stops",
    "commas", "lines", "line_words", "distinct", "top_word", "non_ascii", "long_words", "quotes",
)


def _share(part: np.ndarray, whole: np.ndarray) -> np.ndarray:
    """Log-odds of a share, with half a count added to either side."""
    return np.log((part + 0.5) / (np.maximum(whole - part, 0) + 0.5))


def statistics(texts: pa.Array) -> np.ndarray:
    """One row of transformed statistics per text."""
    raw, off = textkit.string_buffers(texts)
    n = len(texts)
    c = host_rules.rule_counts(texts)
    flat, bounds = textkit.words(raw, off)
    ids, values = textkit.codes(flat)
    docs = textkit.owner(bounds)
    nw, nc = c["n_words"].astype(float), c["word_chars"].astype(float)

    def bytes_in(mask: np.ndarray) -> np.ndarray:
        upto = np.concatenate([[0], np.cumsum(mask)])
        return (upto[off[1:]] - upto[off[:-1]]).astype(float)

    pair = docs * max(1, len(values)) + ids
    distinct, counts = np.unique(pair, return_counts=True)
    of = distinct // max(1, len(values))
    top = np.zeros(n)
    np.maximum.at(top, of, counts)
    long_word = (pc.utf8_length(values).to_numpy(zero_copy_only=False) > 12)[ids] if len(ids) else np.zeros(0, bool)
    lines = bytes_in(raw == 10) + 1
    columns = [
        np.log1p(nw),
        np.log((nc + 1) / (nw + 1)),
        _share(c["n_symbols"].astype(float), nc),
        np.log1p(c["n_dup_lines"]),
        _share(c["n_repeat_words"].astype(float), nw),
        _share(bytes_in((raw >= 65) & (raw <= 90)), nc),
        _share(bytes_in((raw >= 48) & (raw <= 57)), nc),
        _share(bytes_in(raw == 33), nc),
        _share(bytes_in(raw == 124), nc),
        _share(bytes_in(raw == 46), nc),
        _share(bytes_in(raw == 44), nc),
        np.log(lines),
        np.log((nw + 1) / lines),
        _share(np.bincount(of, minlength=n).astype(float), nw),
        _share(top, nw),
        _share(bytes_in(raw >= 192), nc),
        _share(np.bincount(docs, weights=long_word, minlength=n), nw),
        _share(bytes_in((raw == 34) | (raw == 39)), nc),
    ]
    return np.stack(columns, axis=1)


def described(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` and the vector ``x`` of statistics."""
    picked = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text}`").alias("__text__"))
    schema = T.StructType(picked.schema.fields[:-1] + [T.StructField("x", T.ArrayType(T.DoubleType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in textkit.slices(batches, "__text__"):
            x = statistics(b.column(b.num_columns - 1))
            bounds = np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.ListArray.from_arrays(pa.array(bounds), pa.array(x.ravel()))], names=[*b.schema.names[:-1], "x"])

    return picked.mapInArrow(run, schema)


def class_sums(labelled: DataFrame) -> dict[int, tuple[float, np.ndarray, np.ndarray]]:
    """Of each class: weight, sum of x, sum of x x'. Every task sends one row of fixed size per class."""
    d = len(STATISTICS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = {}
        for b in batches:
            y = b.column("y").to_numpy(zero_copy_only=False)
            x = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            for k in (0, 1):
                w = y if k else 1 - y
                n, s, q = sums.get(k, (0.0, np.zeros(d), np.zeros((d, d))))
                sums[k] = (n + w.sum(), s + w @ x, q + (x * w[:, None]).T @ x)
        for k, (n, s, q) in sums.items():
            yield pa.RecordBatch.from_pydict({"k": pa.array([k], pa.int32()), "v": pa.array([np.concatenate([[n], s, q.ravel()])])})

    parts = labelled.select("y", "x").mapInArrow(run, "k int, v array<double>")
    rows = parts.select("k", F.posexplode("v")).groupBy("k", "pos").agg(F.sum("col").alias("v")).collect()  # 2 * (1 + d + d * d) rows
    flat = {k: np.zeros(1 + d + d * d) for k in (0, 1)}
    for r in rows:
        flat[r.k][r.pos] = r.v
    return {k: (v[0], v[1 : d + 1], v[d + 1 :].reshape(d, d)) for k, v in flat.items()}


class Discriminant:
    """Class means, Cholesky factors and log determinants; ``score`` maps rows of statistics to [0, 1]."""

    def __init__(self, sums: dict[int, tuple[float, np.ndarray, np.ndarray]], pooled: float = POOLED_SHRINKAGE, ridge: float = RIDGE, temperature: float = TEMPERATURE):
        n = {k: v[0] for k, v in sums.items()}
        total = n[0] + n[1]
        self.prior = n[1] / total if total > 0 else 0.5
        self.temperature = temperature
        self.parts = None
        if min(n.values()) < 2:
            return
        d = len(sums[0][1])
        mean = {k: v[1] / v[0] for k, v in sums.items()}
        scatter = {k: v[2] - v[0] * np.outer(mean[k], mean[k]) for k, v in sums.items()}
        common = (scatter[0] + scatter[1]) / total
        self.scale = np.sqrt(np.maximum(np.diag(common), 1e-9))
        common = common / np.outer(self.scale, self.scale)
        self.parts = []
        for k in (0, 1):
            own = scatter[k] / n[k] / np.outer(self.scale, self.scale)
            cov = (1 - pooled) * own + pooled * common
            cov = (1 - ridge) * cov + ridge * np.trace(cov) / d * np.eye(d)
            factor = np.linalg.cholesky(cov)
            self.parts.append((mean[k] / self.scale, np.linalg.inv(factor), 2 * np.log(np.diag(factor)).sum()))

    def difference(self, x: np.ndarray) -> np.ndarray:
        """log p(x, class 1) - log p(x, class 0)."""
        z = x / self.scale
        logs = [-0.5 * (((z - m) @ inverse.T) ** 2).sum(axis=1) - 0.5 * det for m, inverse, det in self.parts]
        return logs[1] - logs[0] + np.log(self.prior / (1 - self.prior))

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.parts is None:
            return np.full(len(x), self.prior)
        return 1 / (1 + np.exp(-np.clip(self.difference(x) / self.temperature, -700, 700)))


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 3 == 1


def scored(docs: DataFrame, labels: DataFrame, text: str = "text", doc_id: str = "doc_id", label: str = "quality", **options) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of ``docs``. Labels of held-out documents are not read."""
    x = cut(described(docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("_body")), "_body"))
    known = labels.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{label}`").cast("double").alias("y")).where(~held_out(F.col("doc_id")) & F.col("y").isNotNull())
    known = known.groupBy("doc_id").agg(F.avg("y").alias("y"))
    model = Discriminant(class_sums(x.join(known, "doc_id")), **options)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                v = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(model.score(v))], names=["doc_id", "score"])

    kind = x.schema["doc_id"].dataType.simpleString()
    out = x.mapInArrow(run, f"doc_id {kind}, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
