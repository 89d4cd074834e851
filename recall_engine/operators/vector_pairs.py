"""All pairs of vectors with their cosine score, in blocks: a task multiplies two blocks as matrices.

Pairs are the square of the vectors, so they are made again for each reader and never kept. Each reader gets the same scores, bit by
bit: a block's vectors are in the order of their ids, and its tiles are multiplied in the same shapes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Vectors of a block where pairs are counted and where they are rows, and those that are multiplied at a time.
COUNT_BLOCK, ROW_BLOCK, TILE = 8192, 8192, 512
#: Blocks of a small table, so that it makes several tasks, and tasks of a large one.
LEAST_BLOCKS, MOST_TASKS = 8, 20_000
NEAR = 1e-9
BINS = 10
#: Equal parts of [0, 1] that tell the place of nearly all scores among some thresholds.
PLACES = 1 << 16


def _blocks(vectors: DataFrame, size: int, made: Callable[[dict, dict, bool], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """What ``made`` yields for each two blocks, and for each block with itself. ``vectors`` has vec_id, embedding and label."""
    n = vectors.count()
    blocks = max(1, -(-n // size), min(LEAST_BLOCKS, -(-n // TILE)))
    tasks = min(MOST_TASKS, blocks * (blocks + 1) // 2)
    kind = "float" if dict(vectors.dtypes)["embedding"] == "array<float>" else "double"  # widened by the tasks, which changes no value
    dtype = np.dtype(np.float32 if kind == "float" else np.float64)
    placed = vectors.select("vec_id", "label", F.col("embedding").cast(f"array<{kind}>").alias("e"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block"))

    def packed(table: pa.Table) -> pa.Table:
        e = table["e"].combine_chunks()
        ids, labels = table["vec_id"].to_numpy(), table["label"].to_numpy().astype(np.int64)
        x = e.flatten().to_numpy(zero_copy_only=False).reshape(len(e), -1)
        order = np.lexsort((labels, ids))
        columns = [pa.array([table["block"][0].as_py()], pa.int32()), *[pa.array([np.ascontiguousarray(v[order]).tobytes()], pa.binary()) for v in (ids, labels, x)]]
        return pa.Table.from_arrays(columns, names=["block", "ids", "labels", "x"])

    rows = placed.groupBy("block").applyInArrow(packed, "block int, ids binary, labels binary, x binary")
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other")
    keyed = rows.select("*", other).select(F.least("block", "other").cast("long").alias("i"), F.greatest("block", "other").cast("long").alias("j"), "block", "ids", "labels", "x")
    # Tasks of two blocks come before those of one, which take half the time.
    gap = F.col("j") - F.col("i")
    place = F.when(gap == 0, F.lit(blocks * (blocks - 1) // 2) + F.col("i")).otherwise((gap - 1) * F.lit(blocks) - F.expr("((j - i - 1) * (j - i)) div 2") + F.col("i"))
    dealt = keyed.repartitionById(tasks, (place % F.lit(tasks)).cast("int")).sortWithinPartitions("i", "j", "block")

    def side(r: dict) -> dict:
        ids = np.frombuffer(r["ids"], np.int64)
        x = np.frombuffer(r["x"], dtype).astype(np.float64).reshape(len(ids), -1)
        squares = np.zeros(len(ids))
        for k in range(x.shape[1]):  # in the order in which the vector's elements are added up elsewhere
            squares += x[:, k] * x[:, k]
        return {"id": ids, "label": np.frombuffer(r["labels"], np.int64), "x": x, "norm": np.sqrt(squares)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = (r for b in batches for k in range(b.num_rows) for r in b.slice(k, 1).to_pylist())
        for (i, j), group in groupby(each, lambda r: (r["i"], r["j"])):
            sides = [side(r) for r in group]
            if i == j or len(sides) == 2:
                yield from made(sides[0], sides[-1], i == j)

    return dealt.mapInArrow(run, schema)


def _score(dot: np.ndarray, norm: np.ndarray) -> np.ndarray:
    """(1 + cosine) / 2 within [0, 1]; one half beside a vector of length zero."""
    if norm.all():
        dot /= norm
    else:
        dot = np.divide(dot, norm, out=np.zeros_like(dot), where=norm != 0)
    dot += 1.0
    dot /= 2.0
    return np.clip(dot, 0.0, 1.0, out=dot)


def _tiles(a: dict, b: dict, same: bool, bins: int = BINS) -> Iterator[tuple[slice, slice, np.ndarray, np.ndarray | None]]:
    """(rows, columns, scores, which pairs count, None for all) of each two tiles; of a block with itself, each pair once. A pair whose
    score comes near a stratum's edge has its product added up element by element, as a plain loop does."""
    for lo in range(0, len(a["id"]), TILE):
        for at in range(lo if same else 0, len(b["id"]), TILE):
            r, c = slice(lo, lo + TILE), slice(at, at + TILE)
            p = _score(a["x"][r] @ b["x"][c].T, a["norm"][r][:, None] * b["norm"][c])
            place = p * bins
            edge = np.rint(place)
            k, m = np.nonzero(np.abs(place - edge) < NEAR * bins)
            inner = (edge[k, m] > 0.5) & (edge[k, m] < bins - 0.5)
            k, m = k[inner], m[inner]
            if len(k):
                dot = np.zeros(len(k))
                for e in range(a["x"].shape[1]):
                    dot += a["x"][r][k, e] * b["x"][c][m, e]
                p[k, m] = _score(dot, a["norm"][r][k] * b["norm"][c][m])
            yield r, c, p, np.triu(np.ones(p.shape, bool), 1) if same and at == lo else None


def _stratum(p: np.ndarray, bins: int) -> np.ndarray:
    """As ``strata.equal_width`` has it."""
    at = (np.nan_to_num(p) if np.isnan(p.sum()) else p) * bins
    return np.minimum(at.astype(np.int64), bins - 1)


def _counted(vectors: DataFrame, name: str, places: int, place: Callable[[np.ndarray], np.ndarray], bins: int = BINS) -> DataFrame:
    """(``name``, n, pos): the pairs of each place, below ``places``, that ``place`` finds for their scores, and those with equal labels."""

    def made(a: dict, b: dict, same: bool) -> Iterator[pa.RecordBatch]:
        n = np.zeros((places, 2), np.int64)
        for r, c, p, use in _tiles(a, b, same, bins):
            at = place(p)
            at *= 2
            at += a["label"][r][:, None] == b["label"][c]
            n += np.bincount(at.ravel() if use is None else at[use], minlength=2 * places).reshape(-1, 2)
        some = np.flatnonzero(n.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array(n.sum(axis=1)[some]), pa.array(n[some, 1])], names=[name, "n", "pos"])

    parts = _blocks(vectors, COUNT_BLOCK, made, f"{name} int, n long, pos long")
    return parts.groupBy(name).agg(F.sum("n").alias("n"), F.sum("pos").alias("pos"))


def score_histogram(vectors: DataFrame, bins: int = BINS) -> DataFrame:
    """(d, n, pos): the pairs of each stratum of the score, and those with equal labels."""
    return _counted(vectors, "d", bins, lambda p: _stratum(p, bins), bins)


def counts_by_place(vectors: DataFrame, values: list[float]) -> DataFrame:
    """(place, n, pos): the same by the number of the sorted ``values`` that the score is not below."""
    values = np.array(values, np.float64)
    # The place of all scores of a part, or -1 where a value lies in the part.
    ends = np.searchsorted(values, np.arange(PLACES + 2) / PLACES, side="left")
    known = np.where(ends[:-1] == ends[1:], ends[:-1], -1)

    def place(p: np.ndarray) -> np.ndarray:
        if np.isnan(p.sum()):  # no number is below one that is none
            return np.searchsorted(values, p, side="right")
        at = known[(p * PLACES).astype(np.int64)]
        open_ = at < 0
        at[open_] = np.searchsorted(values, p[open_], side="right")
        return at

    return _counted(vectors, "place", len(values) + 1, place)


def scored_pairs(vectors: DataFrame) -> DataFrame:
    """(pair_id, p, y, d) of every pair, the smaller id first."""

    def made(a: dict, b: dict, same: bool) -> Iterator[pa.RecordBatch]:
        for r, c, p, use in _tiles(a, b, same):
            k, m = np.nonzero(np.ones(p.shape, bool) if use is None else use)
            ids = np.concatenate([a["id"][r], b["id"][c]])
            names = pa.array(ids).cast(pa.string())
            m = m + p.shape[0]
            first = ids[k] <= ids[m]
            pair = pc.binary_join_element_wise(names.take(pa.array(np.where(first, k, m))), names.take(pa.array(np.where(first, m, k))), "|")
            y = a["label"][r][:, None] == b["label"][c]
            d = _stratum(p, BINS).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pair, *(pa.array(v.ravel() if use is None else v[use]) for v in (p, y, d))], names=["pair_id", "p", "y", "d"])

    return _blocks(vectors, ROW_BLOCK, made, "pair_id string, p double, y boolean, d int")
