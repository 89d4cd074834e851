"""Hash-keyed samples of scored pairs, stratified by score.

A pair belongs to a sample if its key is among the smallest of its stratum. A cut-off on the key, a little above the share that
the quota needs, drops nearly all pairs inside the scan; only the rest is shuffled and ranked. The cut-off leaves too few
with a chance below 1e-15.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hashing


def sizes(df: DataFrame) -> dict[int, int]:
    """Pairs per stratum ``d``."""
    return {r["d"]: r["count"] for r in df.groupBy("d").count().collect()}  # one row per stratum


def quotas(n: dict[int, int], k: int, quota: str = "equal", refill: bool = False, sigma: dict[int, float] | None = None) -> dict[int, int]:
    """How many of each stratum: ``equal``, ``proportional`` or ``neyman`` (in proportion to size times ``sigma``)."""
    total = sum(n.values())
    k = min(k, total)
    if quota == "equal":
        want = {h: k // max(1, len(n)) for h in n}
        for h in sorted(n)[: k % max(1, len(n))]:
            want[h] += 1
        got = {h: min(n[h], want[h]) for h in n}
        while refill and (left := k - sum(got.values())) > 0:
            room = [h for h in sorted(n) if got[h] < n[h]]
            each = max(1, left // len(room))
            for h in room:
                add = min(each, n[h] - got[h], left)
                got[h], left = got[h] + add, left - add
        return got
    weight = {h: n[h] * (1.0 if quota == "proportional" or sigma is None else sigma[h]) for h in n}
    if quota == "proportional":
        got = {h: k * n[h] // total for h in n} if total else {}
        rest = sorted(n, key=lambda h: (-(k * n[h] % total), h))  # largest remainder
        for h in rest[: k - sum(got.values())]:
            got[h] += 1
        return got
    mass = sum(weight.values()) or 1.0
    return {h: min(n[h], max(1, round(k * weight[h] / mass))) for h in n}


def _by_stratum(values: dict[int, float], d: Column, other: float) -> Column:
    """The value of stratum ``d``, looked up in an array, so ``d`` is computed once."""
    if not values:
        return F.lit(other)
    least = min(values)
    table = F.array(*[F.lit(float(values.get(h, other))) for h in range(least, max(values) + 1)])
    return F.coalesce(F.get(table, d - least), F.lit(float(other)))


def cutoff(quota: int, n: int) -> float:
    """The share of keys that holds the ``quota`` smallest of ``n`` with a margin of eight standard deviations."""
    return 1.0 if quota >= n else min(1.0, (quota + 8 * math.sqrt(quota) + 40) / n)


def sample(df: DataFrame, k: int, seed: int, quota: str = "equal", family: str = "xxhash64", refill: bool = False, sigma: dict[int, float] | None = None, n: dict[int, int] | None = None) -> DataFrame:
    """The sample with hash_key, n_h, quota_h and the design weight w = n_h / quota_h. ``df`` has pair_id, p and d.

    ``global`` takes the k smallest keys of all strata together: a simple random sample, its weights all alike.
    """
    n = sizes(df) if n is None else n
    keyed = df.withColumn("hash_key", hashing.key(F.col("pair_id"), F.col("d"), seed, family))
    if quota == "global":
        total = sum(n.values())
        k = min(k, total)
        near = keyed.where(hashing.below(F.col("hash_key"), F.lit(cutoff(k, total)), family))
        return near.orderBy("hash_key").limit(k).withColumns({"n_h": F.lit(total).cast("long"), "quota_h": F.lit(k).cast("long"), "w": F.lit(total / max(1, k))})
    q = quotas(n, k, quota, refill, sigma)
    share = _by_stratum({h: cutoff(q[h], n[h]) if q[h] else 0.0 for h in n}, F.col("d"), 0.0)
    near = keyed.where(hashing.below(F.col("hash_key"), share, family))
    rank = F.row_number().over(Window.partitionBy("d").orderBy("hash_key"))
    quota_of = _by_stratum({h: float(v) for h, v in q.items()}, F.col("d"), 0.0)
    chosen = near.withColumn("_r", rank).where(F.col("_r") <= quota_of).drop("_r")
    size_of = _by_stratum({h: float(v) for h, v in n.items()}, F.col("d"), 0.0)
    return chosen.withColumns({"n_h": size_of.cast("long"), "quota_h": quota_of.cast("long"), "w": size_of / quota_of})


def pool(df: DataFrame, k: int, seed: int, family: str = "xxhash64") -> DataFrame:
    """An unstratified sample of pairs that need no score yet."""
    total = df.count()
    d0 = df.withColumn("d", F.lit(0)) if "d" not in df.columns else df
    keyed = d0.withColumn("hash_key", hashing.key(F.col("pair_id"), F.lit(0), seed, family))
    return keyed.where(hashing.below(F.col("hash_key"), F.lit(cutoff(min(k, total), max(1, total))), family)).orderBy("hash_key").limit(k)


def subsamples(df: DataFrame, count: int, k: int, seed: int, mode: str = "reseed", quota: str = "proportional", family: str = "xxhash64", n: dict[int, int] | None = None) -> DataFrame:
    """``count`` samples with column ``subsample``: a seed each (``reseed``), or one sample of count * k dealt out by key (``split``)."""
    n = sizes(df) if n is None else n
    if mode == "split":
        whole = sample(df, count * k, seed, quota, family, n=n)
        place = F.row_number().over(Window.partitionBy("d").orderBy("hash_key")) - 1
        dealt = whole.withColumn("subsample", (place % count).cast("int"))
        per = dealt.groupBy("d", "subsample").agg(F.count("*").alias("_q")).withColumnsRenamed({"d": "_d", "subsample": "_s"})
        joined = dealt.join(F.broadcast(per), (F.col("d") == F.col("_d")) & (F.col("subsample") == F.col("_s")))  # strata times count rows
        return joined.withColumns({"quota_h": F.col("_q"), "w": F.col("n_h") / F.col("_q")}).drop("_d", "_s", "_q")
    q = quotas(n, k, quota)
    share = _by_stratum({h: cutoff(q[h], n[h]) if q[h] else 0.0 for h in n}, F.col("d"), 0.0)
    # One pass: all keys of a pair side by side, and only those below the cut-off go on.
    keys = F.array(*[F.struct(F.lit(j).alias("subsample"), hashing.key(F.col("pair_id"), F.col("d"), seed + j, family).alias("hash_key")) for j in range(count)])
    hits = F.filter(keys, lambda x: hashing.below(x["hash_key"], share, family))
    near = df.select("*", F.explode(hits).alias("_h")).select(*df.columns, "_h.subsample", "_h.hash_key")
    rank = F.row_number().over(Window.partitionBy("subsample", "d").orderBy("hash_key"))
    quota_of = _by_stratum({h: float(v) for h, v in q.items()}, F.col("d"), 0.0)
    size_of = _by_stratum({h: float(v) for h, v in n.items()}, F.col("d"), 0.0)
    chosen = near.withColumn("_r", rank).where(F.col("_r") <= quota_of).drop("_r")
    return chosen.withColumns({"n_h": size_of.cast("long"), "quota_h": quota_of.cast("long"), "w": size_of / quota_of})


#: The seed of a simple random sample differs from that of a stratified one by these bits.
RANDOM = 0x5DEECE66D


@dataclass(frozen=True)
class Draw:
    """A sample by its seed: of each stratum in ``n`` (its pairs) the ``q`` smallest keys. ``plain`` is a simple random one, of the one
    stratum 0 that holds all pairs."""

    seed: int
    plain: bool
    n: dict[int, int]
    q: dict[int, int]

    def weight(self, d: np.ndarray) -> np.ndarray:
        """The design weight of each row by its stratum."""
        if self.plain:
            return np.ones(len(d))
        return _looked_up({h: self.n[h] / self.q[h] if self.q[h] else np.nan for h in self.n}, d, np.float64)


def _looked_up(values: dict[int, float], d: np.ndarray, dtype: type) -> np.ndarray:
    known = np.array(sorted(values))
    return np.array([values[h] for h in known], dtype)[np.searchsorted(known, d)]


def _keyed(df: DataFrame, draws: list[Draw], *more: str) -> DataFrame:
    """d, ``more`` and the key of each draw, k0, k1, ..."""
    keys = [f"{hashing.key_sql('0' if x.plain else 'd', x.seed)} AS k{i}" for i, x in enumerate(draws)]
    return df.selectExpr("CAST(d AS INT) AS d", *more, *keys)


def _of_strata(draw: Draw, values: dict[int, float], known: list[int], dtype: type) -> np.ndarray:
    """The draw's value of each of the strata ``known``, 0 where there are no pairs."""
    return np.array([values.get(0 if draw.plain else h, 0) for h in known], dtype)


class TooFew(ValueError):
    """A sample needs more pairs than there are."""


def _key_at(share: float) -> int:
    """The key that has this share of all below it."""
    least, most = -(1 << 63), (1 << 63) - 1
    return min(most, max(least, int(share * (1 << 64)) + least))


def near(df: DataFrame, draws: list[Draw]) -> DataFrame:
    """The pairs whose key is not above the cut of some draw and its margin: a few times the draws' quotas, however many pairs there are.
    ``cuts`` and ``taken`` find the same in them as in all pairs, or raise TooFew where the margin was too small."""
    tests = []
    for x in draws:
        upto = {h: _key_at(cutoff(x.q[h], x.n[h])) for h in x.n if x.q[h]}
        if upto and x.plain:
            tests.append(f"{hashing.key_sql('0', x.seed)} <= {_long(upto[0])}")
        elif upto:
            table = ", ".join(_long(upto.get(h)) for h in range(min(upto), max(upto) + 1))
            tests.append(f"{hashing.key_sql('d', x.seed)} <= get(array({table}), CAST(d AS INT) - {min(upto)})")
    return df.where(" OR ".join(tests) or "false")


def _long(x: int | None) -> str:
    """An SQL literal; the least one can't be written as a number."""
    return f"CAST({'NULL' if x is None else repr(str(x))} AS BIGINT)"


def cuts(df: DataFrame, draws: list[Draw]) -> list[dict[int, int | None]]:
    """Of each draw and stratum the largest key taken, exactly, or None if none is. One pass over the pairs serves all draws: keys that
    are surely taken are counted, and only those around the cut, within eight standard deviations, leave the scan."""
    least, most = -(1 << 63), (1 << 63) - 1
    known = sorted({h for x in draws if not x.plain for h in x.n}) or [0]
    found = [{h: None if not x.q[h] else most for h in x.n} for x in draws]
    open_ = {(i, h) for i, x in enumerate(draws) for h in x.n if 0 < x.q[h] < x.n[h]}

    narrow = True
    while open_:
        bounds = []  # below the first, a key is surely taken; above the second, surely not
        for i, x in enumerate(draws):
            lo, hi = {}, {}
            for h in x.n:
                if (i, h) not in open_:  # nothing to find
                    lo[h], hi[h] = least, least
                elif narrow:
                    lo[h], hi[h] = _key_at((x.q[h] - 8 * math.sqrt(x.q[h]) - 40) / x.n[h]), _key_at(cutoff(x.q[h], x.n[h]))
                else:
                    lo[h], hi[h] = least, most
            bounds.append((lo, hi))
        # A row of the tables per draw, a column per stratum.
        low, high = (np.stack([_of_strata(x, b[k], known, np.int64) for x, b in zip(draws, bounds, strict=True)]) for k in range(2))
        named = [(i, np.zeros(len(known), np.int32) if x.plain else np.array(known, np.int32)) for i, x in enumerate(draws)]

        def near(batches: Iterator[pa.RecordBatch], low=low, high=high, named=named, known=np.array(known)) -> Iterator[pa.RecordBatch]:
            below = np.zeros(low.shape, np.int64)
            for b in batches:
                at = np.minimum(np.searchsorted(known, b.column(0).to_numpy(zero_copy_only=False)), len(known) - 1)
                found = []
                for i, strata in named:
                    key = b.column(i + 1).to_numpy(zero_copy_only=False)
                    lo = low[i][at]
                    under = key < lo
                    below[i] += np.bincount(at[under], minlength=len(known))
                    around = np.flatnonzero(~under & (key <= high[i][at]))
                    if len(around):
                        found.append((np.full(len(around), i), strata[at[around]], key[around], np.full(len(around), -1)))
                if found:  # one batch for all draws
                    yield made(*map(np.concatenate, zip(*found, strict=True)))
            for i, strata in named:
                yield made(np.full(len(known), i), strata, np.zeros(len(known)), below[i])

        def made(i: np.ndarray, h: np.ndarray, key: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
            types = zip((i, h, key, n), (np.int32, np.int32, np.int64, np.int64), strict=True)
            return pa.RecordBatch.from_arrays([pa.array(x.astype(t)) for x, t in types], names=["i", "h", "key", "below"])

        rows = _keyed(df, draws).mapInArrow(near, "i int, h int, key long, below long").withColumn("around", F.col("below") == -1).withColumn("below", F.greatest("below", F.lit(0)))
        # Of each draw and stratum some thousands of keys, whatever the number of pairs.
        keys = F.sort_array(F.collect_list(F.when(F.col("around"), F.col("key"))))
        per = rows.groupBy("i", "h").agg(F.sum("below").alias("below"), keys.alias("keys"))
        quota = df.sparkSession.createDataFrame([(i, h, draws[i].q[h]) for i, h in sorted(open_)], "i int, h int, q long")
        last = per.join(F.broadcast(quota), ["i", "h"]).select("i", "h", F.get("keys", (F.col("q") - F.col("below") - 1).cast("int")).alias("key"))
        left = set(open_)
        for r in last.where("key IS NOT NULL").collect():  # a row per draw and stratum
            found[r.i][r.h] = r.key
            left.discard((r.i, r.h))
        if left and not narrow:
            raise TooFew("the pairs changed between two passes")
        open_, narrow = left, False
    return found


#: A positive of a sample as it travels, many of them in one value.
PACKED = np.dtype([("p", "<f8"), ("hash_key", "<i8"), ("d", "<i4")])
PACKED_BYTES = 4 << 20


def taken(df: DataFrame, draws: list[Draw], together: list[list[int]]) -> DataFrame:
    """The positives of every draw, in values of many (draw, packed), in one pass and without a shuffle of pairs. For each list of
    draws in ``together`` also rows with draw -1, -2, ... and ``pairs``, whose sum is the number of distinct pairs in them."""
    at = cuts(df, draws)
    known = sorted({h for x in draws if not x.plain for h in x.n}) or [0]
    upto = np.stack([_of_strata(x, {h: -(1 << 63) if c is None else c for h, c in of.items()}, known, np.int64) for x, of in zip(draws, at, strict=True)])
    some = np.stack([_of_strata(x, {h: c is not None for h, c in of.items()}, known, bool) for x, of in zip(draws, at, strict=True)])

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, pairs = [[] for _ in some], 0, [0] * len(together)

        def made(draw: list[int], packed: list[bytes], pairs: list[int]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(draw, pa.int32()), pa.array(packed, pa.binary()), pa.array(pairs, pa.int64())], names=["draw", "packed", "pairs"])

        def sent() -> Iterator[pa.RecordBatch]:
            for i, rows in enumerate(held):
                if rows:
                    yield made([i], [b"".join(rows)], [0])
                    rows.clear()

        for b in batches:
            d, p, y = (b.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            y = np.asarray(y == True, bool)  # noqa: E712, unknown labels are none
            h = np.minimum(np.searchsorted(known, d), len(known) - 1)
            mine = []
            for i in range(len(some)):
                key = b.column(i + 3).to_numpy(zero_copy_only=False)
                mine.append((key <= upto[i][h]) & some[i][h])
                use = np.flatnonzero(mine[-1] & y)
                if len(use):
                    rows = np.empty(len(use), PACKED)
                    rows["p"], rows["hash_key"], rows["d"] = p[use], key[use], d[use]
                    held[i].append(rows.tobytes())
                    size += rows.nbytes
            for j, group in enumerate(together):
                pairs[j] += int(np.logical_or.reduce([mine[i] for i in group]).sum())
            if size >= PACKED_BYTES:
                yield from sent()
                size = 0
        yield from sent()
        yield made([-1 - j for j in range(len(together))], [b""] * len(together), pairs)

    return _keyed(df, draws, "p", "y").mapInArrow(members, "draw int, packed binary, pairs long")


def random(df: DataFrame, k: int, seed: int, family: str = "xxhash64") -> DataFrame:
    """Baseline: a simple random sample under a seed of its own, stable under any partitioning."""
    return pool(df, k, seed ^ RANDOM, family).withColumns({"w": F.lit(1.0)})
