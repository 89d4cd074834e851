"""Best-fit packing of token sequences by linear grouping.

Only the histogram of piece lengths (one count per length up to the capacity, whatever the corpus) reaches the driver.
There, long pieces are sorted, put into groups of equal cardinality and rounded up to their group's longest; the few
sizes left are filled into configurations, one subset-sum each, taken as often as the counts allow. Actual lengths then
take the places of the rounded ones, which leaves the bins a little more room, and short pieces go where they fit best.

The plan is a list of runs: the pieces of one length with ranks r0 .. r0 + n go, k to a sequence, into consecutive
sequences at one offset. Its size depends on the capacity alone. Ranks within a length are prefix sums over hash buckets
and then inside a bucket, so a length or group of copies that a third of all rows share is spread over many tasks.

Defined results: null or empty text is the end id alone, one piece of length 1; rows that repeat a doc_id are pieces of
their own; a very long text is one slice of its own in a worker; other columns, whatever their names, are not read; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import encoding, textkit
from .scratch import cut

CAPACITY = 2048
GROUPS = 96
#: Pieces up to this share of the capacity are short: they fill gaps.
SHORT = 1 / 16
RANK_BUCKETS = 1 << 9


def linear_groups(counts: dict[int, int], groups: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Lengths, longest first, in groups of equal cardinality: (rounded size, [(length, count), ...]). A length is in several groups if its count asks for it."""
    total = sum(counts.values())
    quota = max(1, -(-total // groups))
    out, room = [], 0
    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            if not room:
                out.append((length, []))
                room = quota
            n = min(left, room)
            out[-1][1].append((length, n))
            left, room = left - n, room - n
    return out


def fullest(sizes: list[int], available: list[int], room: int) -> list[int]:
    """How many of each size fill ``room`` best (bounded subset sum)."""
    item = np.full(room + 1, -1, np.int64)  # the item that first reached a sum
    item[0] = -2
    items = []
    for g, s in enumerate(sizes):
        most, n = min(available[g], room // s if s else 0), 1
        while most > 0:
            n_now = min(n, most)
            w = n_now * s
            if w <= room:
                new = np.flatnonzero((item[: room + 1 - w] != -1) & (item[w:] == -1)) + w
                item[new] = len(items)
                items.append((g, n_now, w))
            most -= n_now
            n *= 2
        if item[room] != -1:
            break
    at = int(np.flatnonzero(item != -1)[-1])
    taken = [0] * len(sizes)
    while at:
        g, n, w = items[item[at]]
        taken[g] += n
        at -= w
    return taken


def configurations(sizes: list[int], demands: list[int], capacity: int) -> list[tuple[list[int], int]]:
    """Patterns (how many of each size) and how often each is used, until all demands are met. Sizes fall."""
    left, out = list(demands), []
    while any(left):
        g = next(k for k, n in enumerate(left) if n)
        free = list(left)
        free[g] -= 1
        pattern = fullest(sizes, free, capacity - sizes[g])
        pattern[g] += 1
        times = min(n // p for n, p in zip(left, pattern, strict=True) if p)
        out.append((pattern, times))
        left = [n - p * times for n, p in zip(left, pattern, strict=True)]
    return out


def substituted(groups: list[tuple[int, list[tuple[int, int]]]], patterns: list[tuple[list[int], int]]) -> list[tuple[Counter, int]]:
    """Bins with actual lengths: (how many of each length, number of such bins)."""
    queues = [list(members) for _, members in groups]
    bins: Counter = Counter()
    for pattern, times in patterns:
        slots = []
        for g, n in enumerate(pattern):
            for _ in range(n):
                runs, need = [], times
                while need:
                    length, have = queues[g][0]
                    use = min(have, need)
                    runs.append((length, use))
                    need -= use
                    queues[g][0] = (length, have - use)
                    if have == use:
                        queues[g].pop(0)
                slots.append(runs)
        edges = sorted({0, *(e for runs in slots for e in np.cumsum([n for _, n in runs]).tolist())})
        ends = [np.cumsum([n for _, n in runs]) for runs in slots]
        for lo, hi in zip(edges, edges[1:], strict=False):
            content = Counter(runs[int(np.searchsorted(e, lo, side="right"))][0] for runs, e in zip(slots, ends, strict=True))
            bins[tuple(sorted(content.items()))] += hi - lo
    return [(Counter(dict(content)), n) for content, n in bins.items()]


def fill_gaps(bins: list[tuple[Counter, int]], short: dict[int, int], capacity: int) -> list[tuple[Counter, int]]:
    """Best fit of the short lengths, longest first; what fits nowhere opens bins."""
    by_room: dict[int, list[tuple[Counter, int]]] = {}

    def put(content: Counter, n: int) -> None:
        if n:
            by_room.setdefault(capacity - sum(k * v for k, v in content.items()), []).append((content, n))

    for content, n in bins:
        put(content, n)
    for length in sorted(short, reverse=True):
        left = short[length]
        while left:
            room = min((r for r in by_room if r >= length), default=None)
            if room is None:
                each = capacity // length
                put(Counter({length: each}), left // each)
                put(Counter({length: left % each}) if left % each else Counter(), int(left % each > 0))
                break
            each, (content, n) = room // length, by_room[room].pop()
            if not by_room[room]:
                del by_room[room]
            full = min(n, left // each)
            put(content + Counter({length: each}), full)
            left -= full * each
            if full < n:
                if left and left < each:
                    put(content + Counter({length: left}), 1)
                    left, full = 0, full + 1
                put(content, n - full)
    return [b for same in by_room.values() for b in same]


def packing_plan(histogram: dict[int, int], capacity: int = CAPACITY, groups: int = GROUPS, short: float = SHORT) -> dict[str, np.ndarray]:
    """Runs sorted by (length, rank): length, rank, sequence, each, offset. ``sequences`` has their number."""
    limit = int(capacity * short)
    long = {k: n for k, n in histogram.items() if limit < k and n}
    grouped = linear_groups(long, groups)
    patterns = configurations([s for s, _ in grouped], [sum(n for _, n in m) for _, m in grouped], capacity)
    bins = fill_gaps(substituted(grouped, patterns), {k: n for k, n in histogram.items() if k <= limit and n}, capacity)
    rows, rank, sequence = [], Counter(), 0
    for content, n in bins:
        offset = 0
        for length, each in sorted(content.items(), reverse=True):
            rows.append((length, rank[length], sequence, each, offset))
            rank[length] += n * each
            offset += length * each
        sequence += n
    table = np.array(sorted(rows), np.int64).reshape(-1, 5)
    return dict(zip(("length", "rank", "sequence", "each", "offset"), table.T, strict=True)) | {"sequences": sequence}


def pieces(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: the ended ids of each document, cut after every ``capacity``."""
    picked = docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("_text"))
    schema = T.StructType([picked.schema["doc_id"], *[T.StructField(n, t) for n, t in (("piece", T.IntegerType()), ("start", T.LongType()), ("length", T.LongType()), ("ids_crc32", T.LongType()))]])

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, flat, bounds in encoding.encoded(batches, tokenizer, end_id):
            size = np.diff(bounds)
            n = -(-size // capacity)
            doc = np.repeat(np.arange(len(size)), n)
            piece = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
            length = np.minimum(capacity, size[doc] - piece * capacity)
            at = bounds[doc] + piece * capacity
            crcs = np.fromiter((encoding.crc32(flat[a : a + m]) for a, m in zip(at.tolist(), length.tolist(), strict=True)), np.int64, len(doc))
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pa.array(doc)), pa.array(piece.astype(np.int32)), pa.array(piece * capacity), pa.array(length), pa.array(crcs)], names=["doc_id", "piece", "start", "length", "ids_crc32"]
            )

    return picked.mapInArrow(run, schema)


def ranked(parts: DataFrame, buckets: int = RANK_BUCKETS) -> DataFrame:
    """``parts`` with ``rank``: 0, 1, ... among the rows of equal length."""
    spread = parts.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(buckets)).cast("int"))
    counts = spread.groupBy("length", "bucket").agg(F.count("*").alias("n"))
    earlier = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("before", F.coalesce(F.sum("n").over(earlier), F.lit(0))).drop("n")
    inside = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")) - 1
    return spread.withColumn("inside", inside).join(counts, ["length", "bucket"]).withColumn("rank", F.col("before") + F.col("inside")).drop("bucket", "before", "inside")


def packed(docs: DataFrame, tokenizer: str, end_id: int = 0, capacity: int = CAPACITY, text: str = "text", doc_id: str = "doc_id", groups: int = GROUPS) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    parts = cut(pieces(docs, tokenizer, end_id, capacity, text, doc_id))
    histogram = {r["length"]: r["count"] for r in parts.groupBy("length").count().collect()}  # at most ``capacity`` rows
    plan = packing_plan(histogram, capacity, groups)
    placed = ranked(parts)
    names = parts.columns
    schema = T.StructType([*parts.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shift = 1 << 44
        key = plan["length"] * shift + plan["rank"]
        for b in batches:
            length, rank = (b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            i = np.searchsorted(key, length * shift + rank, side="right") - 1
            step = rank - plan["rank"][i]
            sequence = plan["sequence"][i] + step // plan["each"][i]
            offset = plan["offset"][i] + step % plan["each"][i] * length
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(c)) for c in names), pa.array(sequence), pa.array(offset)], names=[*names, "sequence_id", "offset"])

    return placed.mapInArrow(run, schema)
