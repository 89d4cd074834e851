"""N-gram Jaccard join by parity sketches.

A document's set is its distinct word shingles, as 64-bit hashes. Per size band the hash space is cut into parts; a
part of a document holds the parity word (XOR) of the hashes that fall into it. A shingle that only one of two
documents has changes one part, so documents whose sets differ in at most k shingles have equal parity words in all but
k parts (pigeonhole): of the first k + 1 non-empty parts of either, in any order common to both, one is the same. A set
whose shingles fall into no more than k parts sends its first k + 1 shingles too: if no part is the same, that holds for
both sets, and as a link's sets have more than k shingles, one of those is the same. With Jaccard similarity at least t, k is at most
(1 - t) / (1 + t) times the sum of the sizes. Parts that hold frequent
shingles come last in the order, so passages and lines that many documents share hardly ever make candidates.

Buckets are compared on a second, finer sketch of one bit per shingle hash, whose Hamming distance is a lower bound of
the symmetric difference; what it leaves is verified on the whole sets. Documents with equal sets are one node from the
start, named by 128 bits.

Only connected components are asked for, so not every pair of a bucket is made. In each of a few rounds a node gives one
pair at most: with the nearest node, by sketch, of another component in any of its buckets. The verified links join
components, and most of a bucket soon is one. What then remains, pairs of one bucket, of different components, near enough
by size and sketch and not tried yet, is made in whole, each pair in one bucket only, and verified. No link between
components is missed. Large buckets are compared in chunks in the rounds, which cost in proportion to their nodes, and in
blocks, nodes outside the largest component against all, at the end.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkit
from .scratch import cut, release, shuffle_partitions

WIDTH = 5
#: Similarity as a fraction: 100 * intersection >= 75 * union.
SIMILARITY = (75, 100)
BAND_RATIO = 8
FREQUENT_LIST = 1 << 17
#: Text that a worker handles at a time, and keys that it gathers before it sends them: both bound its memory.
SLICE_BYTES = 1_000_000
SEND_KEYS = 500_000
#: Keys that meet in one group, on average, and the number of one batch's nodes from which on a key's nodes don't go there.
MEET_KEYS = 500_000
HOT_KEY = 64
ROUNDS = 2
#: Nodes of a bucket that a round compares with each other, and bits of a sketch for a shingle.
CHUNK = 2048
SKETCH_BITS = 2
#: Buckets that a node's row names, to give each pair in one bucket only.
NAMED_BUCKETS = 64
#: Rows of some tens of bytes up to which a table is broadcast.
BROADCAST_ROWS = 1_000_000
#: Links up to which one task finds the components; beyond, rounds of joins do.
SMALL_GRAPH = 1_000_000
_ODD = np.uint64(0x9E3779B97F4A7C15)


def shingles(texts: pa.Array, width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, sorted (uint64), and bounds (n + 1). Lower-cases A to Z.

    Hashes of 64 bits stand for shingles: two of a pair of sets of m and n shingles agree by accident with a chance of
    m * n / 2^64.
    """
    raw, off = textkit.string_buffers(texts)
    word, bounds = textkit.word_hashes(textkit.lower_ascii(raw), off)
    count = np.diff(bounds)
    n = len(word)
    factor = textkit.mix64(np.arange(1, width + 1, dtype=np.uint64)) | np.uint64(1)
    whole = max(0, n - width + 1)
    h = np.zeros(whole, np.uint64)
    for j in range(width):
        h += word[j : whole + j] * factor[j]
    # Windows that stay inside their text, then the texts of fewer words, each one shingle of all its words.
    span = np.maximum(count - width + 1, 0)
    docs = np.repeat(np.arange(len(count)), span)
    h = h[np.repeat(bounds[:-1] - (np.cumsum(span) - span), span) + np.arange(len(docs))] if len(docs) else np.zeros(0, np.uint64)
    short = np.flatnonzero((count > 0) & (count < width))
    if len(short):
        few = np.array([(word[bounds[k] : bounds[k + 1]] * factor[: count[k]]).sum() + np.uint64(count[k]) for k in short], np.uint64)
        at = np.searchsorted(docs, short)
        h, docs = np.insert(h, at, few), np.insert(docs, at, short)
    h = textkit.mix64(h)
    edges = np.searchsorted(docs, np.arange(len(count) + 1))
    for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        h[lo:hi].sort()
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (docs[1:] != docs[:-1])
    h, docs = h[new], docs[new]
    return h, np.searchsorted(docs, np.arange(len(count) + 1))


def node_ids(h: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """A 128-bit name per set (two columns), equal for equal sets; some two of n sets share a name with a chance of n^2 / 2^129."""
    size = np.diff(bounds).astype(np.uint64)
    out = np.empty((len(size), 2), np.uint64)
    for k, seed in enumerate((_ODD, np.uint64(0xC2B2AE3D27D4EB4F))):
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(textkit.mix64(h ^ seed), dtype=np.uint64)])
        out[:, k] = textkit.mix64(sums[bounds[1:]] - sums[bounds[:-1]] + size * seed)
    return out


def name_column(names: np.ndarray) -> pa.Array:
    """Names as 16 bytes each."""
    data = np.ascontiguousarray(names, dtype=np.uint64)
    return pa.Array.from_buffers(pa.binary(), len(data), [None, pa.py_buffer(np.arange(len(data) + 1, dtype=np.int32) * 16), pa.py_buffer(data)])


def column_names(col: pa.Array) -> np.ndarray:
    return textkit.string_buffers(col)[0].view(np.uint64).reshape(-1, 2)


def same_names(names: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first row of each distinct name, and each row's number among the distinct names."""
    order = np.lexsort((names[:, 1], names[:, 0]))
    head = np.ones(len(names), bool)
    head[1:] = (names[order][1:] != names[order][:-1]).any(axis=1)
    code = np.empty(len(names), np.int64)
    code[order] = np.cumsum(head) - 1
    return order[head], code


def most_different(size: np.ndarray, similarity: tuple[int, int] = SIMILARITY) -> np.ndarray:
    """The largest symmetric difference of a set of this size and any set as similar as asked."""
    a, b = similarity
    # The partner has at most size * b / a elements; |A ^ B| <= (b - a) / (b + a) * (|A| + |B|).
    return (b - a) * (size + size * b // a) // (b + a)


def band_of(size: np.ndarray, ratio: int = BAND_RATIO) -> np.ndarray:
    band = np.zeros(len(size), np.int64)
    top = np.full(len(size), ratio, np.int64)
    while (grow := size >= top).any():
        band[grow] += 1
        top[grow] *= ratio
    return band


def part_keys(h: np.ndarray, bounds: np.ndarray, frequent: np.ndarray, level: np.ndarray, similarity: tuple[int, int] = SIMILARITY, ratio: int = BAND_RATIO) -> tuple[np.ndarray, np.ndarray]:
    """(set index, key) of the parts that each set sends out, in its own band and, if a partner can be there, in the next.
    Sets with too few parts for the pigeonhole send single shingles as well."""
    a, b = similarity
    size = np.diff(bounds)
    home = band_of(size, ratio)
    largest = size * b // a
    up = band_of(largest, ratio) > home
    limit = most_different(size, similarity)
    if len(frequent):
        spot = np.minimum(np.searchsorted(frequent, h), len(frequent) - 1)
        cost = np.where(frequent[spot] == h, level[spot], 0).astype(np.uint64)
    else:
        cost = np.zeros(len(h), np.uint64)
    found_set, found_key = [], []
    for step in (0, 1):
        use = np.flatnonzero((size > 0) & (up if step else True))
        if not len(use):
            continue
        lengths = size[use]
        owner = np.repeat(use, lengths)
        at = np.repeat(bounds[use] - (np.cumsum(lengths) - lengths), lengths) + np.arange(len(owner))
        band = (home + step)[owner]
        # Twice as many parts as the band's largest sets have shingles; the high bits choose the part, so sorted hashes are sorted by part.
        bits = np.ceil(np.log2(ratio) * (band + 1)).astype(np.uint64) + np.uint64(1)
        x = h[at]
        part = x >> (np.uint64(64) - bits)
        head = np.flatnonzero(np.concatenate([[True], (part[1:] != part[:-1]) | (owner[1:] != owner[:-1])]))
        parity = np.bitwise_xor.reduceat(x, head)
        worst = np.minimum.reduceat(cost[at], head)  # a part is as rare as its rarest shingle
        key = textkit.mix64(parity ^ textkit.mix64(part[head] * np.uint64(64) + (band[head].astype(np.uint64) + np.uint64(1))))
        # The common order: rare parts first, then by hash; the key itself holds it.
        key = (worst << np.uint64(58)) | (key >> np.uint64(6))
        own = owner[head]
        few = np.zeros(len(size), bool)
        few[use] = np.bincount(own, minlength=len(size))[use] <= limit[use]
        single = few[owner]
        # A single shingle's key is made like that of a part past the last.
        alone = textkit.mix64(x[single] ^ textkit.mix64((np.uint64(64) << bits[single]) + (band[single].astype(np.uint64) + np.uint64(1))))
        alone = (cost[at][single] << np.uint64(58)) | (alone >> np.uint64(6))
        for own, key in ((own, key), (owner[single], alone)):
            first = np.searchsorted(own, use)
            for lo, hi in zip(first.tolist(), [*first[1:].tolist(), len(own)], strict=True):
                key[lo:hi].sort()
            sent = np.arange(len(own)) - first[np.searchsorted(use, own)] <= limit[own]
            found_set.append(own[sent])
            found_key.append(key[sent])
    if not found_set:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return np.concatenate(found_set), np.concatenate(found_key)


def bit_sketch(h: np.ndarray, bounds: np.ndarray, bits: int = SKETCH_BITS) -> list[bytes]:
    """Each set's parity bits, as many as the power of two from ``bits`` times its size on (256 at least). A wider sketch
    folds onto a narrower one. The distance falls short of the symmetric difference by shingles that share a bit: with two
    bits a shingle, pairs below a similarity of about .72 differ in more bits than a link allows, with one below about .6."""
    size = np.diff(bounds)
    width = np.maximum(8, np.ceil(np.log2(np.maximum(bits * size, 1))).astype(np.int64))
    place = textkit.mix64(h ^ np.uint64(0xD6E8FEB86659FD93))
    out = []
    for k, w in enumerate(width.tolist()):
        bits = np.bincount((place[bounds[k] : bounds[k + 1]] & np.uint64((1 << w) - 1)).astype(np.int64), minlength=1 << w) & 1
        out.append(np.packbits(bits.astype(np.uint8), bitorder="little").tobytes())
    return out


def folded(sketch: bytes, n_bytes: int) -> np.ndarray:
    x = np.frombuffer(sketch, np.uint8)
    return np.bitwise_xor.reduce(x.reshape(-1, n_bytes), axis=0) if len(x) > n_bytes else x


def may_link(size_a: np.ndarray, size_b: np.ndarray, distance: np.ndarray, similarity: tuple[int, int]) -> np.ndarray:
    """Whether sizes and a lower bound of the symmetric difference leave room for a link."""
    a, b = similarity
    return (b * np.minimum(size_a, size_b) >= a * np.maximum(size_a, size_b)) & ((a + b) * distance <= (b - a) * (size_a + size_b))


def described(docs: DataFrame, width: int, most: int = FREQUENT_LIST) -> DataFrame:
    """(doc_id, _text) to rows of two kinds, in one reading. ``doc``: doc_id, n_shingles, node, half of its name as ``short``, a
    small and a wide sketch and two hashes of the text that find it again. ``shingle``: a shingle's hash in ``t1`` and in ``n_shingles`` how many different sets of this slice hold it."""

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["kind", "doc_id", "n_shingles", "node", "short", "small", "sketch", "t1", "t2"]
        for b in textkit.slices(batches, "_text", SLICE_BYTES):
            h, bounds = shingles(b.column(1), width)
            node, size = node_ids(h, bounds), np.diff(bounds)
            wide = bit_sketch(h, bounds)
            small = [folded(x, max(32, len(x) // SKETCH_BITS)).tobytes() for x in wide]
            yield pa.RecordBatch.from_arrays([pa.array(["doc"] * b.num_rows), b.column(0), pa.array(size), name_column(node), pa.array(np.ascontiguousarray(node[:, 0]).view(np.int64)), pa.array(small, pa.binary()), pa.array(wide, pa.binary()), b.column(2), b.column(3)], names=names)
            pick = np.zeros(len(node), bool)
            pick[same_names(node)[0]] = True  # copies count once
            value = np.sort(h[np.repeat(pick, size)])
            head = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]])) if len(value) else np.zeros(0, np.int64)
            n = np.diff(np.append(head, len(value)))
            often = np.flatnonzero(n >= 4)
            if len(often) > most:
                often = often[np.argpartition(n[often], -most)[-most:]]
            k = len(often)
            yield pa.RecordBatch.from_arrays([pa.array(["shingle"] * k, pa.string()), pa.nulls(k, b.column(0).type), pa.array(n[often]), pa.nulls(k, pa.binary()), pa.nulls(k, pa.int64()), *[pa.nulls(k, pa.binary())] * 2, pa.array(value[head[often]].view(np.int64)), pa.nulls(k, pa.int64())], names=names)

    columns = (("n_shingles", T.LongType()), ("node", T.BinaryType()), ("short", T.LongType()), ("small", T.BinaryType()), ("sketch", T.BinaryType()), ("t1", T.LongType()), ("t2", T.LongType()))
    schema = T.StructType([T.StructField("kind", T.StringType()), T.StructField("doc_id", docs.schema["doc_id"].dataType), *[T.StructField(n, t) for n, t in columns]])
    return docs.select("doc_id", "_text", *_text_hashes("_text")).mapInArrow(run, schema)


def _text_hashes(text: str) -> list:
    return [F.xxhash64(F.lit(k), F.col(text)).alias(f"t{k}") for k in (1, 2)]


def frequent_shingles(rows: DataFrame, most: int = FREQUENT_LIST) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the shingles that most sets hold, sorted, and the power of two of each's count. Orders parts; results don't depend on it."""
    found = rows.groupBy(F.col("t1").alias("h")).agg(F.sum("n_shingles").alias("n")).where("n >= 16")
    top = found.orderBy(F.desc("n"), "h").limit(most).collect()  # a fixed number of rows
    h = np.array([r.h for r in top], np.int64).view(np.uint64)
    level = np.array([int(r.n).bit_length() for r in top], np.uint64)
    order = np.argsort(h)
    return h[order], level[order]


def buckets(docs: DataFrame, width: int, similarity: tuple[int, int], frequent: tuple[np.ndarray, np.ndarray], shingle_count: int) -> DataFrame:
    """(bucket, short): the nodes of each bucket of two and more, by half of their names; two nodes that share it both come
    into the bucket when names are put in its place. Buckets with the same nodes are one.

    Keys meet in groups by their hash, as many groups as the number of keys asks for, so a group has a bounded number of
    keys. A key that HOT_KEY nodes of one batch of keys have is a bucket at once: they go out as its nodes, and one of them
    alone goes to the key's group to stand for them, so a group gets a bounded part of a batch's hot keys.
    """
    a, b = similarity
    parts = max(shuffle_partitions(docs.sparkSession), shingle_count * (b - a) // (a * MEET_KEYS))
    fr, level = frequent

    def sent(own: list, keys: list, names: list, sizes: list) -> Iterator[pa.RecordBatch]:
        """Rows of what was gathered: for each group its keys, sorted by node, and the nodes' names, sizes and numbers of
        keys, and which keys are hot; without a group, the keys and names of hot buckets."""
        shift = np.repeat(np.cumsum([0, *map(len, names)])[:-1], [len(o) for o in own])
        own, key, name, size = np.concatenate(own) + shift, np.concatenate(keys), np.concatenate(names), np.concatenate(sizes)
        one, code = same_names(name)  # a set that came in several slices
        own, name, size = code[own], name[one], size[one]
        order = np.lexsort((own, key))
        own, key = own[order], key[order]
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (own[1:] != own[:-1])
        own, key = own[new], key[new]
        start = np.flatnonzero(np.diff(key, prepend=key[:1] + np.uint64(1)) != 0)
        count = np.diff(np.append(start, len(key)))
        stands = np.zeros(len(key), bool)
        stands[start[count >= HOT_KEY]] = True
        hot = np.flatnonzero(np.repeat(count >= HOT_KEY, count))
        none = pa.array([b""], pa.binary())
        for lo in range(0, len(hot), SEND_KEYS // 8):
            at = hot[lo : lo + SEND_KEYS // 8]
            apart = -1 - int(textkit.mix64(key[at[:1]] ^ name[own[at[:1]], 0])[0] >> np.uint64(2))  # a group of their own
            yield pa.RecordBatch.from_arrays([pa.array([apart], pa.int64()), pa.array([key[at].tobytes()], pa.binary()), pa.array([name[own[at], 0].tobytes()], pa.binary()), none, none, none], names=_SENT)
        keep = stands.copy()
        keep[np.repeat(count < HOT_KEY, count)] = True
        own, key, stands = own[keep], key[keep], stands[keep]
        to = (textkit.mix64(key + _ODD) % np.uint64(parts)).astype(np.int64)
        order = np.lexsort((own, to))
        own, key, to, stands = own[order], key[order], to[order], stands[order]
        used, edge = np.unique(to, return_index=True)
        edge = np.append(edge, len(to))
        for lo in range(0, len(used), 64):
            cols = [[], [], [], [], [], []]
            for k in range(lo, min(lo + 64, len(used))):
                at = slice(edge[k], edge[k + 1])
                local, times = np.unique(own[at], return_counts=True)
                for col, x in zip(cols, (int(used[k]), key[at], name[local, 0], size[local].astype(np.uint32), times.astype(np.uint32), key[at][stands[at]]), strict=True):
                    col.append(x if isinstance(x, int) else x.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), *[pa.array(c, pa.binary()) for c in cols[1:]]], names=_SENT)

    @textkit.giving_back
    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: tuple[list, ...] = ([], [], [], [])
        for batch in textkit.slices(batches, "_text", SLICE_BYTES):
            h, bounds = shingles(batch.column(0), width)
            name, size = node_ids(h, bounds), np.diff(bounds)
            keep = np.zeros(len(name), bool)
            keep[same_names(name)[0]] = True
            h, name, size = h[np.repeat(keep, size)], name[keep], size[keep]
            own, key = part_keys(h, np.concatenate([[0], np.cumsum(size)]), fr, level, similarity)
            for store, x in zip(waiting, (own, key, name, size), strict=True):
                store.append(x)
            if sum(map(len, waiting[1])) >= SEND_KEYS:
                yield from sent(*waiting)
                waiting = ([], [], [], [])
        if waiting[0]:
            yield from sent(*waiting)

    def meet(table: pa.Table) -> pa.Table:
        def joined(column: str, kind: type) -> np.ndarray:
            return np.concatenate([np.frombuffer(x.as_py(), kind) for x in table[column]])

        key, name, size, times = joined("keys", np.uint64), joined("names", np.uint64), joined("sizes", np.uint32), joined("times", np.uint32)
        if table["p"][0].as_py() < 0:
            bucket = hot_bucket(key)
        else:
            node = np.repeat(np.arange(len(name)), times)
            bucket, name = met(key, name[node], size[node].astype(np.int64), np.unique(joined("hot", np.uint64)), similarity)
        return pa.Table.from_arrays([pa.array(bucket), pa.array(name.view(np.int64))], names=["bucket", "short"])

    rows = docs.select("_text").mapInArrow(send, "p long, " + ", ".join(f"{c} binary" for c in _SENT[1:]))
    return rows.groupBy("p").applyInArrow(meet, "bucket long, short long").distinct()


_SENT = ["p", "keys", "names", "sizes", "times", "hot"]


def hot_bucket(key: np.ndarray) -> np.ndarray:
    """The name of a hot key's bucket."""
    return (textkit.mix64(key ^ np.uint64(0xA0761D6478BD642F)) >> np.uint64(1)).astype(np.int64)


def met(key: np.ndarray, name: np.ndarray, size: np.ndarray, hot: np.ndarray, similarity: tuple[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and node of the rows of one group whose key more than one node has, or which is hot."""
    a, b = similarity
    order = np.argsort(key, kind="stable")
    key, name, size = key[order], name[order], size[order]
    same = np.concatenate([[False], key[1:] == key[:-1], [False]])
    many = (same[1:] | same[:-1])[: len(key)] | np.isin(key, hot)
    key, name, size = key[many], name[many], size[many]
    if not len(key):
        return np.zeros(0, np.int64), name
    order = np.lexsort((name, size, key))
    key, name, size = key[order], name[order], size[order]
    new = np.ones(len(key), bool)
    new[1:] = (key[1:] != key[:-1]) | (name[1:] != name[:-1])
    key, name, size = key[new], name[new], size[new]
    is_hot = np.isin(key, hot)
    # Sizes too far apart for a link end a bucket: nothing on one side can link with the other. A hot key's bucket has nodes elsewhere too.
    start = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (~is_hot[1:] & (b * size[:-1] < a * size[1:]))]))
    n = np.diff(np.append(start, len(key)))
    bucket = (textkit.mix64(np.add.reduceat(textkit.mix64(name), start)) >> np.uint64(1)).astype(np.int64)
    bucket = np.where(is_hot[start], hot_bucket(key[start]), bucket)
    _, one = np.unique(bucket, return_index=True)
    one = one[(n[one] > 1) | is_hot[start[one]]]
    rows = np.repeat(start[one] - (np.cumsum(n[one]) - n[one]), n[one]) + np.arange(int(n[one].sum()))
    return np.repeat(bucket[one], n[one]), name[rows]


def shingle_sets(docs: DataFrame, known: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """(node, shingles as bytes) for each wanted node, from one of its texts, which is found by its hashes; copies meet in the aggregate."""
    place = cut(known.join(wanted.select(F.col("node").alias("_n")), F.col("node") == F.col("_n"), "left_semi").groupBy("node").agg(F.min(F.struct("t1", "t2")).alias("t")).select(F.col("t.t1").alias("_1"), F.col("t.t2").alias("_2")))
    place = F.broadcast(place) if place.count() <= BROADCAST_ROWS else place
    texts = docs.select("_text", *_text_hashes("_text")).join(place, (F.col("t1") == F.col("_1")) & (F.col("t2") == F.col("_2")), "left_semi").select("_text")

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in textkit.slices(batches, "_text", SLICE_BYTES):
            h, bounds = shingles(r.column(0), width)
            name = node_ids(h, bounds)
            one = same_names(name)[0]
            yield pa.RecordBatch.from_arrays([name_column(name[one]), pa.array([h[bounds[k] : bounds[k + 1]].tobytes() for k in one], pa.binary())], names=["node", "shingles"])

    return texts.mapInArrow(run, "node binary, shingles binary").groupBy("node").agg(F.first("shingles").alias("shingles"))


def verified(pairs: DataFrame, sets: DataFrame, similarity: tuple[int, int]) -> DataFrame:
    """The (a, b) that link, by their whole sets."""
    a, b = similarity
    one, two = (sets.select(F.col("node").alias(f"_{k}"), F.col("shingles").alias(f"s{k}")) for k in "ab")
    both = pairs.join(one, F.col("a") == F.col("_a")).join(two, F.col("b") == F.col("_b")).select("a", "b", "sa", "sb")

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in batches:
            ok = np.zeros(r.num_rows, bool)
            for k, (x, y) in enumerate(zip(r.column(2), r.column(3), strict=True)):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                common = int((p[np.minimum(np.searchsorted(p, q), len(p) - 1)] == q).sum())
                ok[k] = b * common >= a * (len(p) + len(q) - common)
            yield r.select(["a", "b"]).filter(pa.array(ok))

    return both.mapInArrow(run, "a binary, b binary")


def components(links: DataFrame) -> DataFrame:
    """(a, b) to (node, comp): for every node with a link one node, the same for all that it reaches. One task does it while
    the links are few; beyond, rounds do, which alternate between joining a node's larger and smaller neighbours to its
    smallest, so they grow with the logarithm of the nodes."""

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ends = [np.stack([column_names(r.column(0)), column_names(r.column(1))], axis=1) for r in batches if r.num_rows]
        if not ends:
            return
        names = np.concatenate(ends).reshape(-1, 2)
        one, code = same_names(names)
        a, b, least = code[0::2], code[1::2], np.arange(len(one))
        while True:
            before, m = least.copy(), np.minimum(least[a], least[b])
            np.minimum.at(least, before[a], m)
            np.minimum.at(least, before[b], m)
            while (least[least] != least).any():
                least = least[least]
            if (least == before).all():
                break
        yield pa.RecordBatch.from_arrays([name_column(names[one]), name_column(names[one][least])], names=["node", "comp"])

    if links.count() <= SMALL_GRAPH:
        return links.select("a", "b").coalesce(1).mapInArrow(run, "node binary, comp binary")

    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.expr("bit_xor(xxhash64(a, b))")).first())

    edges = cut(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct())
    before = mark(edges)
    while True:
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionAll(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("_u"), F.least("u", "m").alias("m"))
        large = cut(both.where("v > u").join(least, F.col("u") == F.col("_u")).select(F.col("m").alias("a"), F.col("v").alias("b")).distinct())
        least = large.groupBy("b").agg(F.min("a").alias("m")).withColumnRenamed("b", "_b")
        joined = large.join(least, F.col("b") == F.col("_b"))
        edges = cut(joined.select(F.col("m").alias("a"), "b").unionAll(joined.where("a <> m").select(F.col("m").alias("a"), F.col("a").alias("b"))).distinct())
        after = mark(edges)
        if after == before:
            return edges.select(F.col("b").alias("node"), F.col("a").alias("comp")).unionAll(edges.select(F.col("a").alias("node"), F.col("a").alias("comp")).distinct())
        before = after


def _streamed(batches: Iterator[pa.RecordBatch], keys: list[str], compare: Callable[[pa.Table], pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``compare`` of whole groups of rows that come sorted by the integer columns ``keys``."""
    rest = None
    for b in batches:
        t = pa.Table.from_batches([b]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([b])]).combine_chunks()
        last = _group_starts(t, keys)[-1] if t.num_rows else 0
        if last:
            yield compare(t.slice(0, last))
        rest = t.slice(last)
    if rest is not None and rest.num_rows:
        yield compare(rest)


def _group_starts(t: pa.Table, keys: list[str]) -> np.ndarray:
    change = np.zeros(t.num_rows, bool)
    change[:1] = True
    for c in keys:
        v = t[c].to_numpy()
        change[1:] |= v[1:] != v[:-1]
    return np.flatnonzero(change)


def _near_pairs(t: pa.Table, sketch: str, begin: np.ndarray, many: np.ndarray, similarity: tuple[int, int], most: int = 1_000_000) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Places x and y of the pairs that sizes and sketches leave, of different components, and their distances: row x with
    ``many[x]`` rows from ``begin[x]`` on. At most about ``most`` pairs at a time."""
    size = t["n_shingles"].to_numpy()
    comp = same_names(column_names(pc.coalesce(t["comp"].combine_chunks(), t["a"].combine_chunks())))[1]  # a node without links is its own
    raw, off = textkit.string_buffers(t[sketch].combine_chunks())
    width = np.diff(off)
    a, b = similarity
    left = np.flatnonzero(many > 0)
    upto = np.cumsum(many[left])
    folds: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def words(w: int) -> tuple[np.ndarray, np.ndarray]:
        """Places in, and the matrix of, the sketches of w and 2w bytes, as w bytes."""
        if w not in folds:
            at, matrix = np.full(t.num_rows, -1), []
            for k in (w, 2 * w):
                rows = np.flatnonzero(width == k)
                x = raw[(off[rows][:, None] + np.arange(k))].reshape(len(rows), k)
                at[rows] = np.arange(len(rows)) + sum(map(len, matrix))
                matrix.append(x if k == w else x[:, :w] ^ x[:, w:])
            folds[w] = at, np.ascontiguousarray(np.concatenate(matrix)).view(np.uint64)
        return folds[w]

    lo = 0
    while lo < len(left):
        hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + most, side="right")))
        use = left[lo:hi]
        lo = hi
        x = np.repeat(use, many[use])
        y = np.arange(len(x)) + np.repeat(begin[use] - (np.cumsum(many[use]) - many[use]), many[use])
        ok = (comp[x] != comp[y]) & (b * np.minimum(size[x], size[y]) >= a * np.maximum(size[x], size[y]))
        x, y = x[ok], y[ok]
        w = np.minimum(width[x], width[y])
        d = np.empty(len(x), np.int64)
        for each in np.unique(w).tolist():
            at, matrix = words(each)
            mine = np.flatnonzero(w == each)
            step = max(1, (1 << 25) // each)
            for i in range(0, len(mine), step):
                m = mine[i : i + step]
                d[m] = np.bitwise_count(matrix[at[x[m]]] ^ matrix[at[y[m]]]).sum(axis=1, dtype=np.int64)
        ok = may_link(size[x], size[y], d, similarity)
        yield x[ok], y[ok], d[ok]


def _with_components(nodes: DataFrame, comp: DataFrame | None) -> DataFrame:
    """``nodes`` with ``comp``; a node without links is its own component."""
    if comp is None:
        return nodes.withColumn("comp", F.col("node"))
    own = comp.select(F.col("node").alias("_n"), F.col("comp").alias("_comp"))
    own = F.broadcast(own) if own.count() <= BROADCAST_ROWS else own
    return nodes.join(own, F.col("node") == F.col("_n"), "left").withColumn("comp", F.coalesce("_comp", "node")).drop("_n", "_comp")


def large_buckets(members: DataFrame, chunk: int) -> DataFrame:
    """(bucket, size) of the buckets of more than ``chunk`` nodes; at most a row for each ``chunk`` rows of ``members``."""
    return members.groupBy(F.col("bucket").alias("large")).agg(F.count("*").alias("size")).where(F.col("size") > chunk)


def nearest(members: DataFrame, comp: DataFrame | None, nodes: DataFrame, large: DataFrame, similarity: tuple[int, int], turn: int, chunk: int = CHUNK) -> DataFrame:
    """Pairs (a, b): each node with the nearest one of another component, by its small sketch, among those of its buckets
    that sizes and sketches leave. A bucket of more than ``chunk`` nodes is compared in chunks, dealt anew each ``turn``."""
    sk = _with_components(nodes, comp).select(F.col("short").alias("_s"), F.col("node").alias("a"), F.nullif(F.col("comp"), F.col("node")).alias("comp"), "n_shingles", "small")
    m = members.join(sk, F.col("short") == F.col("_s"))
    m = m.join(F.broadcast(large) if large.count() <= BROADCAST_ROWS else large, F.col("bucket") == F.col("large"), "left")
    part = F.when(F.col("size").isNull(), F.lit(0).cast("long")).otherwise(F.pmod(F.xxhash64("a", F.lit(turn)), F.ceil(F.col("size") / F.lit(float(chunk))).cast("long")))
    rows = m.select("bucket", part.alias("part"), "a", "comp", "n_shingles", "small")

    def best(t: pa.Table) -> pa.RecordBatch:
        start = _group_starts(t, ["bucket", "part"])
        end = np.repeat(np.append(start[1:], t.num_rows), np.diff(np.append(start, t.num_rows)))
        begin = np.arange(t.num_rows) + 1
        size = t["n_shingles"].to_numpy()
        score, partner = np.full(t.num_rows, np.inf), np.full(t.num_rows, -1)
        for x, y, d in _near_pairs(t, "small", begin, end - begin, similarity):
            far = d / (size[x] + size[y])
            node, other, far = np.concatenate([x, y]), np.concatenate([y, x]), np.concatenate([far, far])
            order = np.lexsort((other, far, node))
            node, other, far = node[order], other[order], far[order]
            head = np.flatnonzero(np.diff(node, prepend=-1) != 0)
            closer = head[far[head] < score[node[head]]]
            score[node[closer]], partner[node[closer]] = far[closer], other[closer]
        some = pa.array(np.flatnonzero(partner >= 0))
        a = t["a"].combine_chunks()
        return pa.RecordBatch.from_arrays([a.take(some), pa.array(score[some.to_numpy()]), a.take(pa.array(partner[some.to_numpy()]))], names=["a", "far", "b"])

    @textkit.giving_back
    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _streamed(batches, ["bucket", "part"], best)

    found = rows.repartition("bucket", "part").sortWithinPartitions("bucket", "part", "a").mapInArrow(compare, "a binary, far double, b binary")
    found = found.groupBy("a").agg(F.min(F.struct("far", "b")).alias("n"))
    return found.select(F.least("a", "n.b").alias("a"), F.greatest("a", "n.b").alias("b")).distinct()


def across(members: DataFrame, comp: DataFrame | None, nodes: DataFrame, similarity: tuple[int, int], outside: int = 512, inside: int = 2048) -> DataFrame:
    """All pairs (a, b) of one bucket and different components that size and sketch leave. The nodes of a bucket of more than
    ``inside`` that are outside its largest component are compared with all its nodes, in blocks, so a task holds a bounded
    part of a bucket. Of the buckets that both nodes name, the first gives the pair."""
    own = _with_components(nodes, comp).select(F.col("short").alias("_s"), F.col("node").alias("a"), "comp")
    every = members.join(own, F.col("short") == F.col("_s")).select("bucket", "a", "comp")
    per = every.groupBy(F.col("bucket").alias("_b")).agg(F.count("*").alias("size"), F.min("comp").alias("c0"), F.max("comp").alias("c1")).where("c0 <> c1").select("_b", "size")
    m = cut(every.join(per, F.col("bucket") == F.col("_b")).drop("_b"))
    many = m.where(F.col("size") > inside)
    if many.isEmpty():
        m = m.withColumns({"main": F.lit(None).cast("binary"), "main_n": F.lit(0).cast("long")})
    else:
        main = many.groupBy("bucket", "comp").agg(F.count("*").alias("n")).groupBy(F.col("bucket").alias("_b")).agg(F.max(F.struct("n", "comp")).alias("main"))
        m = m.join(main, F.col("bucket") == F.col("_b"), "left").select("bucket", "a", "comp", "size", F.col("main.comp").alias("main"), F.col("main.n").alias("main_n"))
    # The NAMED_BUCKETS smallest buckets of each node; a node has at most as many as it sent keys.
    named = m.groupBy(F.col("a").alias("_m")).agg(F.slice(F.array_sort(F.collect_list("bucket")), 1, NAMED_BUCKETS).alias("named"))
    sk = nodes.select(F.col("node").alias("_s"), "n_shingles", "sketch")
    m = m.join(sk, F.col("a") == F.col("_s")).join(named, F.col("a") == F.col("_m"))
    m = m.withColumns({"mb": F.ceil(F.col("size") / inside).cast("int"), "ob": F.ceil((F.col("size") - F.coalesce("main_n", F.lit(0))) / outside).cast("int")})
    h = F.xxhash64("a")
    one = F.col("mb") == 1
    # Role 2: a bucket in one block, each node against the later ones. Otherwise nodes outside (0) against all (1), block by block.
    whole = m.where(one).withColumns({"o": F.lit(0), "i": F.lit(0), "role": F.lit(2)})
    out = m.where(~one & ~F.col("comp").eqNullSafe(F.col("main"))).withColumn("o", F.pmod(h, F.col("ob"))).withColumn("i", F.explode(F.sequence(F.lit(0), F.col("mb") - 1))).withColumn("role", F.lit(0))
    in_ = m.where(~one).withColumn("i", F.pmod(h, F.col("mb"))).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("ob") - 1))).withColumn("role", F.lit(1))
    cols = ["bucket", F.col("o").cast("long").alias("o"), F.col("i").cast("long").alias("i"), "role", "a", "comp", "n_shingles", "sketch", "named"]

    @textkit.giving_back
    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _streamed(batches, ["bucket", "o", "i"], lambda t: _across_pairs(t, similarity))

    rows = whole.select(*cols).unionAll(out.select(*cols)).unionAll(in_.select(*cols))
    return rows.repartition("bucket", "o", "i").sortWithinPartitions("bucket", "o", "i", "role").mapInArrow(compare, "a binary, b binary").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _across_pairs(t: pa.Table, similarity: tuple[int, int]) -> pa.RecordBatch:
    """The surviving pairs of whole groups, sorted by role, that no earlier bucket names."""
    role = t["role"].to_numpy()
    start = _group_starts(t, ["bucket", "o", "i"])
    rows = np.diff(np.append(start, t.num_rows))
    group, end = np.repeat(np.arange(len(start)), rows), np.repeat(np.append(start[1:], t.num_rows), rows)
    # Where a left node's partners begin: after itself, or at its group's first row of role 1.
    right = np.add.reduceat((role == 0).astype(np.int64), start) + start
    begin = np.where(role == 2, np.arange(t.num_rows) + 1, right[group])
    many = np.where(role == 1, 0, end - begin)
    name, bucket = column_names(t["a"].combine_chunks()), t["bucket"].to_numpy()
    lists = t["named"].combine_chunks()
    named, off = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy(zero_copy_only=False)
    earlier: dict[int, np.ndarray] = {}

    def marks(g: int) -> np.ndarray:
        """A bit per row of group g and bucket before the group's own that it names."""
        if g not in earlier:
            lo, n = int(start[g]), int(rows[g])
            flat, owner = named[off[lo] : off[lo + n]], np.repeat(np.arange(n), np.diff(off[lo : lo + n + 1]))
            use = flat < bucket[lo]
            values, code = np.unique(flat[use], return_inverse=True)
            bits = np.zeros((n, len(values) + 1), bool)
            bits[owner[use], code] = True
            earlier[g] = np.packbits(bits, axis=1)
        return earlier[g]

    found = [np.zeros((0, 4), np.uint64)]
    for x, y, _ in _near_pairs(t, "sketch", begin, many, similarity):
        order = np.argsort(group[x], kind="stable")
        x, y = x[order], y[order]
        keep = np.zeros(len(x), bool)
        used, edge = np.unique(group[x], return_index=True)
        for g, i, j in zip(used.tolist(), edge.tolist(), [*edge[1:].tolist(), len(x)][: len(used)], strict=True):
            bits = marks(g)
            keep[i:j] = ~(bits[x[i:j] - start[g]] & bits[y[i:j] - start[g]]).any(axis=1)
        earlier.clear()
        x, y = name[x[keep]], name[y[keep]]
        found.append(np.concatenate([x, y], axis=1))
    ab = np.concatenate(found)
    return pa.RecordBatch.from_arrays([name_column(ab[:, :2]), name_column(ab[:, 2:])], names=["a", "b"])


def grouped(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = WIDTH, similarity: tuple[int, int] = SIMILARITY) -> DataFrame:
    """doc_id, n_shingles, component_id of each row.

    Null or empty texts and texts without words have no shingles and link with nothing; a null doc_id is never a
    component's smallest unless all are null; repeated rows are copies of each other; a very long text is one slice of its
    own in a worker; other columns of ``docs``, whatever their names, are not read; an empty table gives an empty result.
    """
    spark = docs.sparkSession
    own = docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("_text"))
    rows = cut(described(own, width))
    known = rows.where("kind = 'doc'").drop("kind")
    count = known.agg(F.coalesce(F.sum("n_shingles"), F.lit(0))).first()[0]
    members = cut(buckets(own, width, similarity, frequent_shingles(rows.where("kind = 'shingle'")), count))
    large = cut(large_buckets(members, CHUNK))
    touched = members.select(F.col("short").alias("_n")).distinct()
    nodes = known.join(touched, F.col("short") == F.col("_n"), "left_semi").groupBy("node").agg(*[F.first(c).alias(c) for c in ("short", "n_shingles", "small", "sketch")])
    nodes = cut(nodes)
    release(spark)
    whole = large.isEmpty()
    sets = links = tried = comp = None

    def tested(pairs: DataFrame) -> None:
        """Adds the links among ``pairs`` and their components."""
        nonlocal sets, links, tried, comp
        if sets is None or not whole:  # else the first round met every node that has a near one
            wanted = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
            if sets is not None:
                wanted = wanted.join(sets.select("node"), "node", "left_anti")
            new = cut(shingle_sets(own, known, wanted, width))
            sets = new if sets is None else sets.unionAll(new)
        new = cut(verified(pairs, sets, similarity))
        links, tried = (new, pairs) if links is None else (links.unionAll(new), tried.unionAll(pairs))
        if comp is None or not new.isEmpty():
            comp = cut(components(links))
        release(spark)

    for turn in range(ROUNDS):
        found = cut(nearest(members, comp, nodes, large, similarity, turn))
        release(spark)
        # A node without a near one of another component in its buckets has no more to find; only buckets compared in chunks may hide one.
        seen = nodes.join(found.select(F.explode(F.array("a", "b")).alias("_n")).distinct(), F.col("node") == F.col("_n"), "left_semi").select("short")
        if not whole:
            seen = seen.unionAll(members.join(large, F.col("bucket") == F.col("large"), "left_semi").select("short"))
        seen = cut(seen.withColumnRenamed("short", "_n").distinct())
        members = cut(members.join(F.broadcast(seen) if seen.count() <= BROADCAST_ROWS else seen, F.col("short") == F.col("_n"), "left_semi"))
        near = found if tried is None else cut(found.join(tried, ["a", "b"], "left_anti"))
        if near.isEmpty():
            break
        tested(near)
    rest = across(members, comp, nodes, similarity)
    rest = cut(rest if tried is None else rest.join(tried, ["a", "b"], "left_anti"))
    release(spark)
    if not rest.isEmpty():
        tested(rest)
    # The smallest doc_id of each component, or of the node where it has no link. Copies and hot components meet in the partial aggregate.
    full = _with_components(known.select("doc_id", "n_shingles", "node"), comp)
    least = cut(full.where("n_shingles > 0").groupBy(F.col("comp").alias("_c")).agg(F.min("doc_id").alias("least")))
    joined = full.join(least, (F.col("comp") == F.col("_c")) & (F.col("n_shingles") > 0), "left")
    return joined.select("doc_id", "n_shingles", F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.col("least")).alias("component_id"))


def one_of_each(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", **options) -> DataFrame:
    """``docs`` with the smallest doc_id of each group of linked documents, all columns unchanged, whatever their names. Rows that share a doc_id stay or go together."""
    stays = grouped(docs, text, doc_id, **options).where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("stays")).distinct()
    return docs.alias("_docs_").join(stays.alias("_stays_"), F.col(f"_docs_.`{doc_id}`").eqNullSafe(F.col("_stays_.stays")), "left_semi")
