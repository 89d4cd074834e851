"""Exact duplicates by deterministic block naming (DataFrame functions only).

Each text is cut into blocks of fixed size. The distinct blocks of the corpus, sorted, get integer names; then the
names of adjacent blocks form pairs, the distinct pairs are sorted and named in the same way, and so on until every
row has one name. Rows have equal names if and only if their texts are equal.

Blocks travel as 128-bit keys. A key serves as a name's stand-in only after the distinct (key, block) rows have shown
that no key stands for two blocks; otherwise the next seed is tried. So names are free of collisions, not just
unlikely to collide.

Names are ranks within buckets of the sorted key, so no task sorts the whole corpus, and they depend on the data alone.
A block or pair that a third of all rows share is one row after the partial aggregation; the join that brings names
back to rows is a plain equi-join, which adaptive execution splits where a key is hot.

Defined results: null text counts as empty; equal rows are copies of each other; a null doc_id is smaller than any
other; a very long text is only more blocks; other columns, whatever their names, are left alone; an empty table gives an
empty result.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scratch import cut

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BLOCK_BYTES = 4096
NAME_BUCKETS = 1 << 12
LEVEL_BITS = 6


def normalised(text: Column) -> Column:
    """A to Z in lower case, nothing else changed; null becomes the empty text."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def block_key(block: Column, seed: int) -> Column:
    return F.struct(F.xxhash64(F.lit(2 * seed), block).alias("k1"), F.xxhash64(F.lit(2 * seed + 1), block).alias("k2"))


def named(keys: DataFrame, cols: list[str], buckets: int) -> DataFrame:
    """Distinct rows of ``cols`` and an integer name for each: bucket by hash, then the place in the bucket's sorted order."""
    distinct = keys.select(*cols).distinct().withColumn("_b", F.pmod(F.xxhash64(*cols), F.lit(buckets)))
    place = F.row_number().over(Window.partitionBy("_b").orderBy(*cols)).cast("long")
    return distinct.select(*cols, (place * buckets + F.col("_b")).alias("name"))


def identities(docs: DataFrame, text: str = "text", block_bytes: int = BLOCK_BYTES, buckets: int = NAME_BUCKETS, key: Callable[[Column, int], Column] = block_key) -> DataFrame:
    """The columns of ``docs`` but the text, with ``_row`` (unique), ``_sha`` and ``identity`` (equal if and only if the normalised texts are equal)."""
    rest = [F.col(f"`{c}`") for c in docs.columns if c != text]
    source = docs.select(*rest, normalised(F.col(f"`{text}`")).cast("binary").alias("_t"))
    count = F.greatest(F.lit(1), F.ceil(F.octet_length("_t") / F.lit(float(block_bytes))).cast("int"))
    blocks = F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.substring(F.col("_t"), i * block_bytes + 1, F.lit(block_bytes)))
    seed = 0
    while True:
        seed += 1
        each = source.select(F.explode(blocks).alias("block")).select(key(F.col("block"), seed).alias("k"), "block")
        content = each.groupBy("k.k1", "k.k2", "block").agg(F.lit(1).alias("one"))
        keys = cut(content.groupBy("k1", "k2").agg(F.count("one").alias("contents")))
        if keys.where("contents > 1").isEmpty():
            break
    rows = cut(source.select(*[F.col(f"`{c}`") for c in docs.columns if c != text], F.monotonically_increasing_id().alias("_row"), F.unhex(F.sha2("_t", 256)).alias("_sha"), F.transform(blocks, lambda b: key(b, seed)).alias("_keys")))
    names = named(keys, ["k1", "k2"], buckets)
    level = cut(rows.select("_row", F.posexplode("_keys").alias("pos", "k")).select("_row", "pos", F.col("k.k1").alias("k1"), F.col("k.k2").alias("k2")).join(names, ["k1", "k2"]).select("_row", "pos", "name"))
    done, depth = [], 0
    while True:
        # A row is finished once its only name stands at place 0; the rest pair up their neighbours.
        sized = level.groupBy("_row").agg(F.max("pos").alias("last"))
        many = sized.where("last > 0").select("_row")
        if many.isEmpty():
            done.append(level.select("_row", F.lit(depth).alias("depth"), "name"))
            break
        done.append(level.join(many, "_row", "left_anti").select("_row", F.lit(depth).alias("depth"), "name"))
        half = (
            level.join(many, "_row", "left_semi")
            .groupBy("_row", F.shiftright("pos", 1).alias("pos"))
            .agg(F.max(F.when(F.col("pos") % 2 == 0, F.col("name"))).alias("a"), F.coalesce(F.max(F.when(F.col("pos") % 2 == 1, F.col("name"))), F.lit(-1)).alias("b"))
        )
        half = cut(half)
        level = cut(half.join(named(half, ["a", "b"], buckets), ["a", "b"]).select("_row", "pos", "name"))
        depth += 1
    every = done[0]
    for more in done[1:]:
        every = every.unionAll(more)
    every = every.select("_row", (F.col("name") * (1 << LEVEL_BITS) + F.col("depth")).alias("identity"))
    return rows.drop("_keys").join(every, "_row")


def deduplicated(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", **options) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256. Of equal texts the largest doc_id stays; of rows that repeat it too, one."""
    known = cut(identities(docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("text")), **options))
    # The largest (doc_id, row) stays, so ties on doc_id leave one row. The groups are kept, so that a hot group's rows meet them in a join of two exchanges, which Spark splits.
    groups = known.groupBy("identity").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"), F.max(F.struct("doc_id", "_row")).alias("w"))
    groups = cut(groups.select("identity", "keep_id", "group_size", F.col("w._row").alias("_winner")))
    return known.join(groups, "identity").select(
        "doc_id", "keep_id", "group_size", (F.col("_row") == F.col("_winner")).alias("kept"), F.lower(F.hex("_sha")).alias("text_sha256")
    )


def keep_one(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", **options) -> DataFrame:
    """``docs`` without copies: the row with the largest doc_id of each group of equal texts, all columns unchanged."""
    known = cut(identities(docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("text")), **options))
    best = cut(known.groupBy("identity").agg(F.max("doc_id").alias("best")))
    stays = known.join(best, "identity").where(F.col("doc_id").eqNullSafe(F.col("best"))).groupBy("doc_id", "_sha").agg(F.count("*").alias("_n"))
    sha = F.unhex(F.sha2(normalised(F.col(f"d.`{text}`")), 256))
    row = F.struct(*[F.col(f"d.`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)])
    joined = docs.alias("d").join(stays.alias("s"), F.col(f"d.`{doc_id}`").eqNullSafe(F.col("s.doc_id")) & (sha == F.col("s._sha")))
    joined = joined.select(row.alias("row"), F.col("s.doc_id").alias("id"), F.col("s._sha").alias("sha"), F.col("s._n").alias("n"))
    one = joined.where("n = 1").unionAll(joined.where("n > 1").dropDuplicates(["id", "sha"]))
    return one.select(*[F.col(f"row.c{k}").alias(c) for k, c in enumerate(docs.columns)])
