"""Mixing sources to target weights with a low-discrepancy schedule (DataFrame functions only).

Slot i of the schedule stands at the golden-ratio point frac(i / phi); the cumulative weights cut [0, 1) into one
interval per source, and the interval that holds the point names the source. A slot's rank among its source's slots
picks the equal-token block of that rank in the source's stream: its documents in hash order, read up to twice.

Ranks and stream positions are prefix sums in two steps (totals per chunk, then inside a chunk), so a source with a
third of all rows is spread over many tasks. Only the table of sources, one row each, is handled in one piece.

Defined results: a document's size is its number of words, null text has size 0; a null source is a source of its own,
last in order; sources without words get target 0; rows that repeat another are documents of their own; a very long
document only touches more blocks; other columns, whatever their names, are left alone; an empty table gives an empty
result. Equal input gives equal output on every run and partitioning.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scratch import cut

BLOCK_TOKENS = 256
#: Golden ratio as a fraction of 2^32 (odd, so that the points of 2^32 slots are all different).
GOLDEN_STEP = 2654435769
POINT_BITS = 32
CHUNK_SLOTS = 1 << 14
STREAM_CHUNKS = 1 << 10
CELLS = 1 << 10


def word_count(text: Column) -> Column:
    return F.when(text.isNull(), 0).otherwise(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+"))).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """(source, source_size) to (source, source_size, weight, target).

    Raising all targets in proportion to weight, each stopping at ``most`` times its size, ends where resharing the
    excess ends: at min(cap, level * weight). Sorted by cap / weight, prefix sums give the level.
    """
    in_order = Window.orderBy(F.col("source").asc_nulls_last())
    rank = (F.row_number().over(in_order) - 1) % len(weights)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), rank + 1)
    t = sizes.withColumn("weight", weight).withColumn("cap", F.col("source_size") * F.lit(most))
    by_cap = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before = by_cap.rowsBetween(Window.unboundedPreceding, -1)
    rest = by_cap.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    t = t.withColumn("total", F.sum("source_size").over(whole) * F.lit(share))
    t = t.withColumn("level", (F.col("total") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(rest))
    # The first source, from the smallest cap / weight on, that the level leaves below its cap fixes it; later levels only fall.
    level = F.max(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level"))).over(whole)
    t = t.withColumn("target", F.least(F.col("cap"), F.coalesce(level, F.lit(float("inf"))) * F.col("weight")))
    return t.select("source", "source_size", "weight", F.when(F.col("source_size") == 0, 0.0).otherwise(F.col("target")).alias("target"))


def schedule(targets: DataFrame, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """(slot, source, rank, tokens): each slot's source, its rank among the source's slots and the tokens it takes.

    A source gets slots until its target is reached; its last slot takes what is left. Slots beyond are not used. What the
    points leave of a narrow source's target follows in slots past the last, source after source.
    """
    quota = targets.select("source", F.floor("target").cast("long").alias("quota")).where("quota > 0")
    total, least = quota.agg(F.sum("quota"), F.min("quota")).first()
    spark = targets.sparkSession
    if not total:
        return spark.createDataFrame([], "slot long, source string, rank long, tokens long")
    # Any stretch of N points has N * width points of an interval up to a few times log2 N; that many more are drawn for the narrowest
    # one, but not more than the blocks themselves: below, a source beside a much larger corpus gets what it lacks, a few times log2 N slots.
    blocks = -(-total // block_tokens)
    slack = 3 * max(4, blocks.bit_length())
    slots = blocks + min(blocks + 1024, -(-slack * total // least))
    upto = F.sum("quota").over(Window.orderBy(F.col("source").asc_nulls_last()))
    scale = F.lit(float(1 << POINT_BITS) / total)
    spans = quota.withColumn("hi", F.round(upto * scale).cast("long")).withColumn("lo", F.round((upto - F.col("quota")) * scale).cast("long"))
    cell = (1 << POINT_BITS) // CELLS
    spans = spans.where("hi > lo").withColumn("cell", F.explode(F.sequence(F.expr(f"lo div {cell}"), F.expr(f"(hi - 1) div {cell}"))))
    turn = F.pmod(F.col("id"), F.lit(1 << POINT_BITS))
    point = F.pmod(F.pmod(turn * F.lit(GOLDEN_STEP >> 1), F.lit(1 << (POINT_BITS - 1))) * 2 + turn, F.lit(1 << POINT_BITS))
    points = spark.range(slots).select(F.col("id").alias("slot"), point.alias("point")).withColumn("cell", F.expr(f"point div {cell}"))
    dealt = points.join(spans, "cell").where("point >= lo AND point < hi").select("slot", "source", "quota", F.expr(f"slot div {CHUNK_SLOTS}").alias("chunk"))
    key = F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))
    dealt = dealt.withColumn("sk", key)
    counts = dealt.groupBy("sk", "chunk").agg(F.count("*").alias("n"))
    had = quota.withColumn("sk", key).join(counts.groupBy("sk").agg(F.sum("n").alias("had")), "sk", "left").withColumn("had", F.coalesce("had", F.lit(0)))
    had = had.withColumn("lacks", F.greatest(F.expr(f"(quota + {block_tokens - 1}) div {block_tokens}") - F.col("had"), F.lit(0)))
    past = F.sum("lacks").over(Window.orderBy(F.col("source").asc_nulls_last())) - F.col("lacks") + F.lit(slots)
    extra = had.withColumn("past", past).where("lacks > 0").select("source", "quota", "had", "past", F.explode(F.sequence(F.col("had"), F.col("had") + F.col("lacks") - 1)).alias("rank"))
    extra = extra.select((F.col("past") + F.col("rank") - F.col("had")).alias("slot"), "source", "quota", "rank")
    earlier = Window.partitionBy("sk").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("before", F.coalesce(F.sum("n").over(earlier), F.lit(0))).drop("n")
    inside = F.row_number().over(Window.partitionBy("sk", "chunk").orderBy("slot")) - 1
    ranked = dealt.withColumn("inside", inside).join(counts, ["sk", "chunk"]).withColumn("rank", F.col("before") + F.col("inside"))
    tokens = F.least(F.lit(block_tokens), F.col("quota") - F.col("rank") * block_tokens)
    ranked = ranked.select("slot", "source", "quota", "rank").unionAll(extra)
    return ranked.withColumn("tokens", tokens.cast("long")).where("tokens > 0").select("slot", "source", "rank", "tokens")


def streams(docs: DataFrame, seed: str, chunks: int = STREAM_CHUNKS) -> DataFrame:
    """``docs`` (doc_id, source, size) with ``start``: the words before the document in its source's shuffled stream."""
    spread = docs.withColumn("sk", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))).withColumn("h", F.md5(F.concat(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))))
    spread = spread.withColumn("chunk", (F.conv(F.substring("h", 1, 8), 16, 10).cast("long") * chunks / F.lit(1 << 32)).cast("int"))
    totals = spread.groupBy("sk", "chunk").agg(F.sum("size").alias("n"))
    earlier = Window.partitionBy("sk").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.withColumn("before", F.coalesce(F.sum("n").over(earlier), F.lit(0))).drop("n")
    inside = Window.partitionBy("sk", "chunk").orderBy("h", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = spread.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    return placed.join(totals, ["sk", "chunk"]).withColumn("start", F.col("before") + F.col("inside")).drop("h", "chunk", "before", "inside")


def mixed(docs: DataFrame, text: str = "text", source: str = "source", doc_id: str = "doc_id", weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0, block_tokens: int = BLOCK_TOKENS, seed: str = "mix") -> DataFrame:
    """Per document: doc_id, source, size, source_size, target, start, first (words taken in the first reading of the source), taken (in all)."""
    sized = cut(docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{source}`").alias("source"), word_count(F.col(f"`{text}`")).alias("size")))
    targets = cut(source_targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most))
    key = F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))
    per_source = targets.select(key.alias("sk"), "source_size", "target")
    placed = cut(streams(sized, seed).join(per_source, "sk").withColumn("_row", F.monotonically_increasing_id()))
    # Blocks that a document touches, in each of the readings that the limit allows.
    readings = F.sequence(F.lit(0), F.lit(int(-(-most // 1)) - 1))
    touched = (
        placed.where("size > 0")
        .select("_row", "sk", "size", "start", "source_size", F.explode(readings).alias("reading"))
        .withColumn("lo", F.col("start") + F.col("reading") * F.col("source_size"))
        .withColumn("hi", F.col("lo") + F.col("size"))
        .select("_row", "sk", "reading", "lo", "hi", F.explode(F.sequence(F.expr(f"lo div {block_tokens}"), F.expr(f"(hi - 1) div {block_tokens}"))).alias("rank"))
    )
    slots = schedule(targets, block_tokens).select(key.alias("sk"), "rank", "tokens")
    begins = F.col("rank") * block_tokens
    part = F.least("hi", begins + F.col("tokens")) - F.greatest("lo", begins)
    taken = touched.join(slots, ["sk", "rank"]).withColumn("part", F.greatest(part, F.lit(0))).groupBy("_row").agg(F.sum(F.when(F.col("reading") == 0, F.col("part")).otherwise(0)).alias("first"), F.sum("part").alias("taken"))
    zero = F.lit(0).cast("long")
    return placed.join(taken, "_row", "left").select("doc_id", "source", "size", "source_size", "target", "start", F.coalesce("first", zero).alias("first"), F.coalesce("taken", zero).alias("taken"))


def mixed_documents(docs: DataFrame, text: str = "text", source: str = "source", doc_id: str = "doc_id", **options) -> DataFrame:
    """``docs`` as the mix reads them: a row for each reading that takes at least half of the document's words, columns unchanged."""
    plan = mixed(docs, text, source, doc_id, **options)
    copies = (2 * F.col("first") >= F.col("size")).cast("int") + (2 * (F.col("taken") - F.col("first")) >= F.col("size")).cast("int")
    # Rows that share an id and a size are dealt as one: their readings go to each of them in turn.
    plan = plan.where("size > 0").select(F.col("doc_id").alias("_id"), F.col("source").alias("_source"), F.col("size").alias("_size"), copies.alias("_copies"))
    plan = plan.groupBy("_id", "_source", "_size").agg(F.max("_copies").alias("_copies")).where("_copies > 0")
    plan = plan.select("_id", "_source", "_size", F.explode(F.sequence(F.lit(1), F.col("_copies"))).alias("_copy"))
    same = F.col(f"d.`{doc_id}`").eqNullSafe(F.col("p._id")) & F.col(f"d.`{source}`").eqNullSafe(F.col("p._source")) & (word_count(F.col(f"d.`{text}`")) == F.col("p._size"))
    return docs.alias("d").join(plan.alias("p"), same).select(*[F.col(f"d.`{c}`") for c in docs.columns])
