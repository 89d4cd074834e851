"""Compressed rows: one row per s with the sorted list of its t and the offset of the list in the whole."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

CHUNKS = 1 << 10
MAX_ROW_LEN = 1 << 16
ROW_CHUNKS = 1 << 6


def build(pairs: DataFrame, max_row_len: int = MAX_ROW_LEN, chunks: int = ROW_CHUNKS) -> DataFrame:
    """s_id, part, row_offset, row_len, t_ids in the order of s_id's hash chunk, then s_id.

    Offsets are prefix sums in two steps, over chunks and then inside a chunk, so no task sees all rows. Lists longer than
    ``max_row_len`` are in parts, each sorted.
    """
    # Lists are cut before they are gathered. The rank of t within s is a prefix sum over hash chunks of t and a place inside
    # its chunk, so a hot s is spread over ``chunks`` tasks.
    dealt = pairs.select("s_id", "t_id").withColumn("_c", F.pmod(F.xxhash64("t_id"), F.lit(chunks)).cast("int"))
    per = dealt.groupBy("s_id", "_c").agg(F.count("*").alias("_n"))
    total, earlier = Window.partitionBy("s_id"), Window.partitionBy("s_id").orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)  # at most ``chunks`` rows
    per = per.select(F.col("s_id").alias("_s"), F.col("_c").alias("_k"), F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_before"), F.sum("_n").over(total).alias("_all")).where(F.col("_all") > max_row_len)
    long = dealt.join(per, (F.col("s_id") == F.col("_s")) & (F.col("_c") == F.col("_k")), "left")
    inside = F.row_number().over(Window.partitionBy("s_id", "_c").orderBy("t_id")) - 1
    ranked = long.withColumn("part", F.when(F.col("_all").isNull(), 0).otherwise(F.floor((F.col("_before") + inside) / max_row_len)).cast("int")).select("s_id", "t_id", "part")
    rows = ranked.groupBy("s_id", "part").agg(F.sort_array(F.collect_list("t_id")).alias("t_ids")).withColumn("row_len", F.size("t_ids").cast("long"))
    rows = rows.withColumn("chunk", F.conv(F.substring(F.md5("s_id"), 1, 4), 16, 10).cast("int") % CHUNKS)
    totals = rows.groupBy("chunk").agg(F.sum("row_len").alias("n"))
    before = Window.orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)  # one row per chunk
    totals = totals.select("chunk", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("chunk").orderBy("s_id", "part").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("inside", F.coalesce(F.sum("row_len").over(inside), F.lit(0)))
    return rows.join(F.broadcast(totals), "chunk").select("s_id", "part", (F.col("base") + F.col("inside")).alias("row_offset"), "row_len", "t_ids")  # at most CHUNKS rows


def explode(csr: DataFrame) -> DataFrame:
    """The pairs again, with their dense index."""
    return csr.select("s_id", "row_offset", F.posexplode("t_ids").alias("pos", "t_id")).select("s_id", "t_id", (F.col("row_offset") + F.col("pos")).alias("index"))
