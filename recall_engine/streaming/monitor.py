"""Streams of scored pairs: review by a fixed threshold, drift of rates, and a hash sample kept up to date."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import hashing, strata
from ..keep import checkpoint_folder, kept

#: Where a replay's time ends.
END = "9000-01-01 00:00:00"

EVENT_SCHEMA = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def replay(spark: SparkSession, folder: str, pattern: str = "events.parquet", files_per_trigger: int = 1) -> DataFrame:
    """Event files of a folder as a stream of scored pairs: score value / 500, positive if a purchase."""
    return scored(spark.readStream.schema(EVENT_SCHEMA).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", files_per_trigger).parquet(folder))


def scored(raw: DataFrame) -> DataFrame:
    p = F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("value") / 500.0))
    return raw.select("event_id", "ts", "user_id", p.alias("p"), (F.col("event_type") == "purchase").alias("y"))


def reviewed(stream: DataFrame, tau: float) -> DataFrame:
    return stream.where(F.col("p") >= tau)


def drift(stream: DataFrame, tau: float, length: str = "1 hour", slide: str | None = None, late: str = "30 minutes") -> DataFrame:
    """Counts, positives and recall at ``tau`` by tumbling or sliding windows; rows later than the watermark are dropped and counted by Spark."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    above = F.col("p") >= tau
    out = stream.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.count_if("y").alias("pos"), F.count_if(above & F.col("y")).alias("hits"), F.count_if(above).alias("above"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "pos", "hits", "above", F.try_divide("hits", "pos").alias("recall"))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "30 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def unique(stream: DataFrame, late: str = "30 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def bottom_k(stream: DataFrame, k: int, seed: int, buckets: int = 16) -> DataFrame:
    """Per stratum and bucket the ``k`` smallest keys so far, as state; an update is emitted when they change.

    Bottom-k sets merge exactly, so the k smallest of all updates are the batch sample, whatever the order of arrival.
    The state of a group holds at most k keys; buckets spread a hot stratum.
    """
    d = strata.equal_width(F.col("p"))
    keyed = stream.select("event_id", d.alias("d"), hashing.key(F.col("event_id"), d, seed).alias("hash_key")).withColumn("bucket", F.pmod(F.col("hash_key"), F.lit(buckets)).cast("int"))

    def update(group: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        keys, ids = state.get if state.exists else ([], [])
        have = dict(zip(keys, ids, strict=True))
        before = set(have)
        for f in frames:
            have.update(zip(f["hash_key"].tolist(), f["event_id"].tolist(), strict=True))
        best = sorted(have)[:k]
        state.update((best, [have[x] for x in best]))
        fresh = [x for x in best if x not in before]
        yield pd.DataFrame({"d": [group[0]] * len(fresh), "event_id": [have[x] for x in fresh], "hash_key": fresh})

    return keyed.groupBy("d", "bucket").applyInPandasWithState(update, "d int, event_id long, hash_key long", "keys array<long>, ids array<long>", "append", "NoTimeout")


def run_to_end(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Everything that is there, through a memory table; for checks and small replays."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def all_sessions(spark: SparkSession, folder: str, pattern: str = "events.parquet") -> DataFrame:
    """Every session of a replay, the last ones included. Sessions go to files when they close, so none passes through the driver.

    All events are read in one batch, so none is late, and with them a mark long after them, which closes all sessions but its own.
    """
    root = f"{checkpoint_folder(spark)}/sessions-{uuid.uuid4().hex}"
    mark = spark.range(1).select(*[(F.lit(END).cast("timestamp") if f.name == "ts" else F.lit(None).cast(f.dataType)).alias(f.name) for f in EVENT_SCHEMA])
    mark.write.parquet(f"{root}/mark")
    marked = scored(spark.readStream.schema(EVENT_SCHEMA).parquet(f"{root}/mark"))
    stream = sessions(replay(spark, folder, pattern, 1 << 30).unionByName(marked))
    stream.writeStream.format("parquet").outputMode("append").option("path", f"{root}/sessions").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    found = kept(spark.read.schema(stream.schema).parquet(f"{root}/sessions"))
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(root)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return found


def to_table(stream: DataFrame, path: str, checkpoint: str):
    """Each micro-batch as files; a batch that runs again replaces its own folder."""
    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(save).option("checkpointLocation", checkpoint).start()
