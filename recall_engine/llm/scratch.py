"""Where intermediate results are kept: the shared folder that the session names in ``spark.checkpoint.dir``."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of this session. Only a session without the setting (tests, local mode) gets a folder of its own."""
    sc = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None)
    current = sc._jsc.sc().getCheckpointDir()
    if root is None:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        if not current.isDefined():
            sc.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="recall_engine_"))
        return sc._jsc.sc().getCheckpointDir().get()
    if not current.isDefined():
        sc.setCheckpointDir(root)
    return root


def cut(df: DataFrame) -> DataFrame:
    """``df`` computed once, kept in the shared folder and read from there: later stages, and retries after a lost executor, start from it."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new folder's path below the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def release(spark: SparkSession) -> None:
    """Lets Spark remove the shuffle files of finished steps now, not at the driver's next garbage collection: they can be
    as large as the input, and their results are kept by ``cut``."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
