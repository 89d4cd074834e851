"""Results computed once and read several times, in the shared folder that the session names."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Parts in which large tables are made whose shuffles would lie on disk together, and rows from which on there is one more part.
SLICES = 4
SLICE_ROWS = 1_000_000


def kept(df: DataFrame) -> DataFrame:
    """``df`` computed now and read from the folder in ``spark.checkpoint.dir`` after: its plan starts there, and a lost executor
    costs no recomputation. Spark removes the files when the table is out of use and the session asks for that
    (``spark.cleaner.referenceTracking.cleanCheckpoints``). Only a local session without the setting gets a folder of its own, until its end.

    The rows are compressed columns, a fraction of a checkpoint's rows, and later readers read the columns that they need. They lie
    in the folder of an empty checkpoint, which stands beside them in a union, so Spark's cleaner removes both together.
    """
    spark = df.sparkSession
    checkpoint_folder(spark)
    tie = spark.range(0).coalesce(1).select(*[F.lit(None).cast(f.dataType).alias(f.name) for f in df.schema]).checkpoint(eager=True)
    path = f"{tie._jdf.queryExecution().logical().rdd().getCheckpointFile().get()}/table"
    df.write.option("compression", "zstd").parquet(path)
    # The shuffles behind the table are garbage now. Spark deletes their files only after a collection on the driver.
    gc.collect()  # plans are held by objects of Python
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()  # and by the last events
    spark.sparkContext._jvm.System.gc()
    return spark.read.schema(df.schema).parquet(path).unionAll(tie)


def kept_in_slices(of: Callable[[int, int], DataFrame], rows: int) -> DataFrame:
    """The union of ``of(k, n)`` for each k below n, computed one after the other: the shuffles of one slice alone lie on disk at a
    time. ``rows``, about the number that goes in, decides n, at most SLICES."""
    n = min(SLICES, 1 + rows // SLICE_ROWS)
    return reduce(DataFrame.unionAll, [kept(of(k, n)) for k in range(n)])


def checkpoint_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; only a local session without the setting gets one of its own."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        root = spark.conf.get("spark.checkpoint.dir", None)
        if root is None:
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
            own = tempfile.mkdtemp(prefix="recall_engine_")
            atexit.register(shutil.rmtree, own, True)
            root = f"file://{own}"
        sc.setCheckpointDir(root)
    return sc._jsc.sc().getCheckpointDir().get()
