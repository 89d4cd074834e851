"""SQL surface: views, functions and a calibration of any table with a score and a label."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions import rules, strata
from .operators import features, grid
from .functions.kdop import relate
from .params import Params
from .plans import calibrate as plan
from .sources.layers import workload


def register(spark: SparkSession) -> None:
    """The scalar function rank_for(rule, n, target_mille, alpha) and the table function recall_curve_of(p and y arrays)."""
    spark.udf.register("rank_for", lambda rule, n, target, alpha: rules.rank(rule, int(n), int(target), float(alpha)), T.LongType())
    spark.udtf.register("recall_curve_of", _curve_udtf())


def _curve_udtf():
    @F.udtf(returnType="rank int, tau double, recall double")
    class RecallCurve:
        """The recall at each positive of a sample, given as arrays."""

        def eval(self, p: list, y: list):
            pairs = sorted(zip(p, y, strict=True), key=lambda x: -x[0])
            total = sum(1 for _, v in pairs if v) or 1
            hits = 0
            for score, good in pairs:
                if good:
                    hits += 1
                    yield hits, float(score), hits / total

    return RecallCurve


def views(spark: SparkSession, sf_dir: str, name: str = "w4") -> None:
    """Temporary views ``candidates`` and ``scored`` of a workload."""
    pairs = grid.candidates(*workload(spark, sf_dir, name))
    pairs.createOrReplaceTempView("candidates")
    scored = features.scored(pairs).select("pair_id", "p", strata.equal_width(F.col("p")).alias("d"), relate("covers").alias("y"))
    scored.createOrReplaceTempView("scored")


def box_join(a: DataFrame, b: DataFrame) -> DataFrame:
    """Pairs of rows of two tables (id, x0, x1, y0, y1) whose boxes share a point, planned as a grid join."""
    return grid.candidates(a, b).drop("shared_cells")


def calibrate(spark: SparkSession, table: str, score: str, label: str, target_mille: int, key: str = "pair_id", params: Params = Params(), **options) -> DataFrame:
    """One row: the threshold of any table with a key, a score in [0, 1] and a boolean label."""
    t = spark.table(table)
    scored = t.select(F.col(key).cast("string").alias("pair_id"), F.col(score).cast("double").alias("p"), F.col(label).cast("boolean").alias("y"))
    scored = scored.withColumn("d", strata.equal_width(F.col("p")))
    r = plan.calibrate(scored, F.col("y"), target_mille, params=params.at_most(scored.count()), **options)
    return spark.createDataFrame([(target_mille, r.method, r.tau, float(r.ci[0]), float(r.ci[1]), r.feasible, r.label_cost)], "target_mille int, method string, tau double, ci_low double, ci_high double, feasible boolean, label_cost long")
