"""The flagship workload by the stages of the published run-time table, timed."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions import strata
from ..functions.kdop import relate
from ..keep import kept
from ..operators import features, grid, measures
from ..params import PUBLISHED
from ..sources.layers import workload
from . import experiment, ranker


def timed(spark: SparkSession, sf_dir: str, w: str = "w4") -> tuple[measures.StageTimer, dict[str, object]]:
    """The timer, and what the run reaches: recall and cost per target, candidates, labels for training."""
    timer, found = measures.StageTimer(), {}
    with timer.stage("indexing"):
        pairs = kept(grid.candidates(*workload(spark, sf_dir, w)).withColumn("y", relate("covers")))
        n = pairs.count()
    timer.rows["indexing"] = n
    with timer.stage("initialisation", n):
        raw = kept(features.raw(pairs).select("pair_id", "y", *features.NAMES))
        scaled = features.scale(raw, features.fit_minmax(raw))
    params = PUBLISHED.at_most(n)
    with timer.stage("training"):
        net, label_cost = ranker.learned(scaled, F.col("y"), params.pool, params.labels, params.base_seed)
    with timer.stage("inference", n):
        scored = kept(ranker.score(scaled, net, ("pair_id", "y"), batch=params.batch).withColumn("d", strata.equal_width(F.col("p"))).select("pair_id", "p", "d", "y"))
    with timer.stage("sampling_and_calibration", n):
        rows = experiment.thresholds(scored, w, params)
    with timer.stage("verification", n):
        runs = experiment.runs(spark, scored, rows).collect()
    for r in runs:
        if r.method == "ivw_min":
            found[f"recall_{r.target_mille}"] = round(r.recall, 4)
            found[f"cost_{r.target_mille}"] = round(r.cost_fraction, 4)
    return timer, found | {"candidates": n, "label_cost_training": label_cost}
