"""More queries with SQL counterparts: static scores, weighted bounds, baselines through ``calibrate``, the ensemble at its published
replicates and subsamples, spreads, costs, streams run to their end."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import hashing, rules, strata
from .functions.kdop import relate
from .keep import kept
from .operators import features, grid, measures, sampler
from .params import PUBLISHED, RULES, TARGETS
from .plans import bootstrap, calibrate, ensemble
from .queries import (
    _BOOT_SQL, _BOX, _COVERS, _GX, _GY, _HIT, _OUT, _PERI, _RAW_SQL, _SIZES, _shown, _stats_sql, BOOT, K, RELEVANT, SEED, candidate_pairs, candidates_sql, chosen_sql, hashed_moments, keyed_sql, positives_of, proportional_sql,
    r6, ranks_sql, raw_features, register, scored_pairs, scored_sql, split_sample,
)
from .sources import io
from .sources.layers import layer_sql, ring, workload
from .streaming import monitor

Z = "1.2815515655446004::DOUBLE"
_TARGET_ROWS = "(VALUES (700), (800), (900)) t(v)"

# --- Static scores -------------------------------------------------------------------------------------------------

_NEAR = f"(1.0::DOUBLE - ({_GX} / ((s_x1 - s_x0)::DOUBLE + (t_x1 - t_x0)::DOUBLE) + {_GY} / ((s_y1 - s_y0)::DOUBLE + (t_y1 - t_y0)::DOUBLE)) / 2.0::DOUBLE)"
_KINDS = {"overlap": f"{_HIT} / {_BOX['t']}", "centre": _NEAR, "margin": "(least(t_x0 - s_x0, s_x1 - t_x1, t_y0 - s_y0, s_y1 - t_y1) + 128.0::DOUBLE) / 256.0::DOUBLE"}
for _kind, _sql in _KINDS.items():
    register(f"heuristic_{_kind}_w4", f"WITH {candidates_sql('w4')}, p0 AS (SELECT *, least(1.0::DOUBLE, greatest(0.0::DOUBLE, {_sql})) AS p FROM c) SELECT pair_id, round(p, 6) AS p, CAST(least(9, floor(p * 10)) AS INTEGER) AS d, {_COVERS} AS y FROM p0")(
        lambda spark, sf_dir, k=_kind: scored_pairs(spark, sf_dir, "w4", k).select("pair_id", r6("p").alias("p"), "d", "y")
    )

_CORNERS = {a: f"CASE WHEN {a}_c = 0 THEN 4 ELSE 8 END" for a in "st"}


@register("feature_corners_w1", f"WITH {candidates_sql('w1')} SELECT pair_id, least({_CORNERS['s']}, {_CORNERS['t']}) / greatest({_CORNERS['s']}, {_CORNERS['t']})::DOUBLE AS f16 FROM c")
def feature_corners_w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ratio of corners, on the workload where boxes without cut corners meet octagons."""
    return raw_features(spark, sf_dir, "w1").select("pair_id", "f16")


def _cells_sql(w: str) -> str:
    return f"""SELECT '{w}' AS workload, * FROM (WITH {candidates_sql(w)}, z AS (SELECT greatest(1, avg(x1 - x0)) AS tx, greatest(1, avg(y1 - y0)) AS ty FROM s),
l AS (SELECT 's' AS side, * FROM s UNION ALL SELECT 't', * FROM t),
lx AS (SELECT side, y0, y1, ty, unnest(range(CAST(floor(x0 / tx) AS BIGINT), CAST(floor(x1 / tx) AS BIGINT) + 1)) AS cx FROM l, z),
lc AS (SELECT side, cx, unnest(range(CAST(floor(y0 / ty) AS BIGINT), CAST(floor(y1 / ty) AS BIGINT) + 1)) AS cy FROM lx),
n AS (SELECT cx, cy, count(*) FILTER (side = 's') * count(*) FILTER (side = 't') AS m FROM lc GROUP BY ALL)
SELECT (SELECT count(*) FROM s) AS n_s, (SELECT count(*) FROM t) AS n_t, (SELECT CAST(sum(m) AS BIGINT) FROM n) AS n_cell_rows, count(*) AS n_box_hits FROM c)"""


@register("grid_statistics", " UNION ALL ".join(_cells_sql(w) for w in ("w1", "w2", "w3", "w4")))
def grid_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes, pairs under a common cell and pairs whose boxes meet, of each workload."""
    out = None
    for w in ("w1", "w2", "w3", "w4"):
        x = grid.dataset_stats(*workload(spark, sf_dir, w), relate(RELEVANT)).select(F.lit(w).alias("workload"), "n_s", "n_t", "n_cell_rows", "n_box_hits")
        out = x if out is None else out.unionByName(x)
    return out


def _wkt_sql() -> str:
    corners = [("x0 + c", "y0"), ("x1 - c", "y0"), ("x1", "y0 + c"), ("x1", "y1 - c"), ("x1 - c", "y1"), ("x0 + c", "y1"), ("x0", "y1 - c"), ("x0", "y0 + c")]
    text = " || ',' || ".join(f"CAST(({x})::DOUBLE AS VARCHAR) || ' ' || CAST(({y})::DOUBLE AS VARCHAR)" for x, y in [*corners, corners[0]])
    return f"SELECT id, CAST(16 AS INTEGER) AS corners_before, CAST(8 AS INTEGER) AS corners, 'POLYGON((' || {text} || '))' AS wkt FROM ({layer_sql('s_cust')})"


@register("simplify_rings", _wkt_sql())
def simplify_rings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Octagons with a point in the middle of each edge, reduced to their corners."""
    from .functions import polygons

    s, _ = workload(spark, sf_dir, "w1")
    r = F.col("ring")
    turned = F.concat(F.slice(r, 2, 7), F.slice(r, 1, 1))
    fine = F.flatten(F.zip_with(r, turned, lambda a, b: F.array(a, F.struct(((a["x"] + b["x"]) / 2).alias("x"), ((a["y"] + b["y"]) / 2).alias("y")))))
    x = s.select("id", ring().alias("ring")).withColumn("ring", fine).withColumn("corners_before", F.size("ring"))
    return polygons.simplified(x, "ring", 0.1).select("id", "corners_before", F.size("ring").alias("corners"), io.to_wkt(F.col("ring")).alias("wkt"))


# --- Samples -------------------------------------------------------------------------------------------------------


@register(
    "sample_neyman",
    f"""WITH {scored_sql("w4")}, {keyed_sql(SEED)}, g AS (SELECT d, count(*) AS n_h, coalesce(stddev_samp(p), 0) AS sd FROM sc GROUP BY d),
q AS (SELECT d, n_h, least(n_h, greatest(1, CAST(round_even({K} * (n_h * sd) / sum(n_h * sd) OVER (), 0) AS BIGINT))) AS quota_h FROM g), {chosen_sql()} {_OUT}""",
)
def sample_neyman(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quotas in proportion to a stratum's size and the spread of its scores."""
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    profile = measures.score_profile(x).collect()  # one row per stratum
    return _shown(sampler.sample(x, K, SEED, "neyman", "md5", sigma={r.d: r.sd_p for r in profile}, n={r.d: r.n for r in profile}))


# --- Weighted bounds and baselines, through calibrate ----------------------------------------------------------------

_EQUAL = f"""WITH {scored_sql("w4")}, {keyed_sql(PUBLISHED.base_seed + 1)}, {_SIZES}, q0 AS (SELECT *, least({K}, n) AS k, count(*) OVER () AS h, row_number() OVER (ORDER BY d) AS pos FROM nh),
q AS (SELECT d, n_h, least(n_h, k // h + CASE WHEN pos <= k % h THEN 1 ELSE 0 END) AS quota_h FROM q0), {chosen_sql()}"""
_STEPS = 4000


def _weighted_sql(sample: str) -> str:
    """(rule, target_mille, tau) of the weighted bounds: the first positive, by falling score, up to which the share of weight suffices.

    Wilson's bound has a closed inverse; the beta bounds are integrated by the midpoint rule at each positive.
    """
    def beta(extra_a: str, extra_b: str) -> str:
        a, b = f"(share * n_eff + {extra_a})", f"((1 - share) * n_eff + {extra_b})"
        return f"(SELECT sum(exp(lgamma({a} + {b}) - lgamma({a}) - lgamma({b}) + ({a} - 1) * ln(x * (i + 0.5) / {_STEPS}) + ({b} - 1) * ln(1 - x * (i + 0.5) / {_STEPS}))) * x / {_STEPS} FROM (SELECT unnest(range(0, {_STEPS})) AS i))"

    return f"""{sample},
ps AS (SELECT p, sum(n_h / quota_h::DOUBLE) OVER (ORDER BY p DESC, n_h / quota_h::DOUBLE ROWS UNBOUNDED PRECEDING) / sum(n_h / quota_h::DOUBLE) OVER () AS share,
       sum(n_h / quota_h::DOUBLE) OVER () ^ 2 / sum((n_h / quota_h::DOUBLE) ^ 2) OVER () AS n_eff FROM ch WHERE y),
tg AS (SELECT p, share, n_eff, t.v AS target_mille, t.v / 1000.0::DOUBLE AS x FROM ps, {_TARGET_ROWS} WHERE share < 1 AND share > t.v / 1000.0 AND share < t.v / 1000.0 + 8 * sqrt(t.v / 1000.0 * (1 - t.v / 1000.0) / n_eff) + 20 / n_eff),
hit AS (SELECT 'wilson' AS rule, target_mille, p FROM tg WHERE share >= x + {Z} * sqrt(x * (1 - x) / n_eff)
  UNION ALL SELECT 'exact_beta', target_mille, p FROM tg WHERE {beta("0", "1")} <= 0.1
  UNION ALL SELECT 'jeffreys', target_mille, p FROM tg WHERE {beta("0.5", "0.5")} <= 0.1
  UNION ALL SELECT 'quantile', target_mille, p FROM tg WHERE share > x)
SELECT rule, CAST(target_mille AS INTEGER) AS target_mille, round(max(p), 6) AS tau FROM hit GROUP BY ALL"""


@register("tau_bounds_weighted_w4", _weighted_sql(_EQUAL))
def tau_bounds_weighted_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All four rules with design weights, as calibration uses them."""
    sample = sampler.sample(kept(scored_pairs(spark, sf_dir, "w4")), K, PUBLISHED.base_seed + 1, "equal", "md5")
    g = positives_of(sample)
    found = [(r, t, round(tau, 6)) for t in TARGETS for r, tau in bootstrap.thresholds(g["p"], g["w"], RULES, t, 0.1).items() if tau is not None]
    return spark.createDataFrame(found, "rule string, target_mille int, tau double")


_RANDOM_SEED = (PUBLISHED.base_seed + 1) ^ 0x5DEECE66D
_RANDOM = f"WITH {scored_sql('w4')}, {keyed_sql(_RANDOM_SEED, '0')}, ch AS (SELECT * FROM ky ORDER BY hash_key LIMIT {K})"
_PLACES = "ps AS (SELECT *, row_number() OVER (ORDER BY p DESC, pair_id) AS place FROM ch WHERE y), ns AS (SELECT count(*) AS n FROM ps)"


def _calibrated(spark: SparkSession, sf_dir: str, methods: tuple[str, ...], **options) -> DataFrame:
    """(method, target_mille, tau) as a user of ``calibrate`` gets them, with keys that SQL has too."""
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    params = replace(PUBLISHED, k=K)
    found = [(m, t, round(calibrate.calibrate(x, F.col("y"), t, m, params, family="md5", **options).tau, 6)) for m in methods for t in TARGETS]
    return spark.createDataFrame(found, "method string, target_mille int, tau double")


register(
    "calibrated_random_w4",
    f"""{_RANDOM}, {_PLACES}, {ranks_sql("ns")},
lb AS (SELECT p, place / n::DOUBLE - {Z} * sqrt((place * (1 - place / n::DOUBLE) ** 2 + (n - place) * (place / n::DOUBLE) ** 2) / (n * n)::DOUBLE) AS bound FROM ps, ns)
SELECT rule AS method, CAST(target_mille AS INTEGER) AS target_mille, round(p, 6) AS tau FROM rk JOIN ps ON place = r
UNION ALL SELECT 'wilson_random', CAST(target_mille AS INTEGER), round(p, 6) FROM rk JOIN ps ON place = r WHERE rule = 'wilson'
UNION ALL SELECT 'ht_lower', CAST(t.v AS INTEGER), round(max(p), 6) FROM lb, {_TARGET_ROWS} WHERE bound >= t.v / 1000.0::DOUBLE - 1e-15 GROUP BY t.v""",
)(lambda spark, sf_dir: _calibrated(spark, sf_dir, ("ht_lower", "wilson_random", *RULES)))
register("calibrated_hashed_w4", f"SELECT 'wilson_hash' AS method, target_mille, tau FROM ({_weighted_sql(_EQUAL)}) WHERE rule = 'wilson'")(lambda spark, sf_dir: _calibrated(spark, sf_dir, ("wilson_hash",), quota="equal"))

# --- The ensemble at its published numbers of subsamples and replicates -----------------------------------------------

S, B, NINE_K = PUBLISHED.subsamples, PUBLISHED.n_boot, 3000
_T8 = "1.8595480375308981::DOUBLE"
_NINE = f"""{scored_sql("w4")}, {proportional_sql(NINE_K)}, {", ".join(keyed_sql(SEED + j, name=f"ky{j}") for j in range(S))},
sp AS ({" UNION ALL ".join(f"SELECT {j} AS subsample, pair_id, d, p, y FROM (SELECT ky{j}.*, quota_h, row_number() OVER (PARTITION BY ky{j}.d ORDER BY hash_key) AS r FROM ky{j} JOIN q USING (d)) WHERE r <= quota_h" for j in range(S))}),
ps AS (SELECT *, row_number() OVER (PARTITION BY subsample ORDER BY p DESC, pair_id) AS place FROM sp WHERE y),
ns AS (SELECT subsample, count(*) AS n FROM ps GROUP BY subsample), nd AS (SELECT DISTINCT n FROM ns), {ranks_sql("nd")},
dr AS (SELECT subsample, n, b.b, i.i, CAST('0x' || substr(md5(concat_ws('|', '7', CAST(subsample AS VARCHAR), CAST(b.b AS VARCHAR), CAST(i.i AS VARCHAR))), 1, 8) AS BIGINT) % n + 1 AS place
       FROM ns, (SELECT unnest(range(0, {B})) AS b) b, LATERAL (SELECT unnest(range(0, n)) AS i) i),
od AS (SELECT *, row_number() OVER (PARTITION BY subsample, b ORDER BY place, i) AS r FROM dr),
rp AS (SELECT od.subsample, rk.target_mille, rk.rule, od.b AS replicate, ps.p AS tau FROM od JOIN rk ON rk.n = od.n AND rk.r = od.r JOIN ps ON ps.subsample = od.subsample AND ps.place = od.place),
mo AS (SELECT target_mille, subsample, rule, avg(tau) AS mean_tau, var_samp(tau) AS var_tau FROM rp GROUP BY ALL),
we AS (SELECT *, (1 / greatest(var_tau, 1e-12)) / sum(1 / greatest(var_tau, 1e-12)) OVER (PARTITION BY target_mille, subsample) AS weight FROM mo),
en AS (SELECT target_mille, subsample, sum(weight * mean_tau) AS tau_ens FROM we GROUP BY ALL),
fu AS (SELECT target_mille, min(tau_ens) AS tau_min, median(tau_ens) AS tau_median, avg(tau_ens) AS tau_mean, count(*) AS n, list(tau_ens) AS taus FROM en GROUP BY target_mille),
ci AS (SELECT *, {_T8} * sqrt(list_sum(list_transform(taus, lambda x: (x - tau_min) * (x - tau_min))) / (n * (n - 1))) AS half FROM fu)"""


def nine_replicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hash-drawn replicates of all rules and targets on nine samples."""
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    positives = kept(sampler.subsamples(x, S, NINE_K, SEED, "reseed", "proportional", "md5").where("y").select("subsample", "pair_id", "d", "p", "w"))
    return kept(bootstrap.hashed_replicates(positives, TARGETS, B))


@register("ensemble_nine_w4", f"WITH {_NINE} SELECT CAST(target_mille AS INTEGER) AS target_mille, round(tau_min, 6) AS tau_min, round(tau_median, 6) AS tau_median, round(tau_mean, 6) AS tau_mean, round(tau_min - half, 6) AS ci_low, round(tau_min + half, 6) AS ci_high FROM ci")
def ensemble_nine_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nine subsamples, 200 replicates, three targets: inverse-variance weights, the three fusions and Student's interval."""
    rows = []
    replicates = nine_replicates(spark, sf_dir)
    for t in TARGETS:
        taus = [r.tau_ens for r in ensemble.ivw(ensemble.moments(replicates.where(F.col("target_mille") == t))).orderBy("subsample").collect()]  # one row per subsample
        low = ensemble.fuse(taus, "min")
        lo, hi = ensemble.student_interval(taus, low)
        rows.append((t, *[round(ensemble.fuse(taus, how), 6) for how in ("min", "median", "mean")], round(lo, 6), round(hi, 6)))
    return spark.createDataFrame(rows, "target_mille int, tau_min double, tau_median double, tau_mean double, ci_low double, ci_high double")


register(
    "threshold_spread_w4",
    f"WITH {_BOOT_SQL} SELECT subsample, rule, round(stddev_samp(tau), 6) AS sd_tau, round(stddev_samp(tau) / avg(tau), 6) AS cv_tau FROM rp GROUP BY ALL",
)(lambda spark, sf_dir: measures.threshold_spread(bootstrap.hashed_replicates(split_sample(spark, sf_dir).where("y"), 800, BOOT), ["subsample", "rule"]).select("subsample", "rule", r6("sd_tau").alias("sd_tau"), r6("cv_tau").alias("cv_tau")))
register(
    "threshold_spread_subsamples_w4",
    f"WITH {_BOOT_SQL} SELECT CAST(800 AS INTEGER) AS target_mille, round(stddev_samp(tau_ens), 6) AS sd_tau, round(stddev_samp(tau_ens) / avg(tau_ens), 6) AS cv_tau FROM en",
)(lambda spark, sf_dir: measures.threshold_spread(ensemble.ivw(hashed_moments(spark, sf_dir)).select(F.lit(800).alias("target_mille"), F.col("tau_ens").alias("tau")), ["target_mille"]).select("target_mille", r6("sd_tau").alias("sd_tau"), r6("cv_tau").alias("cv_tau")))

# --- Costs ---------------------------------------------------------------------------------------------------------

_PRICES = (5.0, 0.01)


@register("review_money_w4", f"WITH {scored_sql('w4')} SELECT t.v AS tau, round({_PRICES[0]}::DOUBLE * count(*) FILTER (p >= t.v) + {_PRICES[1]}::DOUBLE * count(*), 4) AS money FROM sc, (VALUES (0.25::DOUBLE), (0.5::DOUBLE), (0.75::DOUBLE)) t(v) GROUP BY t.v")
def review_money_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What checking the pairs above a threshold and the features of all cost."""
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    return spark.createDataFrame([(t, round(measures.review_money(x, t, *_PRICES), 4)) for t in (0.25, 0.5, 0.75)], "tau double, money double")


# --- Streams, run to their end -------------------------------------------------------------------------------------


def _shown_windows(x: DataFrame, *columns: str) -> DataFrame:
    return x.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), *columns)


_EVENTS = "e AS (SELECT event_id, user_id, ts, least(1, greatest(0, value / 500.0::DOUBLE)) AS p, event_type = 'purchase' AS y FROM events)"
_RATES = "count(*) AS n, count(*) FILTER (y) AS pos, count(*) FILTER (y AND p >= 0.5) AS hits, count(*) FILTER (p >= 0.5) AS above"


@register("stream_drift", f"WITH {_EVENTS} SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, {_RATES} FROM e GROUP BY 1")
def stream_drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All windows, the last ones included: a replay has an end, so the whole result is asked for."""
    return _shown_windows(monitor.run_to_end(monitor.drift(monitor.replay(spark, sf_dir), 0.5), "stream_drift", "complete"), "n", "pos", "hits", "above")


@register("stream_sliding", f"WITH {_EVENTS}, w AS (SELECT date_trunc('hour', ts) - INTERVAL 1 HOUR * k.k AS start, y, p FROM e, (VALUES (0), (1)) k(k)) SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, {_RATES} FROM w GROUP BY 1")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown_windows(monitor.run_to_end(monitor.drift(monitor.replay(spark, sf_dir), 0.5, "2 hours", "1 hour"), "stream_sliding", "complete"), "n", "pos", "hits", "above")


@register("stream_sessions", f"""WITH {_EVENTS}, g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM e),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, strftime(date_trunc('second', min(ts)), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown_windows(monitor.all_sessions(spark, sf_dir), "user_id", "n")


@register("stream_reviewed", f"WITH {_EVENTS} SELECT DISTINCT event_id, user_id, round(p, 6) AS p, y FROM e WHERE p >= 0.5")
def stream_reviewed(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = monitor.run_to_end(monitor.unique(monitor.reviewed(monitor.replay(spark, sf_dir), 0.5)), "stream_reviewed", "append")
    return x.select("event_id", "user_id", r6("p").alias("p"), "y")
