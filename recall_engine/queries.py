"""Registered queries of the calibration engine and, where SQL can express them, the same in DuckDB SQL.

The oracle joins boxes by plain inequalities and ranks by binomial sums from lgamma, so it shares no method with the engine.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import hashing, rules, strata
from .functions.kdop import PREDICATES, relate
from .keep import kept
from .operators import csr, features, grid, measures, sampler, vector_pairs, verify
from .params import PUBLISHED, RULES, TARGETS, Params
from .plans import bootstrap, calibrate, ensemble, experiment, inverse_prob, objective
from .sources.layers import LAYERS, OCTAGON, WORKLOADS, layer, layer_sql, workload

K, SEED = 2000, 2026
BOOT, BOOT_K, BOOT_S = 20, 600, 3
RELEVANT = "covers"
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


def r6(c: Column | str) -> Column:
    return F.round(c, 6)


# --- SQL building blocks -------------------------------------------------------------------------------------------

_SIDES = ", ".join(f"{a}.{c} AS {a}_{c}" for a in "st" for c in OCTAGON)


def candidates_sql(w: str) -> str:
    s, t = WORKLOADS[w]
    return f"""s AS MATERIALIZED ({layer_sql(s)}), t AS MATERIALIZED ({layer_sql(t)}),
c AS MATERIALIZED (SELECT s.id AS s_id, t.id AS t_id, s.id || '|' || t.id AS pair_id, {_SIDES}
      FROM s JOIN t ON s.x0 <= t.x1 AND t.x0 <= s.x1 AND s.y0 <= t.y1 AND t.y0 <= s.y1)"""


_COVERS = " AND ".join(f"s_{a}0 <= t_{a}0 AND t_{a}1 <= s_{a}1" for a in "xyuv")
_COVERED = " AND ".join(f"t_{a}0 <= s_{a}0 AND s_{a}1 <= t_{a}1" for a in "xyuv")
_CLOSED = " AND ".join(f"s_{a}0 <= t_{a}1 AND t_{a}0 <= s_{a}1" for a in "xyuv")
_OPEN = " AND ".join(f"s_{a}0 < t_{a}1 AND t_{a}0 < s_{a}1" for a in "xyuv")
_P = """least(1.0::DOUBLE, greatest(0.0::DOUBLE,
  0.5::DOUBLE * (((least(s_x1, t_x1) - greatest(s_x0, t_x0))::DOUBLE * (least(s_y1, t_y1) - greatest(s_y0, t_y0))::DOUBLE) / ((t_x1 - t_x0)::DOUBLE * (t_y1 - t_y0)::DOUBLE))
  + 0.5::DOUBLE * (1.0::DOUBLE - (abs(s_x0 + s_x1 - t_x0 - t_x1)::DOUBLE / ((s_x1 - s_x0)::DOUBLE + (t_x1 - t_x0)::DOUBLE)
                                + abs(s_y0 + s_y1 - t_y0 - t_y1)::DOUBLE / ((s_y1 - s_y0)::DOUBLE + (t_y1 - t_y0)::DOUBLE)) / 2.0::DOUBLE)))"""


def scored_sql(w: str) -> str:
    return f"""{candidates_sql(w)},
p0 AS (SELECT *, {_P} AS p FROM c),
sc AS MATERIALIZED (SELECT pair_id, p, CAST(least(9, floor(p * 10)) AS INTEGER) AS d, ({_COVERS}) AS y FROM p0)"""


def keyed_sql(seed: int, d: str = "d", name: str = "ky") -> str:
    return f"{name} AS (SELECT *, md5(concat_ws('|', '{seed}', pair_id, CAST({d} AS VARCHAR))) AS hash_key FROM sc)"


_SIZES = "nh AS (SELECT d, count(*) AS n_h, (SELECT count(*) FROM sc) AS n FROM sc GROUP BY d)"


def proportional_sql(k: int) -> str:
    return f"""{_SIZES},
q0 AS (SELECT *, least({k}, n) AS k FROM nh),
q1 AS (SELECT *, k * n_h // n AS base, row_number() OVER (ORDER BY (k * n_h) % n DESC, d) AS pos FROM q0),
q AS (SELECT d, n_h, base + CASE WHEN pos <= k - sum(base) OVER () THEN 1 ELSE 0 END AS quota_h FROM q1)"""


def chosen_sql() -> str:
    return """ch AS (SELECT pair_id, d, p, y, hash_key, n_h, quota_h FROM (
  SELECT ky.*, q.n_h, q.quota_h, row_number() OVER (PARTITION BY ky.d ORDER BY hash_key) AS r FROM ky JOIN q USING (d)) WHERE r <= quota_h)"""


def ranks_sql(sizes: str, targets: tuple[int, ...] = TARGETS, alpha: float = 0.10, names: tuple[str, ...] = RULES) -> str:
    """CTEs that end in rk(n, target_mille, rule, r) for the n in the table ``sizes``; infeasible rules are absent."""
    values = ", ".join(f"({t})" for t in targets)
    z = "1.2815515655446004::DOUBLE"
    wanted = ", ".join(f"'{r}'" for r in names)
    return f"""nt AS (SELECT n, t.v AS target_mille, t.v / 1000.0::DOUBLE AS x FROM {sizes}, (VALUES {values}) t(v)),
ks AS (SELECT nt.*, k.k FROM nt, LATERAL (SELECT unnest(range(0, CAST(n AS BIGINT) + 1)) AS k) k),
pm AS (SELECT *, exp(lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1) + k * ln(x) + (n - k) * ln(1 - x)) AS pmf,
       CASE WHEN k < n THEN exp(lgamma(k + 1) - lgamma(0.5) - lgamma(k + 1.5) + 0.5 * ln(x) + (k + 0.5) * ln(1 - x)) ELSE 0 END AS up,
       CASE WHEN k < n THEN exp(lgamma(n + 1) - lgamma(k + 1.5) - lgamma(n - k + 0.5) + (k + 0.5) * ln(x) + (n - k - 0.5) * ln(1 - x)) ELSE 0 END AS down FROM ks),
tl AS (SELECT *, sum(pmf) OVER (PARTITION BY n, target_mille ORDER BY k DESC) AS tail,
       2 / pi() * asin(sqrt(x)) + sum(up) OVER (PARTITION BY n, target_mille)
         - coalesce(sum(down) OVER (PARTITION BY n, target_mille ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS jeff,
       (k / n::DOUBLE + {z} * {z} / (2 * n) - {z} * sqrt((k / n::DOUBLE) * (1 - k / n::DOUBLE) / n + {z} * {z} / (4 * n * n))) / (1 + {z} * {z} / n) AS wil,
       (k / n::DOUBLE + {z} * {z} / (2 * n) - {z} * sqrt((k / n::DOUBLE) * (1 - k / n::DOUBLE) + {z} * {z} / (4 * n))) / (1 + {z} * {z} / n) AS wip FROM pm),
rk AS (SELECT * FROM (
  SELECT n, target_mille, 'exact_beta' AS rule, min(k) AS r FROM tl WHERE k > 0 AND tail <= {alpha} GROUP BY ALL
  UNION ALL SELECT n, target_mille, 'jeffreys', min(k) FROM tl WHERE k > 0 AND jeff <= {alpha} GROUP BY ALL
  UNION ALL SELECT n, target_mille, 'wilson', min(k) FROM tl WHERE k > 0 AND wil >= x GROUP BY ALL
  UNION ALL SELECT n, target_mille, 'wilson_printed', min(k) FROM tl WHERE k > 0 AND wip >= x GROUP BY ALL
  UNION ALL SELECT n, target_mille, 'quantile', CAST(n AS BIGINT) - greatest(1, (CAST(n AS BIGINT) * (1000 - target_mille) + 999) // 1000) + 1 FROM nt) WHERE rule IN ({wanted}))"""


# --- Engine building blocks ----------------------------------------------------------------------------------------

def candidate_pairs(spark: SparkSession, sf_dir: str, w: str, tiles: int = 1) -> DataFrame:
    return grid.candidates(*workload(spark, sf_dir, w), tiles=tiles)


def scored_pairs(spark: SparkSession, sf_dir: str, w: str, kind: str = "blend", tiles: int = 1) -> DataFrame:
    x = features.scored(candidate_pairs(spark, sf_dir, w, tiles), kind)
    return x.select("pair_id", "p", strata.equal_width(F.col("p")).alias("d"), relate(RELEVANT).alias("y"))


def md5_sample(spark: SparkSession, sf_dir: str, quota: str, k: int = K) -> DataFrame:
    return sampler.sample(kept(scored_pairs(spark, sf_dir, "w4")), k, SEED, quota, "md5")


def positives_of(sample: DataFrame) -> dict[str, np.ndarray]:
    """Scores and weights of a sample's positives, at most k rows."""
    rows = sample.where("y").select("p", "w").orderBy(F.desc("p")).collect()
    return {"p": np.array([r.p for r in rows]), "w": np.array([r.w for r in rows])}


# --- Candidates ----------------------------------------------------------------------------------------------------

for _name in ("s_ord", "t_w4"):
    register(f"layer_{_name}", layer_sql(_name))(lambda spark, sf_dir, n=_name: layer(spark, sf_dir, n))


@register("grid_cell_size", "SELECT " + ", ".join(f"round((SELECT greatest(1, avg({a}1 - {a}0)) FROM ({layer_sql(n)})), 6) AS {n}_{a}" for n in ("s_cust", "s_ord") for a in "xy"))
def grid_cell_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    values = [round(v, 6) for n in ("s_cust", "s_ord") for v in grid.cell_size(layer(spark, sf_dir, n))]
    return spark.createDataFrame([values], "s_cust_x double, s_cust_y double, s_ord_x double, s_ord_y double")


@register("grid_cells_w4", f"""
WITH s AS ({layer_sql("s_ord")}), t AS ({layer_sql("t_w4")}), z AS (SELECT greatest(1, avg(x1 - x0)) AS tx, greatest(1, avg(y1 - y0)) AS ty FROM s),
a AS (SELECT 's' AS side, * FROM s UNION ALL SELECT 't', * FROM t),
cells AS (SELECT side, id, CAST(floor(x0 / tx) AS BIGINT) AS cx0, CAST(floor(x1 / tx) AS BIGINT) AS cx1, CAST(floor(y0 / ty) AS BIGINT) AS cy0, CAST(floor(y1 / ty) AS BIGINT) AS cy1 FROM a, z)
SELECT side, CAST(sum((cx1 - cx0 + 1) * (cy1 - cy0 + 1)) AS BIGINT) AS n_rows, CAST(sum(cx1 + cy1) AS BIGINT) AS top_sum FROM cells GROUP BY side""")
def grid_cells_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, t = workload(spark, sf_dir, "w4")
    theta = grid.cell_size(s)

    def one(side: str, df: DataFrame) -> DataFrame:
        per = grid.assign_cells(df, theta).groupBy("id").agg(F.count("*").alias("n"), (F.max("cx") + F.max("cy")).alias("top"))
        return per.agg(F.lit(side).alias("side"), F.sum("n").alias("n_rows"), F.sum("top").alias("top_sum"))

    return one("s", s).unionAll(one("t", t))


for _w in WORKLOADS:
    register(f"cand_grid_{_w}", f"WITH {candidates_sql(_w)} SELECT s_id, t_id FROM c")(lambda spark, sf_dir, w=_w: candidate_pairs(spark, sf_dir, w).select("s_id", "t_id"))
    register(f"relevant_{_w}", f"WITH {candidates_sql(_w)} SELECT s_id, t_id FROM c WHERE {_COVERS}")(lambda spark, sf_dir, w=_w: candidate_pairs(spark, sf_dir, w).where(relate(RELEVANT)).select("s_id", "t_id"))

_W1 = f"WITH {candidates_sql('w1')} SELECT s_id, t_id FROM c"
register("cand_distinct_w1", _W1)(lambda spark, sf_dir: grid.candidates(*workload(spark, sf_dir, "w1"), dedup="distinct").select("s_id", "t_id"))
register("cand_band_w1", _W1)(lambda spark, sf_dir: grid.band_join(*workload(spark, sf_dir, "w1"), 80.0).select("s_id", "t_id"))
register("cand_extent_classes_w1", _W1)(lambda spark, sf_dir: grid.extent_classes(*workload(spark, sf_dir, "w1")).select("s_id", "t_id"))
register("cand_nested_loop_w1", _W1)(lambda spark, sf_dir: grid.nested_loop(*workload(spark, sf_dir, "w1"), tiles=16).select("s_id", "t_id"))


@register("cand_csr_w1", f"""
WITH {candidates_sql("w1")},
g AS (SELECT s_id, count(*) AS row_len, string_agg(t_id, ',' ORDER BY t_id) AS t_ids, CAST('0x' || substr(md5(s_id), 1, 4) AS INTEGER) % {csr.CHUNKS} AS chunk FROM c GROUP BY s_id)
SELECT s_id, row_len, t_ids, CAST(coalesce(sum(row_len) OVER (ORDER BY chunk, s_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS row_offset FROM g""")
def cand_csr_w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return csr.build(candidate_pairs(spark, sf_dir, "w1")).select("s_id", "row_len", F.array_join("t_ids", ",").alias("t_ids"), "row_offset")


register("csr_round_trip_w1", _W1)(lambda spark, sf_dir: csr.explode(csr.build(candidate_pairs(spark, sf_dir, "w1"))).select("s_id", "t_id"))


def _stats_sql(w: str) -> str:
    return f"""SELECT '{w}' AS workload, * FROM (WITH {candidates_sql(w)}
SELECT (SELECT count(*) FROM s) AS n_s, (SELECT count(*) FROM t) AS n_t, count(*) AS n_box_hits, count(*) FILTER ({_COVERS}) AS n_relevant,
       round((SELECT count(*) FROM s) * (SELECT count(*) FROM t)::DOUBLE / count(*), 6) AS reduction_factor, round(count(*) FILTER ({_COVERS}) / count(*)::DOUBLE, 6) AS relevance_rate FROM c)"""


def _stats(spark: SparkSession, sf_dir: str, w: str) -> DataFrame:
    x = grid.dataset_stats(*workload(spark, sf_dir, w), relate(RELEVANT))
    return x.select(F.lit(w).alias("workload"), "n_s", "n_t", "n_box_hits", "n_relevant", r6("reduction_factor").alias("reduction_factor"), r6("relevance_rate").alias("relevance_rate"))


for _w in WORKLOADS:
    register(f"dataset_stats_{_w}", _stats_sql(_w))(lambda spark, sf_dir, w=_w: _stats(spark, sf_dir, w))

_PREDICATE_SQL = {"intersects": _CLOSED, "disjoint": f"NOT ({_CLOSED})", "contains": _COVERS, "covers": _COVERS, "within": _COVERED, "covered_by": _COVERED, "touches": f"({_CLOSED}) AND NOT ({_OPEN})", "overlaps": f"({_OPEN}) AND NOT ({_COVERS}) AND NOT ({_COVERED})", "equals": f"({_COVERS}) AND ({_COVERED})"}
register("relate_all_w4", f"WITH {candidates_sql('w4')} SELECT " + ", ".join(f"count(*) FILTER ({_PREDICATE_SQL[p]}) AS n_{p}" for p in PREDICATES) + " FROM c")(
    lambda spark, sf_dir: candidate_pairs(spark, sf_dir, "w4").agg(*[F.count_if(relate(p)).alias(f"n_{p}") for p in PREDICATES])
)

# --- Features and scores -------------------------------------------------------------------------------------------

_AREA = {a: f"(({a}_x1 - {a}_x0)::DOUBLE * ({a}_y1 - {a}_y0)::DOUBLE - 2.0 * {a}_c * {a}_c)" for a in "st"}
_PERI = {a: f"(2.0 * (({a}_x1 - {a}_x0) + ({a}_y1 - {a}_y0)) - (8 - 4 * sqrt(2)) * {a}_c)" for a in "st"}
_BOX = {a: f"(({a}_x1 - {a}_x0)::DOUBLE * ({a}_y1 - {a}_y0))" for a in "st"}
_HIT = "((least(s_x1, t_x1) - greatest(s_x0, t_x0))::DOUBLE * (least(s_y1, t_y1) - greatest(s_y0, t_y0)))"
_GX, _GY = "abs(s_x0 + s_x1 - t_x0 - t_x1)::DOUBLE", "abs(s_y0 + s_y1 - t_y0 - t_y1)::DOUBLE"


def _rat(a: str, b: str) -> str:
    return f"CASE WHEN greatest({a}, {b}) = 0 THEN 1.0::DOUBLE ELSE least({a}, {b})::DOUBLE / greatest({a}, {b}) END"


def _cells(axis: str) -> str:
    k = "tx" if axis == "x" else "ty"
    return f"(least(floor(s_{axis}1 / {k}), floor(t_{axis}1 / {k})) - greatest(floor(s_{axis}0 / {k}), floor(t_{axis}0 / {k})) + 1)"


_FEATURE_SQL = [
    _rat(_AREA["s"], _AREA["t"]), _rat(_PERI["s"], _PERI["t"]), f"{_cells('x')} * {_cells('y')}", _HIT, f"{_HIT} / ({_BOX['s']} + {_BOX['t']} - {_HIT})", f"{_HIT} / {_BOX['s']}", f"{_HIT} / {_BOX['t']}",
    f"sqrt({_GX} * {_GX} + {_GY} * {_GY}) / 2", f"{_GX} / 2", f"{_GY} / 2", _rat("(s_x1 - s_x0)", "(t_x1 - t_x0)"), _rat("(s_y1 - s_y0)", "(t_y1 - t_y0)"),
    "count(*) OVER (PARTITION BY s_id)", "count(*) OVER (PARTITION BY t_id)", "least(t_x0 - s_x0, s_x1 - t_x1, t_y0 - s_y0, s_y1 - t_y1)", _rat("CASE WHEN s_c = 0 THEN 4 ELSE 8 END", "CASE WHEN t_c = 0 THEN 4 ELSE 8 END"),
]
_RAW_SQL = f"""{candidates_sql("w4")}, z AS (SELECT greatest(1, avg(x1 - x0)) AS tx, greatest(1, avg(y1 - y0)) AS ty FROM s),
f AS (SELECT pair_id, {", ".join(f"CAST({e} AS DOUBLE) AS {n}" for n, e in zip(features.NAMES, _FEATURE_SQL, strict=True))} FROM c, z)"""
_RANGE = f"rg AS (SELECT {', '.join(f'min({n}) AS {n}_lo, max({n}) AS {n}_hi' for n in features.NAMES)} FROM f)"


def raw_features(spark: SparkSession, sf_dir: str, w: str = "w4") -> DataFrame:
    return features.raw(kept(candidate_pairs(spark, sf_dir, w))).select("pair_id", *features.NAMES)


register("features_raw_w4", f"WITH {_RAW_SQL} SELECT pair_id, {', '.join(f'floor({n} * 1e6::DOUBLE + 0.5::DOUBLE) / 1e6::DOUBLE AS {n}' for n in features.NAMES)} FROM f")(
    lambda spark, sf_dir: raw_features(spark, sf_dir).select("pair_id", *[(F.floor(F.col(n) * 1e6 + 0.5) / 1e6).alias(n) for n in features.NAMES])  # rounding that both engines do alike
)


@register("features_minmax_w4", f"WITH {_RAW_SQL}, {_RANGE} " + " UNION ALL ".join(f"SELECT '{n}' AS feature, round({n}_lo, 6) AS lo, round({n}_hi, 6) AS hi FROM rg" for n in features.NAMES))
def features_minmax_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranges = features.fit_minmax(raw_features(spark, sf_dir))
    return spark.createDataFrame([(n, round(lo, 6), round(hi, 6)) for n, (lo, hi) in ranges.items()], "feature string, lo double, hi double")


@register("features_scaled_w4", f"WITH {_RAW_SQL}, {_RANGE} SELECT pair_id, " + ", ".join(f"round(CASE WHEN {n}_hi <= {n}_lo THEN 0 ELSE least(10000.0::DOUBLE, greatest(0.0::DOUBLE, ({n} - {n}_lo) / ({n}_hi - {n}_lo) * 10000.0::DOUBLE)) END, 4) AS {n}" for n in features.NAMES) + " FROM f, rg")
def features_scaled_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = kept(raw_features(spark, sf_dir))
    return features.scale(x, features.fit_minmax(x)).select("pair_id", *[F.round(n, 4).alias(n) for n in features.NAMES])


register("heuristic_score_w4", f"WITH {scored_sql('w4')} SELECT pair_id, round(p, 6) AS p, d, y FROM sc")(lambda spark, sf_dir: scored_pairs(spark, sf_dir, "w4").select("pair_id", r6("p").alias("p"), "d", "y"))
register("decile_hist_w4", f"WITH {scored_sql('w4')} SELECT d, count(*) AS n, count(*) FILTER (y) AS pos, round(avg(p), 6) AS mean_p, round(coalesce(stddev_samp(p), 0), 6) AS sd_p FROM sc GROUP BY d")(
    lambda spark, sf_dir: measures.score_profile(scored_pairs(spark, sf_dir, "w4")).select("d", "n", "pos", r6("mean_p").alias("mean_p"), r6("sd_p").alias("sd_p"))
)


@register("edges_hist_w4", f"WITH {scored_sql('w4')} SELECT CAST((p >= 0.2) AS INTEGER) + CAST((p >= 0.5) AS INTEGER) + CAST((p >= 0.8) AS INTEGER) AS d, count(*) AS n FROM sc GROUP BY 1")
def edges_hist_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored_pairs(spark, sf_dir, "w4").withColumn("d", strata.edges(F.col("p"), [0.2, 0.5, 0.8])).groupBy("d").agg(F.count("*").alias("n"))


@register("equidepth_w4")
def equidepth_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    return x.withColumn("d", strata.edges(F.col("p"), strata.equi_depth_edges(x))).groupBy("d").agg(F.count("*").alias("n"), F.min("p").alias("lo"), F.max("p").alias("hi"))


# --- Samples -------------------------------------------------------------------------------------------------------

_OUT = "SELECT pair_id, d, round(p, 6) AS p, y, hash_key, CAST(n_h AS BIGINT) AS n_h, CAST(quota_h AS BIGINT) AS quota_h, round(n_h / quota_h::DOUBLE, 6) AS w FROM ch"


def _shown(sample: DataFrame) -> DataFrame:
    return sample.select("pair_id", "d", r6("p").alias("p"), "y", "hash_key", "n_h", "quota_h", r6("w").alias("w"))


register("sample_proportional", f"WITH {scored_sql('w4')}, {keyed_sql(SEED)}, {proportional_sql(K)}, {chosen_sql()} {_OUT}")(lambda spark, sf_dir: _shown(md5_sample(spark, sf_dir, "proportional")))
register(
    "sample_equal",
    f"""WITH {scored_sql("w4")}, {keyed_sql(SEED)}, {_SIZES},
q0 AS (SELECT *, least({K}, n) AS k, count(*) OVER () AS h, row_number() OVER (ORDER BY d) AS pos FROM nh),
q AS (SELECT d, n_h, least(n_h, k // h + CASE WHEN pos <= k % h THEN 1 ELSE 0 END) AS quota_h FROM q0), {chosen_sql()} {_OUT}""",
)(lambda spark, sf_dir: _shown(md5_sample(spark, sf_dir, "equal")))
register(
    "sample_global",
    f"""WITH {scored_sql("w4")}, {keyed_sql(SEED)}, ch AS (SELECT *, (SELECT count(*) FROM sc) AS n_h, least({K}, (SELECT count(*) FROM sc)) AS quota_h FROM ky ORDER BY hash_key LIMIT {K}) {_OUT}""",
)(lambda spark, sf_dir: _shown(md5_sample(spark, sf_dir, "global")))
register(
    "sample_weights",
    f"""WITH {scored_sql("w4")}, {keyed_sql(SEED)}, {proportional_sql(K)}, {chosen_sql()}
SELECT d, CAST(any_value(n_h) AS BIGINT) AS n_h, count(*) AS n_sample, round(sum(n_h / quota_h::DOUBLE), 4) AS weight_sum FROM ch GROUP BY d""",
)(lambda spark, sf_dir: md5_sample(spark, sf_dir, "proportional").groupBy("d").agg(F.first("n_h").alias("n_h"), F.count("*").alias("n_sample"), F.round(F.sum("w"), 4).alias("weight_sum")))

_SPLIT = f"""{scored_sql("w4")}, {keyed_sql(SEED)}, {proportional_sql(BOOT_S * BOOT_K)}, {chosen_sql()},
sp AS (SELECT *, CAST((row_number() OVER (PARTITION BY d ORDER BY hash_key) - 1) % {BOOT_S} AS INTEGER) AS subsample FROM ch)"""


def split_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampler.subsamples(kept(scored_pairs(spark, sf_dir, "w4")), BOOT_S, BOOT_K, SEED, "split", "proportional", "md5")


register("sample_split", f"WITH {_SPLIT} SELECT subsample, pair_id, d, y FROM sp")(lambda spark, sf_dir: split_sample(spark, sf_dir).select("subsample", "pair_id", "d", "y"))


@register(
    "sample_reseed",
    f"WITH {scored_sql('w4')}, {proportional_sql(K)}, "
    + ", ".join(f"{keyed_sql(SEED + j, name=f'ky{j}')}" for j in range(3))
    + " "
    + " UNION ALL ".join(f"SELECT {j} AS subsample, pair_id, d FROM (SELECT ky{j}.*, quota_h, row_number() OVER (PARTITION BY ky{j}.d ORDER BY hash_key) AS r FROM ky{j} JOIN q USING (d)) WHERE r <= quota_h" for j in range(3)),
)
def sample_reseed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampler.subsamples(kept(scored_pairs(spark, sf_dir, "w4")), 3, K, SEED, "reseed", "proportional", "md5").select("subsample", "pair_id", "d")


@register("sample_pool", f"WITH {scored_sql('w4')}, {keyed_sql(SEED, '0')} SELECT pair_id FROM ky ORDER BY hash_key LIMIT {K}")
def sample_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampler.pool(kept(candidate_pairs(spark, sf_dir, "w4").select("pair_id")), K, SEED, "md5").select("pair_id")


@register("sample_xxhash")
def sample_xxhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown(sampler.sample(kept(scored_pairs(spark, sf_dir, "w4")), K, SEED, "equal"))


# --- Rules, bootstrap, fusion --------------------------------------------------------------------------------------

_RANK_KEYS = ("l_orderkey", "l_partkey", "l_suppkey")


def _rank_table(spark: SparkSession, sf_dir: str, rule: str, form: str = "standard") -> DataFrame:
    """Ranks for every number of lines that an order, a part or a supplier has, as numbers of positives."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    sizes = reduce(DataFrame.unionAll, [lines.groupBy(k).agg(F.count("*").alias("n")).select("n") for k in _RANK_KEYS]).distinct()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [(n, t, r) for n in b.column(0).to_pylist() for t in TARGETS if (r := rules.rank(rule, n, t, form=form)) is not None]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in found], kind) for k, kind in enumerate((pa.int64(), pa.int32(), pa.int64()))], names=["n", "target_mille", "rank"])

    return sizes.mapInArrow(run, "n long, target_mille int, rank long")


_RANK_SIZES = " UNION ".join(f"SELECT count(*) AS n FROM lineitem GROUP BY {k}" for k in _RANK_KEYS)
for _rule in (*RULES, "wilson_printed"):
    register(f"rank_{_rule}", f"WITH ns AS ({_RANK_SIZES}), {ranks_sql('ns', names=(_rule,))} SELECT CAST(n AS BIGINT) AS n, CAST(target_mille AS INTEGER) AS target_mille, CAST(r AS BIGINT) AS rank FROM rk")(
        lambda spark, sf_dir, r=_rule: _rank_table(spark, sf_dir, r.removesuffix("_printed"), "printed" if r.endswith("printed") else "standard")
    )

_POSITIVES = "ps AS (SELECT *, row_number() OVER (ORDER BY p DESC, pair_id) AS place FROM ch WHERE y), ns AS (SELECT count(*) AS n FROM ps)"


@register("tau_rules_w4", f"WITH {scored_sql('w4')}, {keyed_sql(SEED)}, {proportional_sql(K)}, {chosen_sql()}, {_POSITIVES}, {ranks_sql('ns')} SELECT rule, CAST(target_mille AS INTEGER) AS target_mille, CAST(r AS BIGINT) AS rank, round(p, 6) AS tau FROM rk JOIN ps ON place = r")
def tau_rules_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = positives_of(md5_sample(spark, sf_dir, "proportional"))["p"]
    found = [(r, t, k, round(float(p[k - 1]), 6)) for r in RULES for t in TARGETS if (k := rules.rank(r, len(p), t)) is not None]
    return spark.createDataFrame(found, "rule string, target_mille int, rank long, tau double")


@register(
    "tau_rules_weighted_w4",
    f"""WITH {scored_sql("w4")}, {keyed_sql(SEED)}, {_SIZES}, q0 AS (SELECT *, least({K}, n) AS k, count(*) OVER () AS h, row_number() OVER (ORDER BY d) AS pos FROM nh),
q AS (SELECT d, n_h, least(n_h, k // h + CASE WHEN pos <= k % h THEN 1 ELSE 0 END) AS quota_h FROM q0), {chosen_sql()},
cw AS (SELECT p, sum(n_h / quota_h::DOUBLE) OVER (ORDER BY p DESC) / sum(n_h / quota_h::DOUBLE) OVER () AS share FROM ch WHERE y)
SELECT CAST(t.v AS INTEGER) AS target_mille, round(max(p), 6) AS tau FROM cw, (VALUES (700), (800), (900)) t(v) WHERE share > t.v / 1000.0::DOUBLE GROUP BY t.v""",
)
def tau_rules_weighted_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = positives_of(md5_sample(spark, sf_dir, "equal"))
    return spark.createDataFrame([(t, round(bootstrap.thresholds(g["p"], g["w"], ("quantile",), t, 0.1)["quantile"], 6)) for t in TARGETS], "target_mille int, tau double")


_BOOT_SQL = f"""{_SPLIT}, ps AS (SELECT *, row_number() OVER (PARTITION BY subsample ORDER BY p DESC, pair_id) AS place FROM sp WHERE y),
ns AS (SELECT subsample, count(*) AS n FROM ps GROUP BY subsample), nd AS (SELECT DISTINCT n FROM ns), {ranks_sql("nd", (800,))},
dr AS (SELECT subsample, n, b.b, i.i, CAST('0x' || substr(md5(concat_ws('|', '7', CAST(subsample AS VARCHAR), CAST(b.b AS VARCHAR), CAST(i.i AS VARCHAR))), 1, 8) AS BIGINT) % n + 1 AS place
       FROM ns, (SELECT unnest(range(0, {BOOT})) AS b) b, LATERAL (SELECT unnest(range(0, n)) AS i) i),
od AS (SELECT *, row_number() OVER (PARTITION BY subsample, b ORDER BY place, i) AS r FROM dr),
rp AS (SELECT od.subsample, rk.rule, od.b AS replicate, ps.p AS tau FROM od JOIN rk ON rk.n = od.n AND rk.r = od.r JOIN ps ON ps.subsample = od.subsample AND ps.place = od.place),
mo AS (SELECT subsample, rule, avg(tau) AS mean_tau, var_samp(tau) AS var_tau FROM rp GROUP BY ALL),
we AS (SELECT *, (1 / greatest(var_tau, 1e-12)) / sum(1 / greatest(var_tau, 1e-12)) OVER (PARTITION BY subsample) AS weight FROM mo),
en AS (SELECT subsample, sum(weight * mean_tau) AS tau_ens FROM we GROUP BY subsample)"""


def hashed_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ensemble.moments(bootstrap.hashed_replicates(split_sample(spark, sf_dir).where("y"), 800, BOOT))


register("bootstrap_hashed_moments", f"WITH {_BOOT_SQL} SELECT subsample, rule, round(mean_tau, 6) AS mean_tau, round(var_tau, 8) AS var_tau FROM mo")(
    lambda spark, sf_dir: hashed_moments(spark, sf_dir).select("subsample", "rule", r6("mean_tau").alias("mean_tau"), F.round("var_tau", 8).alias("var_tau"))
)
register("ivw_weights", f"WITH {_BOOT_SQL} SELECT subsample, rule, round(weight, 6) AS weight FROM we")(lambda spark, sf_dir: ensemble.weights(hashed_moments(spark, sf_dir)).select("subsample", "rule", r6("weight").alias("weight")))
register("tau_ivw_single", f"WITH {_BOOT_SQL} SELECT subsample, round(tau_ens, 6) AS tau_ens FROM en")(lambda spark, sf_dir: ensemble.ivw(hashed_moments(spark, sf_dir)).select("subsample", r6("tau_ens").alias("tau_ens")))
for _how, _sql in (("min", "min(tau_ens)"), ("median", "median(tau_ens)"), ("mean", "avg(tau_ens)")):
    register(f"tau_ivw_{_how}", f"WITH {_BOOT_SQL} SELECT round({_sql}, 6) AS tau FROM en")(lambda spark, sf_dir, how=_how: ensemble.fuse_taus(ensemble.ivw(hashed_moments(spark, sf_dir)), how).select(r6("tau").alias("tau")))


@register("t_interval", f"WITH {_BOOT_SQL}, m AS (SELECT min(tau_ens) AS f, count(*) AS n FROM en) SELECT round(f - 2.919985580353726 * sqrt(sum((tau_ens - f) * (tau_ens - f)) / (any_value(n) * (any_value(n) - 1))), 6) AS ci_low, round(f + 2.919985580353726 * sqrt(sum((tau_ens - f) * (tau_ens - f)) / (any_value(n) * (any_value(n) - 1))), 6) AS ci_high FROM en, m GROUP BY f")
def t_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    taus = [r.tau_ens for r in ensemble.ivw(hashed_moments(spark, sf_dir)).orderBy("subsample").collect()]  # one row per subsample
    lo, hi = ensemble.student_interval(taus, min(taus))
    return spark.createDataFrame([(round(lo, 6), round(hi, 6))], "ci_low double, ci_high double")


@register("bootstrap_numpy")
def bootstrap_numpy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bootstrap.replicates(split_sample(spark, sf_dir).where("y"), 800, 50)


@register("bootstrap_analytic")
def bootstrap_analytic(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = positives_of(split_sample(spark, sf_dir).where("subsample = 0"))["p"]
    return spark.createDataFrame([(r, m, v) for r, (m, v) in bootstrap.analytic(p, RULES, 800, 0.1).items()], "rule string, mean_tau double, var_tau double")


# --- Baselines -----------------------------------------------------------------------------------------------------

_POOL = f"{scored_sql('w4')}, {keyed_sql(SEED, '0')}, ch AS (SELECT * FROM ky ORDER BY hash_key LIMIT {K})"


def pool_positives(spark: SparkSession, sf_dir: str) -> np.ndarray:
    return positives_of(sampler.pool(kept(scored_pairs(spark, sf_dir, "w4")), K, SEED, "md5").withColumn("w", F.lit(1.0)))["p"]


@register(
    "ht_lower_w4",
    f"""WITH {_POOL}, cu AS (SELECT p, row_number() OVER (ORDER BY p DESC, pair_id) AS k, count(*) OVER () AS n FROM ch WHERE y),
lb AS (SELECT p, k / n::DOUBLE - 1.2815515655446004::DOUBLE * sqrt((k * (1 - k / n::DOUBLE) ** 2 + (n - k) * (k / n::DOUBLE) ** 2) / (n * n)::DOUBLE) AS bound FROM cu)
SELECT CAST(t.v AS INTEGER) AS target_mille, round(max(p), 6) AS tau FROM lb, (VALUES (700), (800), (900)) t(v) WHERE bound >= t.v / 1000.0::DOUBLE - 1e-15 GROUP BY t.v""",
)
def ht_lower_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = pool_positives(spark, sf_dir)
    return spark.createDataFrame([(t, round(inverse_prob.threshold(p, np.ones(len(p)), t), 6)) for t in TARGETS], "target_mille int, tau double")


def _wilson(spark: SparkSession, p: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(t, round(float(p[rules.rank("wilson", len(p), t) - 1]), 6)) for t in TARGETS], "target_mille int, tau double")


_WILSON_OUT = f"{_POSITIVES}, {ranks_sql('ns', names=('wilson',))} SELECT CAST(target_mille AS INTEGER) AS target_mille, round(p, 6) AS tau FROM rk JOIN ps ON place = r"
register("wilson_random_w4", f"WITH {_POOL}, {_WILSON_OUT}")(lambda spark, sf_dir: _wilson(spark, pool_positives(spark, sf_dir)))
register("wilson_hash_w4", f"WITH {scored_sql('w4')}, {keyed_sql(SEED)}, {proportional_sql(K)}, {chosen_sql()}, {_WILSON_OUT}")(lambda spark, sf_dir: _wilson(spark, positives_of(md5_sample(spark, sf_dir, "proportional"))["p"]))

# --- Measures and review -------------------------------------------------------------------------------------------

register(
    "recall_curve_w4",
    f"""WITH {scored_sql("w4")}, h AS (SELECT CAST(least(99, floor(p * 100)) AS INTEGER) AS bin, count(*) AS n, count(*) FILTER (y) AS pos FROM sc GROUP BY 1)
SELECT bin, CAST(sum(n) OVER w AS BIGINT) AS reviewed, CAST(sum(pos) OVER w AS BIGINT) AS hits, round(sum(pos) OVER w / sum(pos) OVER ()::DOUBLE, 6) AS recall FROM h WINDOW w AS (ORDER BY bin DESC)""",
)(lambda spark, sf_dir: measures.recall_curve(scored_pairs(spark, sf_dir, "w4")).select("bin", "reviewed", "hits", r6("recall").alias("recall")))
_TAUS = (0.25, 0.5, 0.75)
_EVAL = " UNION ALL ".join(f"SELECT {t}::DOUBLE AS tau, count(*) AS candidates, count(*) FILTER (y) AS relevant, count(*) FILTER (p >= {t}) AS reviewed, count(*) FILTER (y AND p >= {t}) AS hits FROM sc" for t in _TAUS)


def _evaluated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.evaluated_many(scored_pairs(spark, sf_dir, "w4"), spark.createDataFrame([(t,) for t in _TAUS], "tau double"))


register("recall_at_tau", f"WITH {scored_sql('w4')}, e AS ({_EVAL}) SELECT tau, relevant, hits, round(hits / relevant::DOUBLE, 6) AS recall FROM e")(lambda spark, sf_dir: _evaluated(spark, sf_dir).select("tau", "relevant", "hits", r6("recall").alias("recall")))
register("review_cost", f"WITH {scored_sql('w4')}, e AS ({_EVAL}) SELECT tau, candidates, reviewed, round(reviewed / candidates::DOUBLE, 6) AS cost_fraction, 5.0 * reviewed + 0.01 * candidates AS money FROM e".replace("5.0 * reviewed + 0.01 * candidates", "round(5.0::DOUBLE * reviewed + 0.01::DOUBLE * candidates, 4)"))(
    lambda spark, sf_dir: _evaluated(spark, sf_dir).select("tau", "candidates", "reviewed", r6("cost_fraction").alias("cost_fraction"), F.round(5.0 * F.col("reviewed") + 0.01 * F.col("candidates"), 4).alias("money"))
)


@register("budget_cut", f"WITH {scored_sql('w4')}, {keyed_sql(SEED)} SELECT pair_id FROM ky WHERE p >= 0.5 ORDER BY p DESC, hash_key LIMIT 500")
def budget_cut(spark: SparkSession, sf_dir: str) -> DataFrame:
    keyed = kept(scored_pairs(spark, sf_dir, "w4").withColumn("hash_key", hashing.key(F.col("pair_id"), F.col("d"), SEED, "md5")))
    return verify.review(keyed, 0.5, 500, "split").select("pair_id")


@register("missed_matches", f"WITH {scored_sql('w4')} SELECT pair_id FROM sc WHERE y AND p < 0.8")
def missed_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = kept(scored_pairs(spark, sf_dir, "w4"))
    return verify.missed(x, verify.review(x, 0.8), F.col("y")).select("pair_id")


@register("variance_bound", f"WITH {scored_sql('w4')}, g AS (SELECT d, coalesce(stddev_samp(p), 0) AS sd, count(*) AS n FROM sc GROUP BY d) SELECT round(max(sd) ** 2 / ({K} / 10.0::DOUBLE) * 1e6, 6) AS bound_e6, round(sum((n / (SELECT count(*) FROM sc)::DOUBLE) ** 2 * sd ** 2 / ({K} / 10.0::DOUBLE)) * 1e6, 6) AS classical_e6 FROM g")
def variance_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = measures.score_profile(scored_pairs(spark, sf_dir, "w4")).orderBy("d").collect()  # one row per stratum
    total = sum(r.n for r in g)
    sd = [r.sd_p for r in g]
    return spark.createDataFrame([(round(measures.variance_bound(K, max(sd)) * 1e6, 6), round(measures.stratified_variance([r.n / total for r in g], sd, [K / 10] * len(g)) * 1e6, 6))], "bound_e6 double, classical_e6 double")


@register(
    "f_beta_best",
    f"""WITH {scored_sql("w4")}, {keyed_sql(SEED)}, {proportional_sql(K)}, {chosen_sql()},
b AS (SELECT p, sum(CASE WHEN y THEN n_h / quota_h::DOUBLE ELSE 0 END) AS a, sum(CASE WHEN y THEN 0 ELSE n_h / quota_h::DOUBLE END) AS f FROM ch GROUP BY p),
cu AS (SELECT p, sum(a) OVER (ORDER BY p DESC) AS tp, sum(f) OVER (ORDER BY p DESC) AS fp, sum(a) OVER () AS pos FROM b),
fb AS (SELECT p, round(5 * tp / (5 * tp + 4 * (pos - tp) + fp), 12) AS fbeta FROM cu)
SELECT round(p, 6) AS tau, round(fbeta, 6) AS f_beta FROM fb ORDER BY fbeta DESC, p DESC LIMIT 1""",
)
def f_beta_best(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objective.f_beta(md5_sample(spark, sf_dir, "proportional"), 2.0).select(r6("tau").alias("tau"), r6("f_beta").alias("f_beta"))


@register("ideal_threshold_w4", f"""WITH {scored_sql("w4")}, ps AS (SELECT p, row_number() OVER (ORDER BY p DESC) AS k, count(*) OVER () AS n FROM sc WHERE y),
ta AS (SELECT CAST(v AS INTEGER) AS target_mille, p AS tau FROM ps, (VALUES (700), (800), (900)) x(v) WHERE k = (n * v + 999) // 1000)
SELECT target_mille, round(tau, 6) AS tau, (SELECT count(*) FROM sc WHERE p >= tau) AS reviewed FROM ta""")
def ideal_threshold_w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = kept(scored_pairs(spark, sf_dir, "w4"))  # read several times per target
    found = [(t, measures.ideal_threshold(x, t)) for t in TARGETS]
    return spark.createDataFrame([(t, round(r["tau"], 6), r["reviewed"]) for t, r in found], "target_mille int, tau double, reviewed long")


register("rollup_stratum", f"WITH {scored_sql('w4')} SELECT coalesce(d, -1) AS d, coalesce(CAST(y AS VARCHAR), 'all') AS y, count(*) AS n FROM sc GROUP BY ROLLUP (sc.d, sc.y)")(
    lambda spark, sf_dir: scored_pairs(spark, sf_dir, "w4").rollup("d", "y").agg(F.count("*").alias("n")).select(F.coalesce("d", F.lit(-1)).alias("d"), F.coalesce(F.col("y").cast("string"), F.lit("all")).alias("y"), "n")
)


def _two(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored_pairs(spark, sf_dir, "w1").withColumn("workload", F.lit("w1")).unionByName(scored_pairs(spark, sf_dir, "w3").withColumn("workload", F.lit("w3")))


register(
    "cube_measures",
    f"SELECT workload, d, count(*) AS n, count(*) FILTER (y) AS pos FROM (SELECT 'w1' AS workload, * FROM (WITH {scored_sql('w1')} SELECT * FROM sc) UNION ALL SELECT 'w3', * FROM (WITH {scored_sql('w3')} SELECT * FROM sc)) GROUP BY CUBE (workload, d)",
)(lambda spark, sf_dir: _two(spark, sf_dir).cube("workload", "d").agg(F.count("*").alias("n"), F.count_if("y").alias("pos")))

# --- Other score tables --------------------------------------------------------------------------------------------


register(
    "embed_pairs_w5",
    """SELECT CAST(least(9, floor(p * 10)) AS INTEGER) AS d, count(*) AS n, count(*) FILTER (y) AS pos FROM (
SELECT least(1, greatest(0, (1 + list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) / (sqrt(list_dot_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[])) * sqrt(list_dot_product(b.embedding::DOUBLE[], b.embedding::DOUBLE[])))) / 2)) AS p, a.label = b.label AS y
FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id) GROUP BY 1""",
)(lambda spark, sf_dir: vector_pairs.score_histogram(spark.read.parquet(f"{sf_dir}/embeddings.parquet")))


def labelled_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with labels; score: how short they are, relevant: low quality."""
    d, q = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    return d.join(q, "doc_id").select(F.col("doc_id").cast("string").alias("pair_id"), (1.0 / (1.0 + F.col("n_chars") / 1000.0)).alias("p"), (F.col("quality") == 0).alias("y"))


register("doc_labels_w6", "SELECT CAST(doc_id AS VARCHAR) AS pair_id, round(1.0::DOUBLE / (1.0::DOUBLE + n_chars / 1000.0::DOUBLE), 6) AS p, quality = 0 AS y FROM documents JOIN labels USING (doc_id)")(
    lambda spark, sf_dir: labelled_documents(spark, sf_dir).select("pair_id", r6("p").alias("p"), "y")
)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    return e.select("event_id", "ts", "user_id", "event_type", "value", "props", F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("value") / 500.0)).alias("p"), (F.col("event_type") == "purchase").alias("y"))


register("event_windows", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, count(*) AS n, count(*) FILTER (event_type = 'purchase') AS pos, count(*) FILTER (value / 500.0 >= 0.5) AS above FROM events GROUP BY 1".replace("time_bucket(INTERVAL 1 HOUR, ts)", "strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S')"))(
    lambda spark, sf_dir: events(spark, sf_dir).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"), F.count_if("y").alias("pos"), F.count_if(F.col("p") >= 0.5).alias("above")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "pos", "above")
)
register(
    "event_session",
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL) GROUP BY ALL""",
)(lambda spark, sf_dir: events(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).groupBy("user_id", "n").agg(F.count("*").alias("sessions")))
register("json_filter", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events WHERE CAST(json_extract_string(props, '$.k') AS BIGINT) % 7 = 3")(
    lambda spark, sf_dir: events(spark, sf_dir).withColumn("k", F.get_json_object("props", "$.k").cast("long")).where("k % 7 = 3").select("event_id", "k")
)


@register(
    "asof_threshold",
    """WITH v AS (SELECT date_trunc('day', ts) AS since, avg(value / 500.0) AS tau FROM events GROUP BY 1), j AS (
SELECT e.event_id, e.value / 500.0 AS p, v.tau FROM events e ASOF JOIN v ON e.ts >= v.since) SELECT event_id, round(tau, 6) AS tau, p >= tau AS reviewed FROM j""",
)
def asof_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The threshold version in force at each event: versions joined in as rows, then the last one by time within a day bucket."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", (F.col("value") / 500.0).alias("p"))
    versions = e.groupBy(F.date_trunc("day", "ts").alias("since")).agg(F.avg("p").alias("tau"))
    return experiment.as_of(e, versions, "ts", "since", ["tau"]).select("event_id", r6("tau").alias("tau"), (F.col("p") >= F.col("tau")).alias("reviewed"))


def flagship(spark: SparkSession, sf_dir: str, w: str = "w4", params: Params | None = None) -> DataFrame:
    """All methods and targets on one workload: threshold, recall, cost, interval."""
    return experiment.run_methods(spark, scored_pairs(spark, sf_dir, w), w, params or PUBLISHED)


def queries() -> dict[str, Query]:
    from . import more_queries, oracle_queries  # noqa: F401  they register their queries

    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(ORACLE)
