"""Polygon layers derived from the given tables: one octagon per row on an integer plane.

An octagon is a box whose four corners are cut by the same length, so it is the intersection of four intervals, on x, y,
x + y and x - y, and every predicate on two of them is exact in integers.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BOX = ("x0", "x1", "y0", "y1")
OCTAGON = (*BOX, "c", "u0", "u1", "v0", "v1")


def _floor(value: str) -> str:
    return f"CAST(floor({value}) AS BIGINT)"


_PRICE, _BALANCE = _floor("o_totalprice"), _floor("abs(c_acctbal)")
_QUANTITY, _EXTENDED = _floor("l_quantity"), _floor("l_extendedprice")
_VALUE = _floor("round(value * 100)")
LINE_ID = "concat_ws('-', CAST(l_orderkey AS STRING), CAST(l_linenumber AS STRING), CAST(l_partkey AS STRING), CAST(l_suppkey AS STRING), CAST(CAST(floor(round(l_extendedprice * 100)) AS BIGINT) AS STRING))"


@dataclass(frozen=True)
class Layer:
    """A layer's table and SQL expressions: id, anchor, jitter and half sizes. ``div`` is integer division."""

    table: str
    id: str
    anchor: str
    jx: str
    jy: str
    hw: str
    hh: str


LAYERS = {
    "s_cust": Layer("customer", "c_custkey", "c_custkey", "c_nationkey % 37", "(3 * c_nationkey) % 41", f"20 + {_BALANCE} % 41", f"20 + ({_BALANCE} div 41) % 41"),
    "s_ord": Layer("orders", "o_orderkey", "o_orderkey", "o_custkey % 37", "o_custkey % 41", f"20 + {_PRICE} % 41", f"20 + ({_PRICE} div 41) % 41"),
    "t_w1": Layer("orders", "o_orderkey", "o_custkey", "(7 * o_orderkey) % 161 - 80", "(13 * o_orderkey) % 157 - 78", f"1 + {_PRICE} % 8", f"1 + ({_PRICE} div 8) % 8"),
    "t_w2": Layer("lineitem", LINE_ID, "l_orderkey", "(7 * l_partkey) % 161 - 80", "(13 * l_suppkey) % 161 - 80", f"14 + {_QUANTITY}", f"14 + {_EXTENDED} % 46"),
    "t_w3": Layer("events", "event_id", "event_id", "(7 * user_id) % 161 - 80", f"{_VALUE} % 161 - 80", f"3 + {_VALUE} % 17", f"3 + ({_VALUE} div 17) % 17"),
    "t_w4": Layer("lineitem", LINE_ID, "l_orderkey", "(7 * l_partkey) % 161 - 80", "(13 * l_suppkey) % 161 - 80", f"3 + {_QUANTITY} % 19", f"3 + {_EXTENDED} % 19"),
}
WORKLOADS = {"w1": ("s_cust", "t_w1"), "w2": ("s_cust", "t_w2"), "w3": ("s_ord", "t_w3"), "w4": ("s_ord", "t_w4")}


def corner_cut(prefix: str = "") -> Column:
    return F.expr(f"least({prefix}x1 - {prefix}x0, {prefix}y1 - {prefix}y0) div 4")


def diagonals(prefix: str = "") -> dict[str, Column]:
    """u0, u1, v0, v1 from the box and the corner cut."""
    x0, x1, y0, y1, c = (F.col(f"{prefix}{n}") for n in (*BOX, "c"))
    return {"u0": x0 + y0 + c, "u1": x1 + y1 - c, "v0": x0 - y1 + c, "v1": x1 - y0 - c}


def octagon(df: DataFrame) -> DataFrame:
    """Adds the corner cut and the diagonal bounds to boxes (x0, x1, y0, y1)."""
    return df.withColumn("c", corner_cut()).withColumns(diagonals())


def layer(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """id (string) and the octagon's integers; only the columns that they need are read."""
    spec = LAYERS[name]
    rows = spark.read.parquet(f"{sf_dir}/{spec.table}.parquet")
    at = rows.select(
        F.expr(f"CAST({spec.id} AS STRING)").alias("id"),
        F.expr(f"CAST(({spec.anchor} % 1000) * 100 + {spec.jx} AS BIGINT)").alias("x"),
        F.expr(f"CAST(({spec.anchor} div 1000) * 100 + {spec.jy} AS BIGINT)").alias("y"),
        F.expr(f"CAST({spec.hw} AS BIGINT)").alias("hw"),
        F.expr(f"CAST({spec.hh} AS BIGINT)").alias("hh"),
    )
    boxes = octagon(at.select("id", F.expr("x - hw").alias("x0"), F.expr("x + hw").alias("x1"), F.expr("y - hh").alias("y0"), F.expr("y + hh").alias("y1")))
    # As a generator's output the bounds are plain columns to the optimiser. Otherwise it derives null checks from every
    # comparison of two bounds and writes the whole arithmetic out in each, which costs far more than the join.
    return boxes.select(F.inline(F.array(F.struct("id", *OCTAGON))))


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    s, t = WORKLOADS[name]
    return layer(spark, sf_dir, s), layer(spark, sf_dir, t)


def ring(prefix: str = "") -> Column:
    """The octagon's eight corners as array of struct(x, y), counter-clockwise; corners coincide where nothing is cut."""
    x0, x1, y0, y1, c = (F.col(f"{prefix}{n}") for n in ("x0", "x1", "y0", "y1", "c"))
    corners = [(x0 + c, y0), (x1 - c, y0), (x1, y0 + c), (x1, y1 - c), (x1 - c, y1), (x0 + c, y1), (x0, y1 - c), (x0, y0 + c)]
    return F.array(*[F.struct(x.cast("double").alias("x"), y.cast("double").alias("y")) for x, y in corners])


def layer_sql(name: str) -> str:
    """The layer as a DuckDB subquery."""
    spec = LAYERS[name]
    text = f"""
SELECT id, x0, x1, y0, y1, c, x0 + y0 + c AS u0, x1 + y1 - c AS u1, x0 - y1 + c AS v0, x1 - y0 - c AS v1 FROM (
  SELECT id, x - hw AS x0, x + hw AS x1, y - hh AS y0, y + hh AS y1, least(2 * hw, 2 * hh) div 4 AS c FROM (
    SELECT CAST({spec.id} AS STRING) AS id, CAST(({spec.anchor} % 1000) * 100 + {spec.jx} AS BIGINT) AS x,
           CAST(({spec.anchor} div 1000) * 100 + {spec.jy} AS BIGINT) AS y, CAST({spec.hw} AS BIGINT) AS hw, CAST({spec.hh} AS BIGINT) AS hh
    FROM {spec.table}))"""
    return text.replace(" div ", " // ").replace("STRING", "VARCHAR")
