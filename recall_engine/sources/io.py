"""Reading and writing tables with declared schemas, and well-known text for rings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

RING = T.ArrayType(T.StructType([T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType())]))


def load(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """``fmt`` is parquet, orc, json or csv; text formats need a schema, so nothing is inferred."""
    if fmt in ("json", "csv") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def save(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*by) if by else writer).save(path)


def save_scored(scored: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Scored pairs by stratum, sorted by score within files, so that ``p >= tau`` reads the top strata and row groups only."""
    scored.repartition("d", F.floor(F.col("p") * 1000)).sortWithinPartitions("d", F.desc("p")).write.mode(mode).partitionBy("d").parquet(path)


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int, mode: str = "errorifexists") -> None:
    """A managed table bucketed and sorted by ``key``: joins on it need no exchange."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def to_wkt(ring: Column) -> Column:
    """POLYGON text of a ring (array of x, y), closed."""
    points = F.transform(ring, lambda p: F.concat_ws(" ", p["x"].cast("string"), p["y"].cast("string")))
    return F.concat(F.lit("POLYGON(("), F.array_join(F.concat(points, F.slice(points, 1, 1)), ","), F.lit("))"))


def from_wkt(text: Column) -> Column:
    """The outer ring of POLYGON text, without the closing point."""
    body = F.regexp_extract(text, r"(?i)^\s*POLYGON\s*\(\s*\(([^)]*)\)", 1)
    points = F.split(F.trim(body), r"\s*,\s*")
    pairs = F.transform(points, lambda p: F.split(F.trim(p), r"\s+"))
    all_points = F.transform(pairs, lambda p: F.struct(p[0].cast("double").alias("x"), p[1].cast("double").alias("y")))
    return F.slice(all_points, F.lit(1), F.size(all_points) - 1)


def polygons(rows: DataFrame, ring: str = "ring") -> DataFrame:
    """Boxes of any rings: adds x0, x1, y0, y1."""
    r = F.col(ring)
    xs, ys = F.transform(r, lambda p: p["x"]), F.transform(r, lambda p: p["y"])
    return rows.withColumns({"x0": F.array_min(xs), "x1": F.array_max(xs), "y0": F.array_min(ys), "y1": F.array_max(ys)})
