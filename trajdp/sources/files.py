"""Points from files, tables for repeated use, and sinks of what is released."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

POINTS = "traj_id long, seq long, x double, y double"


def read_points(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = POINTS, **options) -> DataFrame:
    """Points from parquet, csv, json or orc files of a known schema; folders named key=value become columns."""
    if fmt not in ("parquet", "csv", "json", "orc"):
        raise ValueError(f"unknown format: {fmt}")
    reader = spark.read.options(**options)
    return reader.format(fmt).load(path) if fmt in ("parquet", "orc") else reader.schema(schema).format(fmt).load(path)


def from_polylines(rows: DataFrame, traj_id: str = "traj_id", polyline: str = "polyline") -> DataFrame:
    """Points of trajectories given as JSON texts [[x, y], ...]; null and malformed texts give none, nor do pairs of another length."""
    parsed = F.from_json(polyline, "array<array<double>>")
    out = rows.select(F.col(traj_id).cast("long").alias("traj_id"), F.posexplode(parsed).alias("seq", "p")).where("size(p) = 2")
    return out.select("traj_id", F.col("seq").cast("long").alias("seq"), F.get("p", F.lit(0)).alias("x"), F.get("p", F.lit(1)).alias("y"))


def bucketed(points: DataFrame, table: str, buckets: int) -> DataFrame:
    """The points as a table bucketed by trajectory: windows and joins over trajectories then need no shuffle."""
    points.write.mode("overwrite").bucketBy(buckets, "traj_id").sortBy("traj_id", "seq").saveAsTable(table)
    return points.sparkSession.table(table)


def write_release(hist: DataFrame, path: str) -> None:
    """A released histogram, one folder for each component; refuses frames with columns of true values."""
    extra = set(hist.columns) - {"comp", "row", "col", "cnt"}
    if extra:
        raise ValueError(f"not part of a release: {sorted(extra)}")
    hist.write.mode("overwrite").partitionBy("comp").parquet(path)


def append_metrics(rows: DataFrame, path: str) -> None:
    rows.write.mode("append").partitionBy("workload").parquet(path)
