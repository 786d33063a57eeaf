"""Trajectories: points (traj_id, seq, x, y) from the given tables, samples and a generator."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import noise


@dataclass(frozen=True)
class GridSpec:
    """A public bounding box cut into 2^res by 2^res cells. outside: what happens to points beyond it."""

    x0: float
    x1: float
    y0: float
    y1: float
    res: int
    outside: str = "clamp"

    @property
    def side(self) -> int:
        return 1 << self.res


SOURCES = ("li", "em", "ev", "evu", "or", "cv")


def box(spark: SparkSession, sf_dir: str, source: str, res: int) -> GridSpec:
    """The public box of a source; that of order lines reaches as far as the part table's keys."""
    if source == "li":
        most = spark.read.parquet(f"{sf_dir}/part.parquet").agg(F.max("p_partkey")).first()[0] or 0
        return GridSpec(0.0, float(most + 1), 0.0, 50.0, res)
    x0, x1, y0, y1 = {"em": (-2, 2, -2, 2), "ev": (0, 100, 0, 256), "evu": (0, 100, 0, 256), "or": (0, 2405, 0, 500000), "cv": (0, 16, 0, 16)}[source]
    return GridSpec(float(x0), float(x1), float(y0), float(y1), res)


def points(spark: SparkSession, sf_dir: str, source: str, n: int | None = None, seed: int = 7) -> DataFrame:
    """traj_id, seq, x, y of a source, or of a ``sample`` of n of its trajectories; seq numbers a trajectory's points from 0."""
    picked = lambda rows: sample(rows, n, seed) if n else rows  # noqa: E731  before the numbering, so that it sees no others
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    if source in ("ev", "evu"):
        day = F.datediff(F.col("ts"), F.lit("1970-01-01").cast("date"))
        traj = F.col("user_id") * 100000 + day if source == "ev" else F.col("user_id")
        rows = read("events").select(traj.cast("long").alias("traj_id"), "ts", "event_id", F.get_json_object("props", "$.k").cast("double").alias("x"), F.col("value").cast("double").alias("y"))
        return numbered(picked(rows), ["ts", "event_id"])
    if source == "em":
        pair = F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(31)), lambda i: F.struct(
            F.get("embedding", 2 * i).cast("double").alias("dx"), F.get("embedding", 2 * i + 1).cast("double").alias("dy"))))
        rows = read("embeddings").select(F.col("vec_id").cast("long").alias("traj_id"), pair.alias("seq", "d"))
        walk = Window.partitionBy("traj_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
        return picked(rows).select("traj_id", F.col("seq").cast("long").alias("seq"), F.sum("d.dx").over(walk).alias("x"), F.sum("d.dy").over(walk).alias("y"))
    if source == "li":
        rows = read("lineitem").select(
            F.col("l_orderkey").cast("long").alias("traj_id"), "l_linenumber", "l_partkey", "l_suppkey", "l_quantity",
            F.col("l_partkey").cast("double").alias("x"), (F.col("l_quantity") - 1).cast("double").alias("y"),
        )
        return numbered(picked(rows), ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity"])
    if source == "or":
        rows = read("orders").select(
            F.col("o_custkey").cast("long").alias("traj_id"), "o_orderdate", "o_orderkey",
            F.datediff(F.col("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("double").alias("x"), F.col("o_totalprice").cast("double").alias("y"),
        )
        return numbered(picked(rows), ["o_orderdate", "o_orderkey"])
    rows = read("conversations").select(
        F.col("conv_id").cast("long").alias("traj_id"), "turn", F.col("turn").cast("double").alias("x"),
        F.floor(F.log2(F.coalesce(F.length("text"), F.lit(0)) + 1)).cast("double").alias("y"),
    )
    return numbered(picked(rows), ["turn", "x", "y"])


def numbered(rows: DataFrame, order: list[str]) -> DataFrame:
    w = Window.partitionBy("traj_id").orderBy(*order)
    return rows.select("traj_id", (F.row_number().over(w) - 1).cast("long").alias("seq"), "x", "y")


def sample(rows: DataFrame, n: int, seed: int) -> DataFrame:
    """The points of ``n`` trajectories: those with the least portable uniform number."""
    ids = rows.select("traj_id").distinct().withColumn("u", noise.uniform(seed, "sample", "traj_id"))
    return rows.join(ids.orderBy("u", "traj_id").limit(n).select("traj_id"), "traj_id", "left_semi")


def generate(spark: SparkSession, n: int, length: int, skew: float, seed: int, parts: int | None = None) -> DataFrame:
    """``n`` random walks of ``length`` points in [0, 1)^2; with skew 0 they start anywhere, with more near the centre."""
    ids = spark.range(0, n, 1, parts) if parts else spark.range(n)
    return generate_for(ids.select(F.col("id").alias("traj_id")), length, skew, seed)


def generate_for(ids: DataFrame, length: int, skew: float, seed: int) -> DataFrame:
    """A walk of the generator for each traj_id."""
    rows = ids.select("traj_id", F.explode(F.sequence(F.lit(0), F.lit(length - 1))).alias("seq"))
    w = Window.partitionBy("traj_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    axes = {}
    for name, stream in (("x", "gx"), ("y", "gy")):
        start = 0.5 + (noise.uniform(seed, stream, "traj_id") - 0.5) * F.lit(1.0 / (1.0 + skew))
        move = F.when(F.col("seq") == 0, start).otherwise((noise.uniform(seed, stream, "traj_id", "seq") - 0.5) / 16)
        axes[name] = F.least(F.greatest(F.sum(move).over(w), F.lit(0.0)), F.lit(0.999999))
    return rows.select("traj_id", F.col("seq").cast("long").alias("seq"), axes["x"].alias("x"), axes["y"].alias("y"))
