"""Spatial histograms: faces F, edges V between side-by-side cells and H between cells one above the other."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sums import distinct_counts
from .walks import along, assign, collapse, fill, loops


def crossings(steps: DataFrame) -> DataFrame:
    """traj_id, step, comp, row, col of the border that each step crosses; hops without a common side cross none."""
    s = steps.withColumns({"_r": F.lead("row").over(along()), "_c": F.lead("col").over(along())})
    s = s.where(F.abs(F.col("_r") - F.col("row")) + F.abs(F.col("_c") - F.col("col")) == 1)
    return s.select(
        "traj_id", "step", F.when(F.col("row") == F.col("_r"), "V").otherwise("H").alias("comp"),
        F.least("row", "_r").alias("row"), F.least("col", "_c").alias("col"),
    )


def build(steps: DataFrame, mode: str = "visits", weight: str = "one") -> DataFrame:
    """comp, row, col, cnt. visits: every stay and crossing counts; distinct: once for each trajectory.

    weight inv_len: each trajectory adds one in all, an equal share to each of its distinct cells (faces only).
    """
    if weight == "inv_len":
        cells = steps.select("traj_id", "row", "col").distinct()
        share = cells.join(cells.groupBy("traj_id").agg(F.count(F.lit(1)).alias("k")), "traj_id")
        return share.groupBy(F.lit("F").alias("comp"), "row", "col").agg(F.sum(1.0 / F.col("k")).alias("cnt"))
    if mode == "distinct":  # a hash of walks and components would have nearly as many rows as the steps
        return distinct_counts(steps)
    parts = steps.select("traj_id", F.lit("F").alias("comp"), "row", "col").unionByName(crossings(steps).select("traj_id", "comp", "row", "col"))
    return parts.groupBy("comp", "row", "col").agg(F.count(F.lit(1)).cast("double").alias("cnt"))


def domain(spark, side: int) -> DataFrame:
    """comp, row, col of every component of a square grid."""
    cells = spark.range(side * side).select((F.col("id") / side).cast("int").alias("row"), (F.col("id") % side).cast("int").alias("col"))
    part = lambda k: cells.select(F.lit(k).alias("comp"), "row", "col")
    return part("F").unionByName(part("V").where(F.col("col") < side - 1)).unionByName(part("H").where(F.col("row") < side - 1))


def densify(hist: DataFrame, side: int) -> DataFrame:
    """All components, those without a count as zeros."""
    return domain(hist.sparkSession, side).join(hist, ["comp", "row", "col"], "left").select("comp", "row", "col", F.coalesce("cnt", F.lit(0.0)).alias("cnt"))


def cells(hist: DataFrame) -> DataFrame:
    """row, col, f, e_left, e_right, e_up, e_down: one row for each cell with any count on it."""
    at = lambda comp, name, dr, dc: hist.where(F.col("comp") == comp).select((F.col("row") + dr).alias("row"), (F.col("col") + dc).alias("col"), F.lit(name).alias("part"), "cnt")
    long = at("F", "f", 0, 0)
    for comp, name, dr, dc in (("V", "e_right", 0, 0), ("V", "e_left", 0, 1), ("H", "e_down", 0, 0), ("H", "e_up", 1, 0)):
        long = long.unionByName(at(comp, name, dr, dc))
    one = lambda name: F.coalesce(F.max(F.when(F.col("part") == name, F.col("cnt"))), F.lit(0.0)).alias(name)
    return long.groupBy("row", "col").agg(*[one(n) for n in ("f", "e_left", "e_right", "e_up", "e_down")])


def at_resolution(points: DataFrame, grid, coarser: int, how: str = "staircase", policy: str = "erase", mode: str = "visits") -> DataFrame:
    """The histogram on a grid ``coarser`` levels up. Faces can't be summed up, so walks are made anew from the shifted cells."""
    fine = assign(points, grid)
    up = fine.select("traj_id", "step", F.shiftright("row", coarser).alias("row"), F.shiftright("col", coarser).alias("col"))
    return build(loops(fill(collapse(up), how), policy), mode)


def violations(hist: DataFrame) -> DataFrame:
    """comp, row, col, cnt, low, excess of each edge above the smaller of its two faces."""
    faces = hist.where("comp = 'F'").select("row", "col", F.col("cnt").alias("face"))
    edges = hist.where("comp <> 'F'").withColumns({
        "r2": F.col("row") + (F.col("comp") == "H").cast("int"), "c2": F.col("col") + (F.col("comp") == "V").cast("int")})
    one = edges.join(faces.withColumnRenamed("face", "fa"), ["row", "col"], "left")
    two = one.join(faces.select(F.col("row").alias("r2"), F.col("col").alias("c2"), F.col("face").alias("fb")), ["r2", "c2"], "left")
    low = F.least(F.coalesce("fa", F.lit(0.0)), F.coalesce("fb", F.lit(0.0)))
    return two.withColumn("low", low).where(F.col("cnt") > F.col("low") + 1e-9).select("comp", "row", "col", "cnt", "low", (F.col("cnt") - F.col("low")).alias("excess"))
