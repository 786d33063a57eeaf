"""Query sets: random rectangles, their coverage and overlaps."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import noise


def random_rectangles(spark: SparkSession, side: int, m: int, seed: int = 7, method: str = "sorted") -> DataFrame:
    """qid, r1, r2, c1, c2 of ``m`` rectangles.

    sorted: two uniform cells for each axis. pairs: uniform over all intervals,
    so that short ones are as likely as their number.
    """
    return rectangles_of(spark.range(m).select(F.col("id").alias("qid")), side, seed, method)


def rectangles_of(ids: DataFrame, side: int, seed: int = 7, method: str = "sorted") -> DataFrame:
    """A random rectangle for each qid."""
    if method == "sorted":
        draw = lambda k: F.floor(noise.uniform(seed, k, "qid") * side).cast("int")
        ids = ids.withColumns({k: draw(k) for k in ("a", "b", "c", "d")})
        return ids.select("qid", F.least("a", "b").alias("r1"), F.greatest("a", "b").alias("r2"), F.least("c", "d").alias("c1"), F.greatest("c", "d").alias("c2"))
    total = side * (side + 1) // 2
    out = ids
    for k, lo, hi in (("pr", "r1", "r2"), ("pc", "c1", "c2")):
        # interval number j ends at the largest e with e (e + 1) / 2 <= j and starts at what is left
        out = out.withColumn("_j", F.floor(noise.uniform(seed, k, "qid") * total).cast("long"))
        out = out.withColumn(hi, F.floor((F.sqrt(8.0 * F.col("_j") + 1.0) - 1.0) / 2.0).cast("int"))
        out = out.withColumn(lo, (F.col("_j") - F.col(hi).cast("long") * (F.col(hi) + 1) / 2).cast("int"))
    return out.select("qid", "r1", "r2", "c1", "c2")


def coverage(queries: DataFrame, side: int) -> DataFrame:
    """row, col, hits: how many rectangles cover each cell, from four signed corners and two running sums."""
    corner = lambda r, c, s: F.struct(r.alias("row"), c.alias("col"), F.lit(s).alias("v"))
    r1, r2, c1, c2 = (F.col(k) for k in ("r1", "r2", "c1", "c2"))
    marks = queries.select(F.explode(F.array(corner(r1, c1, 1), corner(r1, c2 + 1, -1), corner(r2 + 1, c1, -1), corner(r2 + 1, c2 + 1, 1))).alias("m")).select("m.*")
    marks = marks.groupBy("row", "col").agg(F.sum("v").alias("v"))
    cells = queries.sparkSession.range(side * side).select((F.col("id") / side).cast("int").alias("row"), (F.col("id") % side).cast("int").alias("col"))
    rows = Window.partitionBy("row").orderBy("col").rowsBetween(Window.unboundedPreceding, 0)
    cols = Window.partitionBy("col").orderBy("row").rowsBetween(Window.unboundedPreceding, 0)
    s = cells.join(marks, ["row", "col"], "left").withColumn("s", F.sum(F.coalesce("v", F.lit(0))).over(rows))
    return s.select("row", "col", F.sum("s").over(cols).alias("hits"))


def overlaps(a: DataFrame, b: DataFrame) -> DataFrame:
    """qid, qid2, cells: pairs of a rectangle of ``a`` and a later one of ``b`` that share cells."""
    other = b.select(F.col("qid").alias("qid2"), *[F.col(k).alias(f"o_{k}") for k in ("r1", "r2", "c1", "c2")])
    high = F.least("r2", "o_r2") - F.greatest("r1", "o_r1") + 1
    wide = F.least("c2", "o_c2") - F.greatest("c1", "o_c1") + 1
    meet = (F.col("r1") <= F.col("o_r2")) & (F.col("o_r1") <= F.col("r2")) & (F.col("c1") <= F.col("o_c2")) & (F.col("o_c1") <= F.col("c2"))
    return a.join(other, (F.col("qid") < F.col("qid2")) & meet).select("qid", "qid2", (high * wide).cast("long").alias("cells"))
