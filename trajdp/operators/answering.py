"""Answers of range queries: from walks, from histograms directly, and through prefix sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .histogram import densify
from .relational import range_binned


def inside(prefix: str = ""):
    return F.col("row").between(F.col("r1"), F.col("r2")) & F.col("col").between(F.col("c1"), F.col("c2"))


def small(queries: DataFrame, most: int = 200_000) -> DataFrame:
    """The queries, marked for broadcast if a count shows that they are few."""
    return F.broadcast(queries) if queries.count() <= most else queries


def every_query(queries: DataFrame, answers: DataFrame) -> DataFrame:
    return queries.select("qid").join(answers, "qid", "left").select("qid", F.coalesce("ans", F.lit(0)).cast("double").alias("ans"))


def located(steps: DataFrame, queries: DataFrame, most: int = 64) -> DataFrame:
    """Steps with the rectangles that hold them. A few rectangles are compared with every step; more meet the steps of
    the tiles they touch by equality."""
    if queries.count() <= most:
        return steps.join(F.broadcast(queries), inside())
    side = queries.agg(F.max(F.greatest("r2", "c2"))).first()[0] + 1
    return range_binned(steps, queries, max(1, side // 16))


def exact(steps: DataFrame, queries: DataFrame, approx: bool = False) -> DataFrame:
    """qid, ans: distinct trajectories that meet each rectangle."""
    met = located(steps.select("traj_id", "row", "col").distinct(), queries)
    if approx:
        return every_query(queries, met.groupBy("qid").agg(F.approx_count_distinct("traj_id").alias("ans")))
    once = met.groupBy("qid", "traj_id").agg(F.lit(1).alias("one"))  # summed up in each task before it is shuffled
    return every_query(queries, once.groupBy("qid").agg(F.sum("one").alias("ans")))


def segments(steps: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, ans: maximal runs of steps inside each rectangle: steps inside less crossings between two of them."""
    w = Window.partitionBy("traj_id").orderBy("step")
    before = steps.withColumns({"r0": F.lag("row").over(w), "c0": F.lag("col").over(w), "s0": F.lag("step").over(w)})
    met = located(before, queries)
    stays = (F.col("step") - F.col("s0") == 1) & F.col("r0").between(F.col("r1"), F.col("r2")) & F.col("c0").between(F.col("c1"), F.col("c2"))
    return every_query(queries, met.groupBy("qid").agg(F.sum(F.when(stays, 0).otherwise(1)).alias("ans")))


def in_component():
    """Whether a component lies strictly inside the rectangle: edges on its border don't."""
    last_row = F.col("r2") - (F.col("comp") == "H").cast("int")
    last_col = F.col("c2") - (F.col("comp") == "V").cast("int")
    return F.col("row").between(F.col("r1"), last_row) & F.col("col").between(F.col("c1"), last_col)


def from_hist(hist: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, ans: faces minus edges inside, summed over the components."""
    met = hist.join(small(queries), in_component())
    signed = F.when(F.col("comp") == "F", F.col("cnt")).otherwise(-F.col("cnt"))
    return every_query(queries, met.groupBy("qid").agg(F.sum(signed).alias("ans")))


def faces_only(hist: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, ans: cell counts alone, which count a trajectory once for each cell."""
    return from_hist(hist.where("comp = 'F'"), queries)


def prefix(hist: DataFrame, side: int) -> DataFrame:
    """comp, row, col, total: sums of each component up to a row and column. Two running sums over all components."""
    dense = densify(hist, side)
    along_row = Window.partitionBy("comp", "row").orderBy("col").rowsBetween(Window.unboundedPreceding, 0)
    along_col = Window.partitionBy("comp", "col").orderBy("row").rowsBetween(Window.unboundedPreceding, 0)
    rows = dense.withColumn("s", F.sum("cnt").over(along_row))
    return rows.select("comp", "row", "col", F.sum("s").over(along_col).alias("total"))


def from_prefix(table: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, ans: twelve look-ups in the prefix sums for each query, by equality."""
    corners = []
    for comp, sgn in (("F", 1), ("V", -1), ("H", -1)):
        r2 = F.col("r2") - (1 if comp == "H" else 0)
        c2 = F.col("c2") - (1 if comp == "V" else 0)
        valid = (r2 >= F.col("r1")) & (c2 >= F.col("c1"))
        for r, c, s in ((r2, c2, sgn), (F.col("r1") - 1, c2, -sgn), (r2, F.col("c1") - 1, -sgn), (F.col("r1") - 1, F.col("c1") - 1, sgn)):
            corners.append(F.when(valid, F.struct(F.lit(comp).alias("comp"), r.alias("row"), c.alias("col"), F.lit(s).alias("s"))))
    look = queries.select("qid", F.explode(F.array(*corners)).alias("k")).where("k is not null").select("qid", "k.*")
    got = look.join(table, ["comp", "row", "col"]).groupBy("qid").agg(F.sum(F.col("s") * F.col("total")).alias("ans"))
    return every_query(queries, got)


def plan(hist: DataFrame, queries: DataFrame, side: int) -> tuple[str, DataFrame]:
    """The cheaper way to all answers: direct while cells times queries are few, else prefix sums."""
    direct = side * side * queries.count() <= 50_000_000
    return ("direct", from_hist(hist, queries)) if direct else ("prefix", from_prefix(prefix(hist, side), queries))


def monotone_violations(hist: DataFrame, pairs: DataFrame) -> DataFrame:
    """qid, inner, outer of nested pairs (qid, r1.. of the inner, o_r1.. of the outer) whose inner answer is larger."""
    a = from_hist(hist, pairs.select("qid", "r1", "r2", "c1", "c2")).withColumnRenamed("ans", "inner")
    b = from_hist(hist, pairs.select("qid", F.col("o_r1").alias("r1"), F.col("o_r2").alias("r2"), F.col("o_c1").alias("c1"), F.col("o_c2").alias("c2"))).withColumnRenamed("ans", "outer")
    return a.join(b, "qid").where("inner > outer + 1e-9")
