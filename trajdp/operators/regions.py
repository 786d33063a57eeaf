"""Other ways to partition: best pruning, exhaustive, kd-tree, packed boxes, uniform blocks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..storage import kept
from .quadtree import NODE


def pruned_costs(table: DataFrame, res: int, charge: float) -> DataFrame:
    """level, br, bc, best, split of all nodes, from the leaves up: the least cost plus ``charge`` a region of a pruning below each."""
    table = kept(table.select(*NODE, F.col("cost")))
    below, done = None, []
    for level in range(res, -1, -1):
        here = table.where(F.col("level") == level)
        own = F.col("cost") + charge
        if below is None:
            here = here.select(*NODE, own.alias("best"), F.lit(False).alias("split"))
        else:
            here = here.join(below, list(NODE)).select(*NODE, F.least(own, F.col("below")).alias("best"), (F.col("below") < own - 1e-9).alias("split"))
        done.append(kept(here))  # each level stands alone: the next one's plan begins here
        below = done[-1].groupBy((F.col("level") - 1).alias("level"), F.shiftright("br", 1).alias("br"), F.shiftright("bc", 1).alias("bc")).agg(F.sum("best").alias("below"))
    every = done[0]
    for x in done[1:]:
        every = every.unionByName(x)
    return every


def best_pruning(table: DataFrame, res: int, charge: float) -> DataFrame:
    """level, br, bc, size, cost of the quadtree pruning with the least cost plus ``charge`` a region."""
    table = kept(table)
    stop = pruned_costs(table, res, charge).where("not split").select(*NODE)
    ends = stop.select(*[F.col(k).alias(f"a_{k}") for k in NODE])
    up = stop.withColumn("a_level", F.explode(F.expr("case when level > 0 then sequence(0, level - 1) end")))
    up = up.select(*NODE, "a_level", F.expr("shiftright(br, level - a_level)").alias("a_br"), F.expr("shiftright(bc, level - a_level)").alias("a_bc"))
    hidden = up.join(ends, ["a_level", "a_br", "a_bc"], "left_semi").select(*NODE).distinct()
    return stop.join(hidden, list(NODE), "left_anti").join(table, list(NODE)).select(*NODE, "size", "cost")


def exhaustive(cells: np.ndarray, charge: float) -> tuple[float, list[tuple[int, int, int, int]]]:
    """The cheapest tiling of a tiny grid by rectangles, each at its deviation plus ``charge``; tries all."""
    rows, cols = cells.shape
    full = (1 << (rows * cols)) - 1
    boxes = []
    for r1 in range(rows):
        for r2 in range(r1, rows):
            for c1 in range(cols):
                for c2 in range(c1, cols):
                    part = cells[r1 : r2 + 1, c1 : c2 + 1]
                    mask = sum(1 << (r * cols + c) for r in range(r1, r2 + 1) for c in range(c1, c2 + 1))
                    boxes.append((mask, float(np.abs(part - part.mean()).sum()) + charge, (r1, r2, c1, c2)))
    known: dict[int, tuple[float, list]] = {full: (0.0, [])}

    def solve(done: int) -> tuple[float, list]:
        if done not in known:
            first = (~done & full) & -(~done & full)
            known[done] = min(
                ((c + solve(done | m)[0], [b, *solve(done | m)[1]]) for m, c, b in boxes if m & first and not m & done), key=lambda x: x[0])
        return known[done]

    return solve(0)


def kdtree(faces: DataFrame, side: int, depth: int) -> DataFrame:
    """pid, r1, r2, c1, c2: each level cuts every region behind the cell line that reaches half of its count, rows and columns in turn."""
    regions = faces.sparkSession.createDataFrame([(0, 0, side - 1, 0, side - 1)], "pid long, r1 int, r2 int, c1 int, c2 int")
    for level in range(depth):
        axis, lo, hi = ("row", "r1", "r2") if level % 2 == 0 else ("col", "c1", "c2")
        inside = F.col("row").between(F.col("r1"), F.col("r2")) & F.col("col").between(F.col("c1"), F.col("c2"))
        lines = faces.join(F.broadcast(regions), inside).groupBy("pid", axis).agg(F.sum("cnt").alias("s"))
        w = Window.partitionBy("pid")
        run = lines.withColumn("run", F.sum("s").over(w.orderBy(axis).rowsBetween(Window.unboundedPreceding, 0))).withColumn("all", F.sum("s").over(w))
        cut = run.where("2 * run >= all").groupBy("pid").agg(F.min(axis).alias("cut"))
        at = regions.join(cut, "pid", "left").withColumn("cut", F.least(F.coalesce("cut", lo), F.col(hi) - 1))
        low = at.where(F.col(lo) < F.col(hi)).withColumn(hi, F.col("cut")).withColumn("pid", F.col("pid") * 2)
        high = at.where(F.col(lo) < F.col(hi)).withColumn(lo, F.col("cut") + 1).withColumn("pid", F.col("pid") * 2 + 1)
        whole = at.where(F.col(lo) >= F.col(hi)).withColumn("pid", F.col("pid") * 2)
        cut_up = low.unionByName(high).unionByName(whole).select("pid", "r1", "r2", "c1", "c2")
        regions = faces.sparkSession.createDataFrame(cut_up.collect(), cut_up.schema)  # 2^depth rows at most: cuts the plan
    return regions


def packed_boxes(faces: DataFrame, tiles: int) -> DataFrame:
    """pid, r1, r2, c1, c2, cells: boxes around non-empty cells, packed into columns and then along them; may overlap and leave gaps."""
    full = faces.where("cnt > 0").withColumn("a", F.ntile(tiles).over(Window.orderBy("col", "row")))
    full = full.withColumn("b", F.ntile(tiles).over(Window.partitionBy("a").orderBy("row", "col")))
    return full.groupBy(((F.col("a") - 1) * tiles + F.col("b") - 1).cast("long").alias("pid")).agg(
        F.min("row").alias("r1"), F.max("row").alias("r2"), F.min("col").alias("c1"), F.max("col").alias("c2"), F.count(F.lit(1)).alias("cells"))


def uniform(spark: SparkSession, res: int, level: int) -> DataFrame:
    """pid, r1, r2, c1, c2 of equal blocks."""
    k, w = 1 << level, 1 << (res - level)
    ids = spark.range(k * k).select(F.col("id").alias("pid"), (F.col("id") / k).cast("int").alias("br"), (F.col("id") % k).cast("int").alias("bc"))
    return ids.select("pid", (F.col("br") * w).alias("r1"), ((F.col("br") + 1) * w - 1).alias("r2"), (F.col("bc") * w).alias("c1"), ((F.col("bc") + 1) * w - 1).alias("c2"))
