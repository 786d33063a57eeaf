"""Private partitioning by a quadtree, all nodes of all levels at once.

Every node's total and cost come from two aggregations over cells times levels;
a node is a leaf if it is not split and all its ancestors are. Noise depends on
the node, so the result is that of descending from the root.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import noise
from ..storage import kept


@dataclass(frozen=True)
class PartitionParams:
    """scope leaf: each node's cost gets all of eps1, as only leaves are released; per_level: eps1 is shared by the
    levels, which holds under sequential composition. threshold variance: 4 / eps1^2; stddev: that of the compared
    noise; or a number. density_on count: noise on the count, then divided by n; ratio: noise on the ratio.
    parent_noise reuse: a node is compared as a parent with the noisy cost that it had as a child; fresh: with another
    draw. runs: the sensitivity of a region's count. seed: for tests; without one noise can't be repeated."""

    eps1: float = 0.025
    eps2: float = 0.025
    sensitivity: float = 2.0
    scope: str = "leaf"
    threshold: str | float = "variance"
    density_on: str = "count"
    clamp: bool = True
    noise: bool = True
    parent_noise: str = "reuse"
    runs: float = 1.0
    seed: int | None = None


NODE = ("level", "br", "bc")


def threshold(p: PartitionParams) -> float:
    if p.threshold == "variance":
        return 4 / p.eps1**2
    if p.threshold == "stddev":
        return math.sqrt(2.5) * p.sensitivity / p.eps1
    return float(p.threshold)


def by_level(faces: DataFrame, res: int) -> DataFrame:
    """Each cell once for each level, with its block there; level 0 is the whole grid."""
    rows = faces.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(res))))
    up = lambda c: F.call_function("shiftright", F.col(c), F.lit(res) - F.col("level"))
    return rows.withColumns({"br": up("row"), "bc": up("col")})


def nodes(faces: DataFrame, res: int) -> DataFrame:
    """level, br, bc, size, total, cost of all nodes; faces: all cells (row, col, cnt)."""
    rows = by_level(faces, res)
    totals = rows.groupBy(*NODE).agg(F.count(F.lit(1)).alias("size"), F.sum("cnt").alias("total"))
    costs = rows.join(totals, list(NODE)).groupBy(*NODE).agg(
        F.first("size").alias("size"), F.first("total").alias("total"), F.sum(F.abs(F.col("cnt") - F.col("total") / F.col("size"))).alias("cost"))
    return costs.select(*NODE, "size", "total", "cost")


def cost(faces: DataFrame, cell_region: DataFrame) -> DataFrame:
    """pid, cost: the summed deviation of each region's cells from their mean."""
    rows = faces.join(cell_region, ["row", "col"])
    means = rows.groupBy("pid").agg(F.avg("cnt").alias("mean"))
    return rows.join(means, "pid").groupBy("pid").agg(F.sum(F.abs(F.col("cnt") - F.col("mean"))).alias("cost"))


def uniform_regions(faces: DataFrame, cell_region: DataFrame) -> DataFrame:
    return cost(faces, cell_region).select("pid", (F.col("cost") <= 1e-9).alias("is_uniform"))


def noisy(table: DataFrame, p: PartitionParams, res: int) -> DataFrame:
    """The nodes with Laplace noise on their costs: noisy_cost as a child, parent_cost as a parent."""
    if not p.noise:
        return table.withColumns({"noisy_cost": F.col("cost"), "parent_cost": F.col("cost")})
    eps, source = p.eps1 / (res + 1) if p.scope == "per_level" else p.eps1, noise.draws(p.seed)
    scale = p.sensitivity / (eps if p.parent_noise == "reuse" else eps / 2)  # two draws of a cost share its budget
    out = source.drawn(table, "_u", "cost", *NODE).withColumn("noisy_cost", F.col("cost") + noise.laplace(F.col("_u"), scale)).drop("_u")
    if p.parent_noise == "reuse":
        return out.withColumn("parent_cost", F.col("noisy_cost"))
    return source.drawn(out, "_u", "parent", *NODE).withColumn("parent_cost", F.col("cost") + noise.laplace(F.col("_u"), scale)).drop("_u")


def split_flags(table: DataFrame, p: PartitionParams) -> DataFrame:
    """The nodes with ``split``: own noisy cost more than the threshold above the mean of the four children's."""
    children = table.where("level > 0").groupBy((F.col("level") - 1).alias("level"), F.shiftright("br", 1).alias("br"), F.shiftright("bc", 1).alias("bc")).agg(F.avg("noisy_cost").alias("child_cost"))
    both = table.join(children, list(NODE), "left")
    return both.withColumn("split", F.coalesce(F.col("parent_cost") - F.col("child_cost") > threshold(p), F.lit(False))).drop("child_cost")


def leaves(table: DataFrame, res: int) -> DataFrame:
    """pid, level, br, bc, r1, r2, c1, c2, size, total of the nodes that aren't split below ancestors that all are."""
    stop = table.where("not split").select(*[F.col(k).alias(f"a_{k}") for k in NODE])
    up = table.where("not split").withColumn("a_level", F.explode(F.expr("case when level > 0 then sequence(0, level - 1) end")))
    up = up.select(*NODE, "a_level", F.expr("shiftright(br, level - a_level)").alias("a_br"), F.expr("shiftright(bc, level - a_level)").alias("a_bc"))
    hidden = up.join(stop, ["a_level", "a_br", "a_bc"], "left_semi").select(*NODE).distinct()
    found = table.where("not split").join(hidden, list(NODE), "left_anti")
    width = F.expr(f"shiftleft(1, {res} - level)")
    pid = F.expr("cast((power(4, level) - 1) / 3 as bigint) + br * shiftleft(1L, level) + bc")
    return found.select(
        pid.alias("pid"), *NODE, (F.col("br") * width).alias("r1"), ((F.col("br") + 1) * width - 1).alias("r2"),
        (F.col("bc") * width).alias("c1"), ((F.col("bc") + 1) * width - 1).alias("c2"), "size", "total")


def cell_region(regions: DataFrame) -> DataFrame:
    """row, col, pid of every cell of rectangular regions."""
    rows = regions.select("pid", F.explode(F.sequence("r1", "r2")).alias("row"), "c1", "c2")
    return rows.select("row", F.explode(F.sequence("c1", "c2")).alias("col"), "pid")


def check_cover(regions: DataFrame, side: int) -> DataFrame:
    """row, col, times of cells that the regions don't cover exactly once."""
    cells = regions.sparkSession.range(side * side).select((F.col("id") / side).cast("int").alias("row"), (F.col("id") % side).cast("int").alias("col"))
    times = cell_region(regions).groupBy("row", "col").agg(F.count(F.lit(1)).alias("n"))
    return cells.join(times, ["row", "col"], "full").select("row", "col", F.coalesce("n", F.lit(0)).cast("long").alias("times")).where("times <> 1")


def density(regions: DataFrame, n: int, counted: DataFrame) -> DataFrame:
    """``regions`` with b: their count, from ``counted`` (pid, count), over the number of trajectories."""
    return regions.join(counted, "pid", "left").withColumn("b", F.coalesce("count", F.lit(0.0)) / F.lit(float(n))).drop("count")


def counted(hist: DataFrame, regions: DataFrame, how: str = "range") -> DataFrame:
    """pid, count. faces: cell counts summed, as for a histogram of shares; range: as a range query over the region.

    Cells meet their region by equality, and so do both cells of an edge: work grows with cells, not with cells times regions.
    """
    cells = cell_region(regions)
    rows = hist.where("comp = 'F'") if how == "faces" else hist
    rows = rows.withColumns({"r2": F.col("row") + (F.col("comp") == "H").cast("int"), "c2": F.col("col") + (F.col("comp") == "V").cast("int")})
    other = cells.select(F.col("row").alias("r2"), F.col("col").alias("c2"), F.col("pid").alias("other"))
    met = rows.join(cells, ["row", "col"]).join(other, ["r2", "c2"]).where("pid = other")
    found = met.groupBy("pid").agg(F.sum(F.when(F.col("comp") == "F", F.col("cnt")).otherwise(-F.col("cnt"))).alias("count"))
    return regions.select("pid").join(found, "pid", "left").select("pid", F.coalesce("count", F.lit(0.0)).alias("count"))


def noisy_density(regions: DataFrame, n: int, p: PartitionParams) -> DataFrame:
    """The regions with Laplace noise on b, not below 0 if ``clamp``."""
    if not p.noise:
        return regions
    scale = p.runs / p.eps2 / (n if p.density_on == "count" else 1)
    drawn = noise.draws(p.seed).drawn(regions, "_u", "density", "pid")
    b = F.col("b") + noise.laplace(F.col("_u"), scale)
    return drawn.withColumn("b", F.greatest(b, F.lit(0.0)) if p.clamp else b).drop("_u")


def partition(hist: DataFrame, cost_faces: DataFrame, n: int, res: int, p: PartitionParams, count: str = "range") -> DataFrame:
    """The leaves with noisy densities: pid, level, br, bc, r1, r2, c1, c2, size, total, b."""
    table = kept(noisy(nodes(cost_faces, res), p, res))  # read three times below; four thirds of the grid's size at most
    found = leaves(split_flags(table, p), res)
    return kept(noisy_density(density(found, n, counted(hist, found, count)), n, p))


def stats(found: DataFrame, res: int) -> DataFrame:
    """metric, value: leaves, height, largest and smallest leaf, cells times levels."""
    one = found.agg(F.count(F.lit(1)), F.max("level"), F.max("size"), F.min("size")).select(F.array(*[F.col(c).cast("double") for c in ("count(1)", "max(level)", "max(size)", "min(size)")]).alias("v"))
    names = ("leaves", "height", "largest", "smallest")
    rows = one.select(F.explode(F.array(*[F.struct(F.lit(k).alias("metric"), F.get("v", F.lit(i)).alias("value")) for i, k in enumerate(names)])).alias("m")).select("m.*")
    return rows.union(rows.sparkSession.createDataFrame([("work", float((res + 1) << (2 * res)))], "metric string, value double"))
