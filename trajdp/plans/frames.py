"""Private synthesis over frames: the rounds of plans.estimator for grids of any size, with its state written each round.

Queries are scored through prefix sums or direct sums, one row of the best
noisy score comes to the driver, cells take their region's factor by equality,
and one aggregate gives what normalising needs. Inconsistent components are
repaired in groups of their own.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import noise
from ..operators import answering, histogram, mechanisms, quadtree
from ..storage import kept
from . import repair
from .estimator import LARGEST, SynthParams, measured

MOST_REGIONS = 200_000  # of which factors are broadcast


def initial(spark: SparkSession, side: int, n: float, face_mass: float) -> DataFrame:
    """comp, row, col, cnt: uniform faces of the mass in all, uniform edges of face_mass - n."""
    edges = 2 * side * (side - 1)
    each = max(0.0, face_mass - n) / edges if edges else 0.0
    return histogram.domain(spark, side).withColumn("cnt", F.when(F.col("comp") == "F", face_mass / (side * side)).otherwise(each))


def owned(est: DataFrame, regions: DataFrame) -> DataFrame:
    """comp, row, col, pa, pb: the regions of a component's one or two cells."""
    cells = quadtree.cell_region(regions)
    rows = est.select("comp", "row", "col").withColumns({"r2": F.col("row") + (F.col("comp") == "H").cast("int"), "c2": F.col("col") + (F.col("comp") == "V").cast("int")})
    one = rows.join(cells.withColumnRenamed("pid", "pa"), ["row", "col"])
    return one.join(cells.select(F.col("row").alias("r2"), F.col("col").alias("c2"), F.col("pid").alias("pb")), ["r2", "c2"]).select("comp", "row", "col", "pa", "pb")


def scaled_regions(regions: DataFrame, how: str) -> DataFrame:
    """pid, r1, r2, c1, c2, b with scaled densities."""
    if how == "max1":
        top = regions.agg(F.max("b").alias("top"))
        regions = regions.join(F.broadcast(top)).withColumn("b", F.when(F.col("top") > 0, F.col("b") / F.col("top")).otherwise(F.col("b")))
    elif how == "per_cell":
        size = (F.col("r2") - F.col("r1") + 1) * (F.col("c2") - F.col("c1") + 1)
        total = regions.agg(F.sum(size).alias("total"))
        regions = regions.join(F.broadcast(total)).withColumn("b", F.col("b") * F.col("total") / size)
    return regions.select("pid", "r1", "r2", "c1", "c2", F.col("b").cast("double").alias("b"))


def power(x, p: SynthParams):
    most = LARGEST if p.most_exponent is None else p.most_exponent
    return F.exp(F.greatest(F.lit(-most), F.least(F.lit(most), x)))


def scores(true: DataFrame, guess: DataFrame) -> DataFrame:
    """qid, score, true, guess of each query."""
    both = true.withColumnRenamed("ans", "true").join(guess.withColumnRenamed("ans", "guess"), "qid")
    return both.withColumn("score", F.abs(F.col("true") - F.col("guess")))


def chosen(scored: DataFrame, i: int, p: SynthParams):
    """The row of the query that the round takes; without noise the largest score."""
    if not p.noise:
        return scored.orderBy(F.desc("score"), "qid").limit(1).first()
    return mechanisms.exponential(scored, p.eps3 / p.rounds, p.runs, p.seed, f"em{i}").first()


def updated(est: DataFrame, own: DataFrame, regions: DataFrame, q, error: float, n: float, p: SynthParams) -> DataFrame:
    """The histogram after the round's rescaling."""
    if p.update == "classic":
        f = float(np.exp(np.clip(error / (2 * n), -LARGEST if p.most_exponent is None else -p.most_exponent, LARGEST if p.most_exponent is None else p.most_exponent)))
        r2, c2 = F.lit(q["r2"]) - (F.col("comp") == "H").cast("int"), F.lit(q["c2"]) - (F.col("comp") == "V").cast("int")
        hit = F.col("row").between(F.lit(q["r1"]), r2) & F.col("col").between(F.lit(q["c1"]), c2)
        return est.withColumn("cnt", F.when(hit, F.col("cnt") * f).otherwise(F.col("cnt")))
    hit = (F.col("r1") <= q["r2"]) & (F.col("r2") >= q["r1"]) & (F.col("c1") <= q["c2"]) & (F.col("c2") >= q["c1"])
    factors = regions.where(hit).select("pid", power(F.lit(error) * F.col("b") / (2 * n), p).alias("f"))
    factors = F.broadcast(factors) if factors.count() <= MOST_REGIONS else factors
    met = est.join(own, ["comp", "row", "col"]).join(factors.select(F.col("pid").alias("pa"), F.col("f").alias("fa")), "pa", "left")
    met = met.join(factors.select(F.col("pid").alias("pb"), F.col("f").alias("fb")), "pb", "left")
    across = {"min": F.least("fa", "fb"), "mean": (F.col("fa") + F.col("fb")) / 2, "none": F.lit(1.0)}[p.cross_edge]
    factor = F.when(F.col("pa") == F.col("pb"), F.coalesce("fa", F.lit(1.0))).when(F.col("fa").isNotNull() & F.col("fb").isNotNull(), across).otherwise(1.0)
    return met.select("comp", "row", "col", (F.col("cnt") * factor).alias("cnt"))


def masses(est: DataFrame) -> tuple[float, float]:
    """Sums of faces and of edges."""
    face = F.col("comp") == "F"
    got = est.agg(F.sum(F.when(face, F.col("cnt"))).alias("f"), F.sum(F.when(~face, F.col("cnt"))).alias("e")).first()
    return float(got["f"] or 0.0), float(got["e"] or 0.0)


def normalised(new: DataFrame, before: tuple[float, float], how: str, n: float) -> tuple[DataFrame, tuple[float, float]]:
    """The scaled histogram and its sums; one aggregate over the cells."""
    f, e = masses(new)
    if how == "face":
        kf = ke = before[0] / f if f else 1.0
    elif how == "answer":
        kf = ke = n / (f - e) if f > e else 1.0
    elif how == "mass":
        kf, ke = before[0] / f if f else 1.0, before[1] / e if e else 1.0
    else:
        kf = ke = 1.0
    return new.withColumn("cnt", F.col("cnt") * F.when(F.col("comp") == "F", kf).otherwise(ke)), (f * kf, e * ke)


def run(truth: DataFrame, queries: DataFrame, regions: DataFrame, side: int, n: float, face_mass: float, p: SynthParams) -> tuple[DataFrame, list[dict]]:
    """The histogram after all rounds, and a trace. truth: comp, row, col, cnt; regions: pid, r1, r2, c1, c2, b, disjoint over the grid."""
    spark = truth.sparkSession
    est = kept(initial(spark, side, n, face_mass))
    sums, trace = (float(face_mass), max(0.0, face_mass - n)), []
    queries, regions = kept(queries), kept(scaled_regions(regions, p.density_scale))
    own = kept(owned(est, regions)) if p.update == "region" else None
    true = kept(answering.plan(truth, queries, side)[1])
    for i in range(p.rounds):
        how, guess = answering.plan(est, queries, side)
        q = chosen(scores(true, guess).join(queries, "qid"), i, p)
        error = measured(q["true"], q["guess"], q["qid"], p, i, noise.draws(p.seed))
        new = kept(updated(est, own, regions, q, error, n, p))
        est, sums = normalised(new, sums, p.normalise, n)
        row = {"iter": i, "qid": q["qid"], "werr": error, "answers": how, "violated": 0, "repaired_l1": 0.0, "components": 0, "certified": True}
        est = kept(est)
        if p.repair != "none" and (bad := histogram.violations(est).count()):
            row["violated"] = bad
            fixed, moves = repair.optimal_frame(est, side) if p.repair == "optimal" else (repair.greedy_frame(est, p.repair), None)
            est = kept(fixed)
            sums = masses(est)
            if moves is not None:
                got = moves.agg(F.sum(F.abs("change")).alias("l1"), F.sum("matched").alias("matched"), F.countDistinct("component").alias("k")).first()
                row |= {"repaired_l1": got["l1"], "components": got["k"], "certified": abs(got["l1"] - got["matched"]) <= 1e-6 * max(1.0, got["l1"])}
        trace.append(row)
    return est, trace
