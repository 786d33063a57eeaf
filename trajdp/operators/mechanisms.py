"""Laplace and exponential mechanisms, budgets and their ledger."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import noise


def laplace(answers: DataFrame, eps: float, sensitivity: float = 1.0, seed: int | None = None, stream: str = "lm", key: str = "qid", value: str = "ans") -> DataFrame:
    """The answers with independent Laplace noise of scale sensitivity / eps; without a seed from the operating system."""
    drawn = noise.draws(seed).drawn(answers, "_u", stream, key)
    return drawn.withColumn(value, F.col(value) + noise.laplace(F.col("_u"), sensitivity / eps)).drop("_u")


def exponential(scored: DataFrame, eps: float, sensitivity: float = 1.0, seed: int | None = None, stream: str = "em", key: str = "qid", score: str = "score") -> DataFrame:
    """One row, chosen with probability in proportion to exp(eps score / 2 sensitivity): the largest with Gumbel noise."""
    drawn = noise.draws(seed).drawn(scored, "_u", stream, key)
    noisy = F.col(score) * (eps / (2 * sensitivity)) + noise.gumbel(F.col("_u"))
    return drawn.withColumn("_noisy", noisy).orderBy(F.desc("_noisy"), key).limit(1).drop("_noisy", "_u")


def exponential_probs(scored: DataFrame, eps: float, sensitivity: float = 1.0, key: str = "qid", score: str = "score") -> DataFrame:
    """key, prob: the exact chances of each row. The largest score is taken off first, so no power overflows."""
    top = scored.agg(F.max(score).alias("top"))
    rows = scored.join(F.broadcast(top)).select(key, F.exp((F.col(score) - F.col("top")) * (eps / (2 * sensitivity))).alias("e"))
    return rows.join(F.broadcast(rows.agg(F.sum("e").alias("all")))).select(key, (F.col("e") / F.col("all")).alias("prob"))


PARTS = ("cost", "density", "choice", "answer")


def split_budget(eps: float, weights: tuple[float, float, float, float] = (0.25, 0.25, 0.25, 0.25)) -> tuple[float, ...]:
    """Shares of the four parts; the weights must sum to 1."""
    if len(weights) != 4 or any(w <= 0 for w in weights) or abs(sum(weights) - 1) > 1e-9:
        raise ValueError("four positive weights that sum to 1 are needed")
    return tuple(eps * w for w in weights)


def split_budgets(budgets: DataFrame, weights: tuple[float, float, float, float] = (0.25, 0.25, 0.25, 0.25), eps: str = "eps") -> DataFrame:
    """``budgets`` with four rows, part and eps, for each."""
    share = F.explode(F.array(*[F.struct(F.lit(k).alias("part"), F.lit(w).alias("w")) for k, w in zip(PARTS, split_budget(1.0, weights))]))
    return budgets.withColumn("_s", share).withColumns({"part": F.col("_s.part"), eps: F.col(eps) * F.col("_s.w")}).drop("_s")


@dataclass
class Ledger:
    """Budget spent so far. parallel: rows of one stage on disjoint data count once, the largest."""

    eps: float
    rows: list[tuple[str, int, float, float, float, str]] = field(default_factory=list)

    def spend(self, stage: str, eps: float, sensitivity: float, step: int = 0, composition: str = "sequential") -> float:
        """Records the amount and returns the scale of noise; refuses what is more than is left."""
        self.rows.append((stage, step, eps, sensitivity, sensitivity / eps, composition))
        if self.total() > self.eps * (1 + 1e-9):
            self.rows.pop()
            raise ValueError(f"{stage}: the budget of {self.eps} is spent")
        return sensitivity / eps

    def total(self) -> float:
        most: dict[str, float] = {}
        for stage, _, eps, _, _, composition in self.rows:
            most[stage] = max(most.get(stage, 0.0), eps) if composition == "parallel" else most.get(stage, 0.0) + eps
        return math.fsum(most.values())

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "stage string, step int, eps double, sensitivity double, scale double, composition string")


def ledger_totals(rows: DataFrame) -> DataFrame:
    """stage, eps: sums of sequential rows, largest of parallel ones."""
    return rows.groupBy("stage", "composition").agg(F.sum("eps").alias("s"), F.max("eps").alias("m")).groupBy("stage").agg(
        F.sum(F.when(F.col("composition") == "parallel", F.col("m")).otherwise(F.col("s"))).alias("eps"))


def neighbour(points: DataFrame, how: str, traj_id: int, other: int | None = None) -> DataFrame:
    """The points without a trajectory (remove), with a copy of it under a new id (add), or with it replaced by a copy of ``other`` (change)."""
    one = F.col("traj_id") == traj_id
    if how == "remove":
        return points.where(~one)
    if how == "add":
        return points.unionByName(points.where(one).withColumn("traj_id", F.lit(-1 - traj_id).cast("long")))
    return points.where(~one).unionByName(points.where(F.col("traj_id") == other).withColumn("traj_id", F.lit(traj_id).cast("long")))


def query_sensitivity(steps: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, most: the largest change of each histogram answer by taking away one trajectory (its own runs inside)."""
    from .answering import located

    w = Window.partitionBy("traj_id").orderBy("step")
    before = steps.withColumns({"r0": F.lag("row").over(w), "c0": F.lag("col").over(w), "s0": F.lag("step").over(w)})
    stays = (F.col("step") - F.col("s0") == 1) & F.col("r0").between(F.col("r1"), F.col("r2")) & F.col("c0").between(F.col("c1"), F.col("c2"))
    runs = located(before, queries).groupBy("qid", "traj_id").agg(F.sum(F.when(stays, 0).otherwise(1)).alias("n"))
    return queries.select("qid").join(runs.groupBy("qid").agg(F.max("n").alias("m")), "qid", "left").select("qid", F.coalesce("m", F.lit(0)).cast("long").alias("most"))


def cost_sensitivity(steps: DataFrame, side: int, weight: str = "inv_len") -> DataFrame:
    """weight, most, bound: the largest change of the whole grid's cost when one trajectory goes, and what bounds it.

    raw: each visited cell counts one; inv_len: one in all. Taking a trajectory away moves the mean by its
    mass alone, so the sum over all cells is needed once for each mass, and else only the trajectory's own cells.
    """
    cells = steps.select("traj_id", "row", "col").distinct()
    own = cells.join(cells.groupBy("traj_id").agg(F.count(F.lit(1)).alias("k")), "traj_id")
    own = own.select("traj_id", "row", "col", (F.lit(1.0) if weight == "raw" else 1.0 / F.col("k")).alias("w"), (F.col("k").cast("double") if weight == "raw" else F.lit(1.0)).alias("mass"))
    size = float(side * side)
    total = own.groupBy("row", "col").agg(F.sum("w").alias("cnt"))
    whole = total.agg((F.sum("cnt") / size).alias("mean"), F.count(F.lit(1)).alias("full"))
    masses = own.select("mass").distinct().unionByName(steps.sparkSession.range(1).select(F.lit(0.0).alias("mass"))).distinct()
    moved = masses.join(F.broadcast(whole)).withColumn("at", F.col("mean") - F.col("mass") / size)
    # as many masses as lengths of walks; empty cells lie at 0
    sums = total.join(F.broadcast(moved)).groupBy("mass").agg(
        (F.sum(F.abs(F.col("cnt") - F.col("at"))) + (size - F.first("full")) * F.abs(F.first("at"))).alias("all"), F.first("at").alias("at"))
    base = sums.where("mass = 0").select(F.col("all").alias("base"))
    change = own.join(total, ["row", "col"]).join(F.broadcast(sums), "mass").groupBy("traj_id").agg(
        (F.sum(F.abs(F.col("cnt") - F.col("w") - F.col("at")) - F.abs(F.col("cnt") - F.col("at"))) + F.first("all")).alias("after"), F.first("mass").alias("mass"))
    return change.join(F.broadcast(base)).agg(F.lit(weight).alias("weight"), F.max(F.abs(F.col("after") - F.col("base"))).alias("most"), (2 * F.max("mass")).alias("bound"))


def change_sensitivity(steps: DataFrame, side: int) -> DataFrame:
    """neighbours, most, bound: the largest change of the whole grid's cost, by shares, when a trajectory turns into the next one.

    Both have a mass of one, so the mean stays and only their own cells change.
    """
    cells = steps.select("traj_id", "row", "col").distinct()
    own = cells.join(cells.groupBy("traj_id").agg((1.0 / F.count(F.lit(1))).alias("w")), "traj_id")
    total = own.groupBy("row", "col").agg(F.sum("w").alias("cnt"))
    mean = total.agg((F.sum("cnt") / float(side * side)).alias("mean"))
    ids = own.select("traj_id").distinct()
    pairs = ids.withColumn("other", F.lead("traj_id").over(Window.orderBy("traj_id"))).where("other is not null")  # ids alone, in order
    change = pairs.join(own, "traj_id").select(F.col("traj_id").alias("pair"), "row", "col", (-F.col("w")).alias("d"))
    change = change.unionByName(pairs.join(own.withColumnRenamed("traj_id", "other"), "other").select(F.col("traj_id").alias("pair"), "row", "col", F.col("w").alias("d")))
    change = change.groupBy("pair", "row", "col").agg(F.sum("d").alias("d")).join(total, ["row", "col"]).join(F.broadcast(mean))
    moved = F.abs(F.col("cnt") + F.col("d") - F.col("mean")) - F.abs(F.col("cnt") - F.col("mean"))
    return change.groupBy("pair").agg(F.abs(F.sum(moved)).alias("by")).agg(F.lit("change").alias("neighbours"), F.max("by").alias("most"), F.lit(4.0).alias("bound"))


def audit(mechanism, first, second, runs: int, width: float) -> float:
    """The largest log ratio of how often a mechanism's outputs fall into buckets on two neighbouring inputs.

    mechanism(input, run) gives a number. Buckets met fewer than 30 times by both are left out.
    """
    from collections import Counter

    a = Counter(math.floor(mechanism(first, i) / width) for i in range(runs))
    b = Counter(math.floor(mechanism(second, i + runs) / width) for i in range(runs))
    common = [k for k in a | b if min(a[k], b[k]) >= 30]
    return max((abs(math.log(a[k] / b[k])) for k in common), default=0.0)
