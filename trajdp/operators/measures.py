"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def errors(truth: DataFrame, est: DataFrame) -> DataFrame:
    """qid, err: absolute error of each answer."""
    return truth.join(est.withColumnRenamed("ans", "est"), "qid").select("qid", F.col("ans").alias("ans_true"), F.abs(F.col("ans") - F.col("est")).alias("err"))


def summary(truth: DataFrame, est: DataFrame, floor: float = 1.0) -> DataFrame:
    """metric, value: mean, largest, deviations of the error, and mean relative error above a floor."""
    e = errors(truth, est).agg(
        F.avg("err").alias("avg_l1"), F.max("err").alias("max"), F.stddev_pop("err").alias("std_pop"), F.stddev_samp("err").alias("std_samp"),
        F.avg(F.col("err") / F.greatest("ans_true", F.lit(floor))).alias("relative"))
    return e.unpivot([], ["avg_l1", "max", "std_pop", "std_samp", "relative"], "metric", "value")


def divergence(truth: DataFrame, est: DataFrame, n: float, comp: str = "F", floor: float = 1e-3, normalise: bool = False) -> DataFrame:
    """value: sum of c log(c / c') / n over the cells; estimates below the floor count as it; normalise: each side by its own sum."""
    a = truth.where(F.col("comp") == comp).select("row", "col", "cnt")
    b = est.where(F.col("comp") == comp).select("row", "col", F.greatest("cnt", F.lit(floor)).alias("guess"))
    rows = a.join(b, ["row", "col"], "left").withColumn("guess", F.coalesce("guess", F.lit(floor)))
    if normalise:
        sums = rows.agg(F.sum("cnt").alias("sc"), F.sum("guess").alias("sg"))
        rows = rows.join(F.broadcast(sums)).select((F.col("cnt") / F.col("sc")).alias("cnt"), (F.col("guess") / F.col("sg")).alias("guess"))
        n = 1.0
    return rows.agg((F.sum(F.when(F.col("cnt") > 0, F.col("cnt") * F.log(F.col("cnt") / F.col("guess"))).otherwise(0.0)) / n).alias("value"))


def improvement(table: DataFrame, own: str = "PM") -> DataFrame:
    """mechanism, ratio: each mechanism's value over that of ``own``, other columns alike."""
    keys = [c for c in table.columns if c not in ("mechanism", "value")]
    base = table.where(F.col("mechanism") == own).select(*keys, F.col("value").alias("base"))
    return table.where(F.col("mechanism") != own).join(base, keys).select(*keys, "mechanism", (F.col("value") / F.col("base")).alias("ratio"))


def held_out(truth: DataFrame, est: DataFrame, used: DataFrame) -> DataFrame:
    """value: mean error over the queries that were not used."""
    return errors(truth, est).join(used.select("qid"), "qid", "left_anti").agg(F.avg("err").alias("value"))


def inconsistency(hist: DataFrame, bad: DataFrame, answers: DataFrame) -> DataFrame:
    """metric, value: violated edges, their share and excess, negative answers."""
    edges = hist.where("comp <> 'F'").agg(F.count(F.lit(1)).alias("edges"))
    v = bad.agg(F.count(F.lit(1)).cast("double").alias("violated"), F.coalesce(F.sum("excess"), F.lit(0.0)).alias("excess"))
    a = answers.agg(F.sum((F.col("ans") < -1e-9).cast("int")).cast("double").alias("negative"))
    one = v.join(F.broadcast(edges)).join(F.broadcast(a)).withColumn("share", F.col("violated") / F.col("edges"))
    return one.select("violated", "share", "excess", "negative").unpivot([], ["violated", "share", "excess", "negative"], "metric", "value")


def signal_to_noise(regions: DataFrame, n: int, eps2: float) -> DataFrame:
    """pid, snr: a region's count over its noise scale."""
    return regions.select("pid", (F.col("b") * n * eps2).alias("snr"))
