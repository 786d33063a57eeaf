"""Experiments: every mechanism over prepared data sets, run by run in tasks of their own.

A case holds what all runs share: the true histogram (bounded by the grid) and
the query set. It is broadcast once; a frame of (mechanism, budget, rounds, run)
is dealt over the tasks, each row is one run, and frames sum up means, deviations
and the lowest mean over the numbers of rounds. Runs draw from a fast generator.
"""

from __future__ import annotations

import time
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import noise
from ..operators import mechanisms, quadtree, sums, walks, workload
from ..sources import trajectories
from ..storage import kept
from . import baselines
from .dense import MOST, DenseHist, collected, partitioned, query_array
from .estimator import SynthParams, cost_summary, run
from .release import ReleaseParams, prepared

MECHANISMS = ("BL-FLAT", "BL-MW1", "BL-BUCKET", "BL-GREEDY", "PM")
ITERATIVE = ("BL-MW1", "BL-GREEDY", "PM")
ONE_DIMENSION = ("BL-MW1", "BL-BUCKET")
#: Steps of one walk, at the most, that a task makes at once.
MOST_STEPS = 1 << 22
ROUNDS = (10, 12, 14, 16, 18, 20)
BUDGETS = (0.01, 0.05, 0.1, 0.5)
#: Public guesses: cells of a walk for each cell of the grid's side.
MEAN_SHARE = {"em": 0.5, "li": 2.0, "ev": 1.0, "evu": 8.0, "or": 4.0, "cv": 0.5, "gen": 1.0}
SCHEMA = "workload string, mechanism string, dataset string, n long, eps double, res int, q_size int, rounds int, run int, metric string, value double"
KEYS = ["workload", "mechanism", "dataset", "n", "eps", "res", "q_size", "rounds", "metric"]


@dataclass
class Case:
    """What the runs over one data set, grid and query set share."""

    source: str
    res: int
    truth: DenseHist
    shares: np.ndarray
    n: int
    longest: int
    mass: float
    qids: np.ndarray
    q: np.ndarray
    build_s: float = 0.0

    @cached_property
    def runs(self) -> baselines.Runs:
        """The query set along the curve, made once in each task's process."""
        return baselines.Runs(self.q, self.res)

    def regions(self, eps: float, draws, weights=(0.25,) * 4, threshold: str | float = "stddev") -> pd.DataFrame:
        e1, e2, _, _ = mechanisms.split_budget(eps, weights)
        return partitioned(self.truth, self.shares, self.n, quadtree.PartitionParams(eps1=e1, eps2=e2, threshold=threshold), source=draws)

    def proposed(self, eps: float, draws, rounds: int = 10, regions: pd.DataFrame | None = None, weights=(0.25,) * 4, threshold: str | float = "stddev", **options):
        _, _, e3, e4 = mechanisms.split_budget(eps, weights)
        regions = self.regions(eps, draws, weights, threshold) if regions is None else regions
        p = replace(SynthParams(rounds=rounds, eps3=e3, eps4=e4), **options)
        return run(self.truth, self.qids, self.q, regions, float(self.n), self.mass, p, source=draws)

    def estimate(self, mechanism: str, eps: float, draws, rounds: int = 10) -> tuple[np.ndarray, DenseHist]:
        """Answers and histogram of a mechanism; the one-dimensional ones have faces only."""
        if mechanism == "BL-FLAT":  # answers bear noise for all queries, the histogram for every cell of the longest walk
            answers = self.truth.answers(self.q) + noise.laplace_value(draws.uniforms("flat", self.qids), len(self.qids) / eps)
            parts = [x + noise.laplace_value(draws.uniforms(f"cells{i}", np.arange(x.size)), self.longest / eps).reshape(x.shape) for i, x in enumerate(self.truth.parts())]
            return answers, DenseHist(*parts)
        if mechanism in ONE_DIMENSION:
            vec, runs = self.truth.f[baselines.hilbert_order(self.res)], self.runs
            if mechanism == "BL-MW1":
                out = baselines.mw1d(vec, runs, float(self.n), self.mass, eps, rounds, qids=self.qids, source=draws)
            else:
                out = baselines.bucket_release(vec, eps, 0.5, runs, source=draws)
            est = DenseHist(baselines.rolled(out, self.res), np.zeros_like(self.truth.v), np.zeros_like(self.truth.h))
            return runs.answers(out), est
        if mechanism == "BL-GREEDY":
            got = baselines.greedy_consistent(self.truth, self.qids, self.q, float(self.n), self.mass, eps, rounds, source=draws).hist
        else:
            got = self.proposed(eps, draws, rounds).hist
        return got.answers(self.q), got

    def measures(self, mechanism: str, answers: np.ndarray, est: DenseHist) -> dict[str, float]:
        """Errors of the one-dimensional mechanisms are against sums of cell counts, all they know (avg_l1), and
        against the true answers, which count a walk once (avg_l1_sequence)."""
        sequence = self.truth.answers(self.q)
        true = self.truth.face_answers(self.q) if mechanism in ONE_DIMENSION else sequence
        err = np.abs(true - answers)
        f, g = self.truth.f, np.maximum(est.f, 1e-3)
        kld = float((f[f > 0] * np.log(f[f > 0] / g[f > 0])).sum() / self.n)
        return {
            "avg_l1": float(err.mean()), "avg_l1_sequence": float(np.abs(sequence - answers).mean()), "std": float(err.std()), "max": float(err.max()), "kld": kld,
            "violated": float(est.violated()), "negative": float((answers < -1e-9).sum()),
        }


def summed(points: DataFrame, grid: trajectories.GridSpec) -> tuple[DenseHist, np.ndarray, int, int] | None:
    """As ``prepared`` for walks that stay whole: the histogram, shares of faces, number of walks and most steps, from one pass over the points.

    None: a walk is too long for a task's arrays.
    """
    rows = sums.walk_sums(walks.assign(points, grid), grid.side, most=MOST_STEPS).toArrow().to_pandas()  # of the grid's size
    one = dict(rows[rows["part"].isin(["N", "K", "L"])][["part", "value"]].itertuples(index=False))
    if one.get("L", 0):
        return None
    truth, faces = DenseHist.zeros(grid.side), np.zeros((grid.side, grid.side))
    for part, x in zip("FVHS", (*truth.parts(), faces)):
        own = rows[rows["part"] == part]
        x[own["row"].to_numpy(int), own["col"].to_numpy(int)] = own["value"].to_numpy(float)
    return truth, faces, int(one.get("N", 0)), int(one.get("K", 0))


def case_of(points: DataFrame, source: str, grid: trajectories.GridSpec, m: int, seed: int = 7, queries: tuple[np.ndarray, np.ndarray] | None = None) -> Case:
    """Walks stay whole and answers have sensitivity 1, as printed. queries: the query set, if it is made."""
    if 3 * grid.side**2 > MOST:
        raise ValueError("experiments run on grids that fit the driver")
    t0 = time.perf_counter()
    if got := summed(points, grid):
        truth, faces, n, longest = got
    else:  # a walk too long for a task's arrays goes through frames
        steps, hist, shares = prepared(points, grid, ReleaseParams(runs=None))
        truth = collected(hist, grid.side)
        faces = collected(shares.selectExpr("'F' AS comp", "row", "col", "cnt"), grid.side).f
        got = steps.groupBy("traj_id").count().agg(F.count(F.lit(1)).alias("n"), F.max("count").alias("k")).first()
        n, longest = got["n"], got["k"] or 0
    build_s = time.perf_counter() - t0
    qids, q = queries or query_array(workload.random_rectangles(points.sparkSession, grid.side, m, seed))
    return Case(source, grid.res, truth, faces, n, longest, n * MEAN_SHARE[source] * grid.side, qids, q, build_s)


def prepared_case(spark: SparkSession, sf_dir: str, source: str, res: int, m: int, n: int | None = None, seed: int = 7) -> Case:
    """A case of a source's walks, or of ``n`` of them."""
    points = trajectories.points(spark, sf_dir, source, n, seed)
    return case_of(points, source, trajectories.box(spark, sf_dir, source, res), m, seed)


def settings(mechanisms_=MECHANISMS, epses=BUDGETS, rounds=ROUNDS, runs: int = 5) -> list[tuple[str, float, int, int]]:
    """mechanism, eps, rounds, run; the mechanisms without rounds have 0."""
    return [(m, float(e), t, r) for m in mechanisms_ for e in epses for t in (rounds if m in ITERATIVE else (0,)) for r in range(runs)]


def simulated(spark: SparkSession, case: Case, rows: list[tuple[str, float, int, int]], name: str) -> DataFrame:
    """One row for each run and measure."""
    shared = spark.sparkContext.broadcast(case)  # of the grid's and query set's size

    def simulate(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        case = shared.value
        for batch in batches:
            for mechanism, eps, rounds, number in batch.itertuples(index=False):
                t0 = time.perf_counter()
                draws = noise.Simulated(number, zlib.crc32(mechanism.encode()), round(eps * 1e6), rounds)
                values = case.measures(mechanism, *case.estimate(mechanism, eps, draws, rounds)) | {"seconds": time.perf_counter() - t0}
                yield pd.DataFrame([(name, mechanism, case.source, case.n, eps, case.res, len(case.q), rounds, number, k, v) for k, v in values.items()], columns=[c.split()[0] for c in SCHEMA.split(", ")])

    frame = spark.createDataFrame(rows, "mechanism string, eps double, rounds int, run int")
    # long runs are dealt out with short ones
    dealt = frame.repartition(max(1, min(len(rows), 4 * spark.sparkContext.defaultParallelism)), F.xxhash64("mechanism", "eps", "rounds", "run"))
    return dealt.mapInPandas(simulate, SCHEMA)


def lowest(rows: DataFrame) -> DataFrame:
    """Means and deviations over runs (metric_dev), of the number of rounds with the lowest mean error; run: how many runs.

    Choosing the rounds looks at true answers: a way to report, as published, and no private choice.
    """
    mean = rows.groupBy(*KEYS).agg(F.avg("value").alias("mean"), F.coalesce(F.stddev_samp("value"), F.lit(0.0)).alias("dev"), F.count(F.lit(1)).cast("int").alias("run"))
    own = Window.partitionBy("workload", "mechanism", "dataset", "n", "eps", "res", "q_size")
    error = F.min(F.when(F.col("metric") == "avg_l1", F.struct("mean", "rounds"))).over(own)
    best = mean.withColumn("best", error).where("rounds = best.rounds").drop("best")
    out = best.select(*KEYS, "run", F.explode(F.array(F.struct(F.lit("").alias("s"), F.col("mean").alias("value")), F.struct(F.lit("_dev").alias("s"), F.col("dev").alias("value")))).alias("x"))
    return out.withColumn("metric", F.concat("metric", "x.s")).select(*KEYS[:-1], "run", "metric", F.col("x.value").alias("value"))


def reported(parts: list[DataFrame], *metrics: str) -> DataFrame:
    every = parts[0]
    for x in parts[1:]:
        every = every.unionByName(x)
    return kept(lowest(every).where(F.col("metric").isin(*metrics, *[f"{m}_dev" for m in metrics])))


def distribution(spark, sf_dir: str, sources=("em", "li"), sizes=(250, 1000, None), epses=BUDGETS, res: int = 8, m: int = 16_000, runs: int = 5, rounds=ROUNDS, mechanisms_=MECHANISMS):
    """Errors by data set, size and budget."""
    cases = [prepared_case(spark, sf_dir, s, res, m, n) for s in sources for n in sizes]
    cases = list({(c.source, c.n): c for c in cases}.values())  # a sample may be the whole
    return reported([simulated(spark, c, settings(mechanisms_, epses, rounds, runs), "distribution") for c in cases], "avg_l1", "avg_l1_sequence")


def deviation(spark, sf_dir: str, epses=BUDGETS, n: int | None = 1000, res: int = 8, m: int = 16_000, runs: int = 5, rounds=ROUNDS):
    """Deviations of the error over queries and of its mean over runs."""
    case = prepared_case(spark, sf_dir, "em", res, m, n)
    return reported([simulated(spark, case, settings(epses=epses, rounds=rounds, runs=runs), "deviation")], "std", "avg_l1")


def query_set(spark, sf_dir: str, sizes=(1000, 2000, 4000, 8000, 16_000), eps: float = 0.1, res: int = 8, runs: int = 5, n: int | None = 1000, rounds=ROUNDS):
    whole = prepared_case(spark, sf_dir, "em", res, max(sizes), n)
    cases = [replace(whole, qids=whole.qids[:m], q=whole.q[:m]) for m in sizes]  # smaller sets are the first of the largest
    return reported([simulated(spark, c, settings(epses=(eps,), rounds=rounds, runs=runs), "query_set") for c in cases], "avg_l1")


def resolution(spark, sf_dir: str, levels=(4, 5, 6, 7, 8), eps: float = 0.1, m: int = 16_000, runs: int = 5, n: int | None = 1000, rounds=ROUNDS):
    cases = [prepared_case(spark, sf_dir, "em", res, m, n) for res in levels]
    return reported([simulated(spark, c, settings(epses=(eps,), rounds=rounds, runs=runs), "resolution") for c in cases], "avg_l1")


def utility(spark, sf_dir: str, epses=BUDGETS, res: int = 8, m: int = 16_000, runs: int = 5, n: int | None = 1000, rounds=ROUNDS):
    cases = [prepared_case(spark, sf_dir, s, res, m, n) for s in ("em", "li")]
    return reported([simulated(spark, c, settings(("PM", "BL-GREEDY", "BL-MW1"), epses, rounds, runs), "utility") for c in cases], "kld")


def best_ratio(spark, sf_dir: str, eps: float = 0.01, res: int = 8, m: int = 8000, runs: int = 5, n: int | None = 1000, rounds=ROUNDS):
    """Mean errors in the setting of the largest published ratio, and their ratios to the proposed mechanism's."""
    case = prepared_case(spark, sf_dir, "em", res, m, n)
    frame = reported([simulated(spark, case, settings(epses=(eps,), rounds=rounds, runs=runs), "best_ratio")], "avg_l1").where("metric = 'avg_l1'")
    base = frame.where("mechanism = 'PM'").select(F.col("value").alias("base"))
    ratio = frame.join(F.broadcast(base)).withColumn("value", F.col("value") / F.col("base")).withColumn("metric", F.lit("ratio")).drop("base")
    return frame.unionByName(ratio)


def variants(spark: SparkSession, case: Case, rows: list[tuple[str, float, int, int]], estimate, name: str) -> DataFrame:
    """As ``simulated`` for variants of the proposed mechanism: estimate(case, variant, eps, rounds, draws) gives a histogram."""
    shared = spark.sparkContext.broadcast(case)

    def simulate(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        case = shared.value
        for batch in batches:
            for variant, eps, rounds, number in batch.itertuples(index=False):
                est = estimate(case, variant, eps, rounds, noise.Simulated(number, round(eps * 1e6), rounds))
                values = case.measures("PM", est.answers(case.q), est)
                yield pd.DataFrame([(name, variant, case.source, case.n, eps, case.res, len(case.q), rounds, number, k, v) for k, v in values.items()], columns=[c.split()[0] for c in SCHEMA.split(", ")])

    frame = spark.createDataFrame(rows, "variant string, eps double, rounds int, run int")
    dealt = frame.repartition(max(1, min(len(rows), 4 * spark.sparkContext.defaultParallelism)), F.xxhash64("variant", "eps", "rounds", "run"))
    return dealt.mapInPandas(simulate, SCHEMA)


WEIGHTS = ((0.25, 0.25, 0.25, 0.25), (0.1, 0.1, 0.4, 0.4), (0.4, 0.1, 0.1, 0.4), (0.1, 0.4, 0.4, 0.1))


def budgets(spark, sf_dir: str, eps: float = 0.5, res: int = 8, m: int = 16_000, runs: int = 5, n: int | None = 1000, rounds=(10,)):
    """Errors under weightings of the four budgets."""
    case = prepared_case(spark, sf_dir, "em", res, m, n)
    names = {"PM " + "/".join(map(str, w)): w for w in WEIGHTS}
    rows = [(k, eps, t, r) for k in names for t in rounds for r in range(runs)]
    return reported([variants(spark, case, rows, lambda c, k, e, t, d: c.proposed(e, d, t, weights=names[k]).hist, "budgets")], "avg_l1")


def best_rounds(spark, sf_dir: str, eps: float = 0.1, res: int = 8, m: int = 16_000, runs: int = 5, n: int | None = 1000, choices=ROUNDS):
    """Mean errors for each number of rounds, and the lowest."""
    case = prepared_case(spark, sf_dir, "em", res, m, n)
    rows = simulated(spark, case, settings(("PM",), (eps,), choices, runs), "best_rounds").where("metric = 'avg_l1'")
    mean = kept(rows.groupBy(*KEYS).agg(F.avg("value").alias("value"), F.count(F.lit(1)).cast("int").alias("run"))).select(*[c.split()[0] for c in SCHEMA.split(", ")])
    return mean.unionByName(mean.orderBy("value").limit(1).withColumn("metric", F.lit("lowest_avg_l1")))


def ablated(case: Case, variant: str, eps: float, rounds: int, draws) -> DenseHist:
    regions, side = case.regions(eps, draws), case.truth.side
    if variant == "no queries":
        spread = DenseHist.zeros(side)
        for r1, r2, c1, c2, b in regions[["r1", "r2", "c1", "c2", "b"]].itertuples(index=False):
            spread.f[r1 : r2 + 1, c1 : c2 + 1] = b * case.n / ((r2 - r1 + 1) * (c2 - c1 + 1))
        return spread
    one = pd.DataFrame({"r1": [0], "r2": [side - 1], "c1": [0], "c2": [side - 1], "b": [1.0]})
    options = {
        "PM": {}, "no densities": {"regions": one}, "greedy repair": {"repair": "lower"}, "no repair": {"repair": "none"}, "classic update": {"update": "classic"},
        "mass kept": {"normalise": "mass"}, "answers kept": {"normalise": "answer"}, "largest density 1": {"density_scale": "max1"}, "densities by cell": {"density_scale": "per_cell"}, "exponents to 5": {"most_exponent": 5.0},
    }[variant]
    return case.proposed(eps, draws, rounds, **({"regions": regions} | options)).hist


def ablations(spark, sf_dir: str, epses=(0.1, 0.5), res: int = 8, m: int = 16_000, runs: int = 5, n: int | None = 1000, rounds=(10, 20)):
    case = prepared_case(spark, sf_dir, "em", res, m, n)
    names = ("PM", "no densities", "no queries", "greedy repair", "no repair", "classic update", "mass kept", "answers kept", "largest density 1", "densities by cell", "exponents to 5")
    rows = [(k, float(e), t, r) for k in names for e in epses for t in rounds for r in range(runs)]
    return reported([variants(spark, case, rows, ablated, "ablations")], "avg_l1", "violated")


def timing(spark, sf_dir: str, sources=("em", "li"), sizes=(1000, None), eps: float = 0.1, res: int = 8, m: int = 16_000, rounds: int = 10, generated: int | None = None):
    """Seconds of the histogram, of step 1 over frames and over arrays, of step 2, and its repairs. generated: walks of a generator besides."""
    rows, made = [], []
    for source in sources:
        grid = trajectories.box(spark, sf_dir, source, res)
        made += [(source, trajectories.points(spark, sf_dir, source, n), grid) for n in sizes]
    if generated:
        made.append(("gen", trajectories.generate(spark, generated, 20, 4.0, 7), trajectories.GridSpec(0, 1, 0, 1, res)))
    queries = query_array(workload.random_rectangles(spark, 1 << res, m))  # of all cases
    for source, points, grid in made:
        case = case_of(points, source, grid, m, queries=queries)
        draws = noise.Simulated(0)
        t0 = time.perf_counter()
        regions = case.regions(eps, draws)
        t1 = time.perf_counter()
        got = case.proposed(eps, draws, rounds, regions)
        t2 = time.perf_counter()
        repair_ms = sum(t["ms"] - t["scale_ms"] for t in got.trace)
        parts = {"build_s": case.build_s, "step1_s": t1 - t0, "step2_s": t2 - t1, "repair_s": repair_ms / 1000, "regions": float(len(regions))} | cost_summary(got.trace)
        rows += [("timing", "PM", source, case.n, eps, res, m, rounds, 1, k, float(v)) for k, v in parts.items()]
    return spark.createDataFrame(rows, SCHEMA)
