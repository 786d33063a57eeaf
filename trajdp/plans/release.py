"""The whole mechanism: histogram, private regions and densities, private synthesis, ledger."""

from __future__ import annotations

from dataclasses import dataclass, replace

import pandas as pd
from pyspark.sql import DataFrame

from ..operators import histogram, mechanisms, quadtree, walks
from ..sources.trajectories import GridSpec
from ..storage import kept
from . import frames
from .dense import MOST, collected, framed, partitioned, query_array
from .estimator import SynthParams, run


@dataclass(frozen=True)
class ReleaseParams:
    """mean_length: public guess of cells in a trajectory, for the mass of the uniform start (None: 8). runs: how often a
    walk may come into a rectangle; walks are cut where they could come in once more, and all answers have that
    sensitivity (None: walks stay whole and 1 is charged, as printed, which holds only for walks that meet a rectangle
    once). backend: dense on the driver, frame, or by the number of components. seed: only for tests, as
    whoever knows it can take the noise off; without one it comes from the operating system."""

    eps: float = 0.1
    weights: tuple[float, float, float, float] = (0.25, 0.25, 0.25, 0.25)
    partition: quadtree.PartitionParams = quadtree.PartitionParams()
    synth: SynthParams = SynthParams()
    mean_length: float | None = None
    count: str = "range"
    how: str = "staircase"
    loops: str = "erase"
    runs: int | None = 4
    backend: str = "auto"
    seed: int | None = None


@dataclass
class Release:
    hist: DataFrame
    regions: pd.DataFrame
    trace: list[dict]
    ledger: mechanisms.Ledger

    def frame(self) -> DataFrame:
        """comp, row, col, cnt: all that may be given away."""
        return self.hist


def prepared(points: DataFrame, grid: GridSpec, p: ReleaseParams) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Steps of bounded walks, dense histogram, and the faces that costs are taken of: each trajectory adds one in all."""
    steps = walks.walk_steps(points, grid, p.how, p.loops)
    steps = kept(steps if p.runs is None else walks.bounded_runs(steps, p.runs))
    hist = kept(histogram.densify(histogram.build(steps, "visits"), grid.side))
    shares = kept(histogram.densify(histogram.build(steps, weight="inv_len"), grid.side).where("comp = 'F'").select("row", "col", "cnt"))
    return steps, hist, shares


def released(points: DataFrame, queries: DataFrame, grid: GridSpec, p: ReleaseParams = ReleaseParams(), prepared_: tuple | None = None) -> Release:
    """An eps-differentially private histogram of the points' trajectories.

    Frames do all work on points. A histogram of few enough components is then partitioned and improved over
    arrays on the driver, a larger one over frames; the grid, not the data, decides.
    """
    spark = points.sparkSession
    steps, hist, shares = prepared_ or prepared(points, grid, p)
    n = steps.select("traj_id").distinct().count()
    e1, e2, e3, e4 = mechanisms.split_budget(p.eps, p.weights)
    ledger, runs = mechanisms.Ledger(p.eps), float(p.runs or 1)
    ledger.spend("cost", e1, p.partition.sensitivity, composition="parallel")
    ledger.spend("density", e2, runs, composition="parallel")
    part = replace(p.partition, eps1=e1, eps2=e2, runs=runs, seed=p.seed)
    synth = replace(p.synth, eps3=e3, eps4=e4, runs=runs, seed=p.seed)
    for i in range(synth.rounds):
        ledger.spend("choice", e3 / synth.rounds, runs, i)
        ledger.spend("answer", e4 / synth.rounds, runs, i)
    mass = n * (8.0 if p.mean_length is None else p.mean_length)
    columns = ["pid", "level", "r1", "r2", "c1", "c2", "b"]
    dense = p.backend == "dense" or (p.backend == "auto" and 3 * grid.side**2 <= MOST)
    if dense:
        truth = collected(hist, grid.side)
        faces = collected(shares.selectExpr("'F' AS comp", "row", "col", "cnt"), grid.side).f
        regions = partitioned(truth, faces, n, part, p.count)[columns]
        qids, q = query_array(queries)
        got = run(truth, qids, q, regions, float(n), mass, synth)
        return Release(framed(spark, got.hist), regions, got.trace, ledger)
    found = quadtree.partition(hist, shares, n, grid.res, part, p.count).select(*columns)
    est, trace = frames.run(hist, queries, found, grid.side, float(n), mass, synth)
    return Release(est, found, trace, ledger)


def leak_free(frame: DataFrame) -> bool:
    """Whether no column of true values is left in a frame meant for release."""
    return not any(c.endswith("_true") or c in ("total", "ans_true") for c in frame.columns)
