"""The mechanisms that the proposed one is compared with.

BL-FLAT: independent Laplace noise. BL-MW1: multiplicative weights over faces in
one dimension. BL-BUCKET: private buckets over faces in one dimension, then a
hierarchy of bucket totals. BL-GREEDY: multiplicative weights over faces and
edges with greedy consistency. The one-dimensional ones follow published
descriptions of such mechanisms; the order of cells is a Hilbert curve's.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import noise
from ..functions.curves import hilbert_index
from ..operators.mechanisms import laplace
from .dense import DenseHist
from .estimator import SynthParams, Synthesis, powers, run


def flat_queries(answers: DataFrame, eps: float, m: int, seed: int | None = None) -> DataFrame:
    """The answers with noise scaled to the number of queries."""
    return laplace(answers, eps, m, seed, "flat")


def flat_cells(hist: DataFrame, eps: float, k: float, side: int, seed: int | None = None, scope: str = "sequential") -> DataFrame:
    """Every component with noise of scale k / eps (k: longest trajectory), or 1 / eps under scope parallel,
    which does not account for trajectories in several cells."""
    key = F.when(F.col("comp") == "F", 0).when(F.col("comp") == "V", 1).otherwise(2) * (side * side) + F.col("row") * side + F.col("col")
    scale = (1.0 if scope == "parallel" else k) / eps
    drawn = noise.draws(seed).drawn(hist.withColumn("_key", key.cast("long")), "_u", "cells", "_key")
    return drawn.withColumn("cnt", F.col("cnt") + noise.laplace(F.col("_u"), scale)).drop("_key", "_u")


def unrolled(hist: DataFrame, res: int) -> DataFrame:
    """pos, cnt: the faces along the Hilbert curve."""
    return hilbert_index(hist.where("comp = 'F'"), res).select("pos", "cnt")


def query_runs(queries: DataFrame, res: int) -> DataFrame:
    """qid, lo, hi: the stretches of the curve that each rectangle covers."""
    cells = queries.select("qid", F.explode(F.sequence("r1", "r2")).alias("row"), "c1", "c2").select("qid", "row", F.explode(F.sequence("c1", "c2")).alias("col"))
    w = Window.partitionBy("qid").orderBy("pos")
    run_ = hilbert_index(cells, res).withColumn("g", F.col("pos") - F.row_number().over(w))
    return run_.groupBy("qid", "g").agg(F.min("pos").alias("lo"), F.max("pos").alias("hi")).drop("g")


def hilbert_order(res: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of the cells in the curve's order, level by level: each level lays four turned copies of the one below."""
    r, c = np.zeros(1, np.int64), np.zeros(1, np.int64)
    for k in range(res):
        s = 1 << k
        r, c = np.concatenate([c, r + s, r + s, s - 1 - c]), np.concatenate([r, c, c + s, 2 * s - 1 - r])
    return r, c


class Runs:
    """Rectangles as stretches of the curve: queries over a vector by prefix sums, a few numbers for each cell of their borders."""

    def __init__(self, q: np.ndarray, res: int):
        """A stretch begins at a cell whose predecessor lies outside the rectangle, and so across one of its sides."""
        side = 1 << res
        r, c = hilbert_order(res)
        place = np.empty((side, side), np.int64)
        place[r, c] = np.arange(len(r))
        step = {(0, -1): 0, (0, 1): 1, (-1, 0): 2, (1, 0): 3}

        def ways(by: int) -> np.ndarray:
            """For each cell the side (left, right, above, below) on which the cell before (by -1) or behind lies; 4: none."""
            out = np.full((side, side), 4)
            i = np.arange(len(r))
            j = i + by
            ok = (j >= 0) & (j < len(r))
            move = np.stack([r[j[ok]] - r[i[ok]], c[j[ok]] - c[i[ok]]], axis=1)
            out[r[i[ok]], c[i[ok]]] = [step[x, y] for x, y in move.tolist()]
            return out

        def borders(way: np.ndarray, open_end: int) -> tuple[np.ndarray, np.ndarray]:
            """query, place of each border cell of the rectangles that the curve leaves or comes in by."""
            ids, at = [], []
            for k, (line, lo, hi, flip) in enumerate(((q[:, 2], q[:, 0], q[:, 1], True), (q[:, 3], q[:, 0], q[:, 1], True), (q[:, 0], q[:, 2], q[:, 3], False), (q[:, 1], q[:, 2], q[:, 3], False))):
                grid, where = (way.T, place.T) if flip else (way, place)
                count = hi - lo + 1
                who = np.repeat(np.arange(len(q)), count)
                along = np.arange(len(who)) - np.repeat(np.cumsum(count) - count, count) + lo[who]
                hit = grid[line[who], along] == k
                ids.append(who[hit])
                at.append(where[line[who][hit], along[hit]])
            end_r, end_c = r[open_end], c[open_end]
            holds = np.flatnonzero((q[:, 0] <= end_r) & (q[:, 1] >= end_r) & (q[:, 2] <= end_c) & (q[:, 3] >= end_c))
            ids, at = np.concatenate([*ids, holds]), np.concatenate([*at, np.full(len(holds), place[end_r, end_c])])
            order = np.lexsort((at, ids))
            return ids[order], at[order]

        self.ids, self.lo = borders(ways(-1), 0)
        _, self.hi = borders(ways(1), len(r) - 1)
        self.first = np.searchsorted(self.ids, np.arange(len(q) + 1))
        self.size = len(r)

    def __len__(self) -> int:
        return len(self.first) - 1

    def answers(self, vec: np.ndarray) -> np.ndarray:
        total = np.r_[0.0, np.cumsum(vec)]
        each = total[self.hi + 1] - total[self.lo]
        return np.add.reduceat(each, self.first[:-1])  # every rectangle has a stretch

    def mask(self, k: int) -> np.ndarray:
        part = slice(self.first[k], self.first[k + 1])
        edge = np.zeros(self.size + 1)
        np.add.at(edge, self.lo[part], 1)
        np.add.at(edge, self.hi[part] + 1, -1)
        return np.cumsum(edge[:-1]) > 0

    def coverage(self) -> np.ndarray:
        """How many rectangles hold each place."""
        edge = np.bincount(self.lo, minlength=self.size + 1) - np.bincount(self.hi + 1, minlength=self.size + 1)
        return np.cumsum(edge[:-1]).astype(float)


def mw1d(vec: np.ndarray, runs: Runs, n: float, mass: float, eps: float, rounds: int, seed: int | None = None, average: bool = False, replays: int = 0, qids: np.ndarray | None = None, most_exponent: float | None = None, source=None) -> np.ndarray:
    """Multiplicative weights over a vector: eps / 2 rounds each for choice and measurement."""
    qids, source = np.arange(len(runs)) if qids is None else qids, source or noise.draws(seed)
    est, true, total, done = np.full(len(vec), mass / len(vec)), runs.answers(vec), np.zeros(len(vec)), []
    each, p = eps / (2 * rounds), SynthParams(most_exponent=most_exponent)
    for i in range(rounds):
        score = np.abs(true - runs.answers(est)) * (each / 2) + noise.gumbel_value(source.uniforms(f"em{i}", qids))
        k = int(np.argmax(score))
        done.append((runs.mask(k), true[k] + float(noise.laplace_value(source.uniforms(f"lm{i}", qids[k : k + 1])[0], 1 / each))))
        for mask, measured in [done[-1]] + done[:-1] * replays:
            est = np.where(mask, est * powers((measured - est[mask].sum()) / (2 * n), p), est)
            est *= mass / est.sum()
        total += est
    return total / rounds if average else est


def bucket_costs(vec: np.ndarray, eps: float, charge: float, source, noisy: bool = True) -> list[np.ndarray]:
    """For each power of two, the noisy deviation and charge of each aligned interval of that length."""
    out = []
    for level in range(len(vec).bit_length()):
        parts = vec.reshape(-1, 1 << level)
        cost = np.abs(parts - parts.mean(axis=1, keepdims=True)).sum(axis=1)
        if noisy and level:
            keys = np.arange(len(cost)) + (level << 40)
            cost = cost + noise.laplace_value(source.uniforms("bucket", keys), 2.0 * (len(vec).bit_length()) / eps)
        out.append(np.maximum(cost, 0) + charge)
    return out


def bucketize(vec: np.ndarray, eps: float, charge: float | None = None, seed: int | None = None, noisy: bool = True, source=None) -> list[tuple[int, int]]:
    """Intervals (start, length) that tile the vector at least cost, by dynamic programming from the short ones up."""
    costs = bucket_costs(vec, eps, 1 / eps if charge is None else charge, source or noise.draws(seed), noisy)
    best, whole = [costs[0]], [np.ones(len(vec), bool)]
    for level in range(1, len(costs)):
        below = best[-1].reshape(-1, 2).sum(axis=1)
        whole.append(costs[level] <= below)
        best.append(np.minimum(costs[level], below))
    out, todo = [], [(len(costs) - 1, 0)]
    while todo:
        level, i = todo.pop()
        if whole[level][i]:
            out.append((i << level, 1 << level))
        else:
            todo += [(level - 1, 2 * i + 1), (level - 1, 2 * i)]
    return sorted(out)


def bucket_estimate(totals: np.ndarray, eps: float, weights: np.ndarray | None = None, seed: int | None = None, noisy: bool = True, source=None) -> np.ndarray:
    """Bucket totals from a binary hierarchy of noisy sums, made consistent by least squares.

    weights: how often the workload meets each bucket; levels get budget in
    proportion to the square root of their mean weight.
    """
    source = source or noise.draws(seed)
    size = 1 << max(0, (len(totals) - 1).bit_length())
    x = np.zeros(size)
    x[: len(totals)] = totals
    w = np.ones(size)
    if weights is not None:
        w[: len(totals)] = np.maximum(weights, 1e-9)
    sums, means = [x], [w.mean()]
    while len(sums[-1]) > 1:
        sums.append(sums[-1].reshape(-1, 2).sum(axis=1))
        means.append(w.reshape(len(sums[-1]), -1).max(axis=1).mean())
    share = np.sqrt(means) / np.sqrt(means).sum()
    var = [1 / (eps * s) ** 2 for s in share]
    seen = [s + (noise.laplace_value(source.uniforms("tree", np.arange(len(s)) + (k << 40)), 1 / (eps * share[k])) if noisy else 0.0) for k, s in enumerate(sums)]
    z, zvar = [seen[0]], [var[0]]
    for k in range(1, len(seen)):  # upwards: own measurement and the children's sum, by precision
        below, bvar = z[-1].reshape(-1, 2).sum(axis=1), 2 * zvar[-1]
        z.append((seen[k] / var[k] + below / bvar) / (1 / var[k] + 1 / bvar))
        zvar.append(1 / (1 / var[k] + 1 / bvar))
    out = z[-1]
    for k in range(len(z) - 2, -1, -1):  # downwards: what parents have more goes to both children
        miss = (out - z[k].reshape(-1, 2).sum(axis=1)) / 2
        out = z[k] + np.repeat(miss, 2)
    return out[: len(totals)]


def bucket_expand(buckets: list[tuple[int, int]], totals: np.ndarray) -> np.ndarray:
    return np.concatenate([np.full(n, t / n) for (_, n), t in zip(buckets, totals)])


def bucket_release(vec: np.ndarray, eps: float, ratio: float = 0.5, runs: Runs | None = None, seed: int | None = None, noisy: bool = True, source=None) -> np.ndarray:
    """Both stages: ``ratio`` of the budget for the buckets, the rest for their totals."""
    source = source or noise.draws(seed)
    buckets = bucketize(vec, eps * ratio, noisy=noisy, source=source)
    starts = np.array([s for s, _ in buckets])
    totals = np.add.reduceat(vec, starts)
    weights = None if runs is None else np.add.reduceat(runs.coverage(), starts) / np.array([n for _, n in buckets])
    return bucket_expand(buckets, bucket_estimate(totals, eps * (1 - ratio), weights, noisy=noisy, source=source))


def greedy_consistent(truth: DenseHist, qids: np.ndarray, q: np.ndarray, n: float, face_mass: float, eps: float, rounds: int, seed: int | None = None, how: str = "lower", source=None) -> Synthesis:
    p = SynthParams(rounds=rounds, eps3=eps / 2, eps4=eps / 2, update="classic", repair=how, seed=seed)
    return run(truth, qids, q, None, n, face_mass, p, source=source)


def rolled(vec: np.ndarray, res: int) -> np.ndarray:
    """The grid of a vector along the curve."""
    out = np.zeros((1 << res, 1 << res))
    out[hilbert_order(res)] = vec
    return out


def longest(steps: DataFrame) -> int:
    return int(steps.groupBy("traj_id").count().agg(F.max("count")).first()[0] or 0)


