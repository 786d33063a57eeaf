"""Private synthesis: a uniform histogram improved by the answers of privately chosen queries."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pandas as pd

from ..functions import noise
from . import repair
from .dense import DenseHist


@dataclass(frozen=True)
class SynthParams:
    """update region: every cell of a region that meets the query, by exp(error density / 2n); classic: the query's own
    cells by exp(error / 2n). cross_edge: the factor of an edge between two touched regions. normalise: what stays as it
    was. repair optimal | lower | raise | none. density_scale raw | max1 | per_cell. average: mean of the iterates.
    runs: the sensitivity of an answer, one unless walks come back into rectangles. most_exponent: a bound that the
    rule itself doesn't have. seed: for tests; without one noise can't be repeated."""

    rounds: int = 10
    eps3: float = 0.025
    eps4: float = 0.025
    update: str = "region"
    cross_edge: str = "min"
    normalise: str = "face"
    repair: str = "optimal"
    density_scale: str = "raw"
    most_exponent: float | None = None
    average: bool = False
    noise: bool = True
    runs: float = 1.0
    seed: int | None = None


@dataclass
class Synthesis:
    hist: DenseHist
    trace: list[dict] = field(default_factory=list)


def initial(side: int, n: float, face_mass: float) -> DenseHist:
    """Uniform faces of the mass in all; uniform edges of face_mass - n, so that the whole space answers n."""
    out = DenseHist.zeros(side)
    out.f += face_mass / out.f.size
    edges = out.v.size + out.h.size
    if edges:
        each = max(0.0, face_mass - n) / edges
        out.v += each
        out.h += each
    return out


def chosen(scores: np.ndarray, qids: np.ndarray, eps: float, p: SynthParams, i: int, source) -> int:
    """Exponential mechanism by Gumbel noise; without noise the largest score."""
    if not p.noise:
        return int(np.argmax(scores))
    return int(np.argmax(scores * (eps / (2 * p.runs)) + noise.gumbel_value(source.uniforms(f"em{i}", qids))))


def measured(true: float, guess: float, qid: int, p: SynthParams, i: int, source) -> float:
    """The noisy error of the chosen query."""
    if not p.noise:
        return float(true - guess)
    u = source.uniforms(f"lm{i}", np.array([qid]))[0]
    return float(true + noise.laplace_value(u, p.runs * p.rounds / p.eps4) - guess)


LARGEST = 500.0  # exponents beyond it leave the range of floats


def powers(x, p: SynthParams):
    most = LARGEST if p.most_exponent is None else p.most_exponent
    return np.exp(np.clip(x, -most, most))


def factors(side: int, q: np.ndarray, error: float, n: float, p: SynthParams, region: np.ndarray | None, b: np.ndarray | None, rect: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Factors of faces, V and H edges."""
    r1, r2, c1, c2 = q
    if p.update == "classic":
        f = powers(error / (2 * n), p)
        out = [np.ones((side, side)), np.ones((side, side - 1)), np.ones((side - 1, side))]
        out[0][r1 : r2 + 1, c1 : c2 + 1] = f
        out[1][r1 : r2 + 1, c1:c2] = f
        out[2][r1:r2, c1 : c2 + 1] = f
        return tuple(out)
    meets = (rect[:, 0] <= r2) & (rect[:, 1] >= r1) & (rect[:, 2] <= c2) & (rect[:, 3] >= c1)
    each = np.where(meets, powers(error * b / (2 * n), p), 1.0)
    cell, touched = each[region], meets[region]

    def between(a: np.ndarray, c: np.ndarray, ra: np.ndarray, rc: np.ndarray, ta: np.ndarray, tc: np.ndarray) -> np.ndarray:
        across = {"min": np.minimum(a, c), "mean": (a + c) / 2, "none": np.ones_like(a)}[p.cross_edge]
        return np.where(ra == rc, a, np.where(ta & tc, across, 1.0))

    v = between(cell[:, :-1], cell[:, 1:], region[:, :-1], region[:, 1:], touched[:, :-1], touched[:, 1:])
    h = between(cell[:-1], cell[1:], region[:-1], region[1:], touched[:-1], touched[1:])
    return cell, v, h


def normalised(new: DenseHist, old: DenseHist, how: str, n: float) -> DenseHist:
    f, e = new.f.sum(), new.v.sum() + new.h.sum()
    if how == "face":
        kf = ke = old.f.sum() / f if f else 1.0
    elif how == "answer":
        kf = ke = n / (f - e) if f > e else 1.0
    elif how == "mass":
        kf, ke = old.f.sum() / f if f else 1.0, (old.v.sum() + old.h.sum()) / e if e else 1.0
    else:
        kf = ke = 1.0
    return DenseHist(new.f * kf, new.v * ke, new.h * ke)


def scaled_densities(b: np.ndarray, sizes: np.ndarray, how: str) -> np.ndarray:
    if how == "max1":
        return b / b.max() if len(b) and b.max() > 0 else b
    return b * sizes.sum() / sizes if how == "per_cell" else b


def laid_out(regions: pd.DataFrame | None, side: int, how: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rectangles, the region of each cell, and scaled densities; None: one region of density 1."""
    if regions is None or not len(regions):
        regions = pd.DataFrame({"r1": [0], "r2": [side - 1], "c1": [0], "c2": [side - 1], "b": [1.0]})
    rect = regions[["r1", "r2", "c1", "c2"]].to_numpy(np.int64)
    region = np.zeros((side, side), np.int64)
    for k, (r1, r2, c1, c2) in enumerate(rect):
        region[r1 : r2 + 1, c1 : c2 + 1] = k
    sizes = (rect[:, 1] - rect[:, 0] + 1) * (rect[:, 3] - rect[:, 2] + 1)
    return rect, region, scaled_densities(regions["b"].to_numpy(float), sizes, how)


def run(truth: DenseHist, qids: np.ndarray, q: np.ndarray, regions: pd.DataFrame | None, n: float, face_mass: float, p: SynthParams, answers: np.ndarray | None = None, source=None) -> Synthesis:
    """T rounds: choose a badly answered query, measure it with noise, rescale, repair what broke.

    regions: r1, r2, c1, c2, b of disjoint regions over the grid (None: one region of density 1).
    """
    side, source = truth.side, source or noise.draws(p.seed)
    est = initial(side, n, face_mass)
    true = truth.answers(q) if answers is None else answers
    rect, region, b = laid_out(regions, side, p.density_scale)
    out, total = Synthesis(est), DenseHist.zeros(side)
    for i in range(p.rounds):
        t0 = time.perf_counter()
        guess = est.answers(q)
        k = chosen(np.abs(true - guess), qids, p.eps3 / p.rounds, p, i, source)
        error = measured(true[k], guess[k], int(qids[k]), p, i, source)
        kf, kv, kh = factors(side, q[k], error, n, p, region, b, rect)
        est = normalised(DenseHist(est.f * kf, est.v * kv, est.h * kh), est, p.normalise, n)
        row = {"iter": i, "qid": int(qids[k]), "werr": float(error), "scored": len(q), "touched": int((kf != 1).sum()), "violated": 0, "repaired_l1": 0.0, "components": 0, "largest": 0, "certified": True}
        row["scale_ms"] = 1000 * (time.perf_counter() - t0)
        if p.repair != "none" and (bad := est.violated()):
            row["violated"] = bad
            if p.repair == "optimal":
                fixed = repair.optimal(est)
                row |= {"repaired_l1": fixed.moved, "certified": fixed.certified, "components": fixed.components, "largest": fixed.largest}
                est = fixed.hist
            else:
                fixed = repair.greedy(est, p.repair)
                row["repaired_l1"] = float(sum(np.abs(x - y).sum() for x, y in zip(fixed.parts(), est.parts())))
                est = fixed
        row["ms"] = 1000 * (time.perf_counter() - t0)
        out.trace.append(row)
        if p.average:
            total = DenseHist(total.f + est.f, total.v + est.v, total.h + est.h)
    out.hist = DenseHist(total.f / p.rounds, total.v / p.rounds, total.h / p.rounds) if p.average and p.rounds else est
    return out


def run_logweight(truth: DenseHist, qids: np.ndarray, q: np.ndarray, regions: pd.DataFrame, n: float, face_mass: float, p: SynthParams, source=None) -> Synthesis:
    """The same without repair, kept as one exponent for each region: est = start * exp(exponent), scaled once at the end of each round."""
    side, start, source = truth.side, initial(truth.side, n, face_mass), source or noise.draws(p.seed)
    rect, region, b = laid_out(regions, side, p.density_scale)
    true, exponent, est = truth.answers(q), np.zeros(len(rect)), start
    inner_v, inner_h = region[:, :-1] == region[:, 1:], region[:-1] == region[1:]
    cross_v, cross_h = np.zeros(start.v.shape), np.zeros(start.h.shape)  # exponents of edges between regions
    out = Synthesis(start)
    for i in range(p.rounds):
        guess = est.answers(q)
        k = chosen(np.abs(true - guess), qids, p.eps3 / p.rounds, p, i, source)
        error = measured(true[k], guess[k], int(qids[k]), p, i, source)
        r1, r2, c1, c2 = q[k]
        meets = (rect[:, 0] <= r2) & (rect[:, 1] >= r1) & (rect[:, 2] <= c2) & (rect[:, 3] >= c1)
        step = np.where(meets, np.log(powers(error * b / (2 * n), p)), 0.0)
        exponent = exponent + step
        for cross, a, c in ((cross_v, region[:, :-1], region[:, 1:]), (cross_h, region[:-1], region[1:])):
            cross += np.where(meets[a] & meets[c], np.minimum(step[a], step[c]), 0.0)
        f = start.f * np.exp(exponent[region])
        v = start.v * np.exp(np.where(inner_v, exponent[region[:, :-1]], cross_v))
        h = start.h * np.exp(np.where(inner_h, exponent[region[:-1]], cross_h))
        est = normalised(DenseHist(f, v, h), start, "face", n)
        out.trace.append({"iter": i, "qid": int(qids[k]), "werr": float(error)})
    out.hist = est
    return out


def cost_summary(trace: list[dict]) -> dict[str, float]:
    """What a synthesis did: scored queries, rescaled cells, repairs, their components and the largest of them."""
    add = lambda k: float(sum(t.get(k, 0) for t in trace))
    return {
        "rounds": float(len(trace)), "scored": add("scored"), "touched": add("touched"), "repairs": float(sum(t.get("violated", 0) > 0 for t in trace)),
        "violated": add("violated"), "components": add("components"), "largest_component": float(max((t.get("largest", 0) for t in trace), default=0)), "repaired_l1": add("repaired_l1"),
    }


def answer_bound(n: float, components: float, rounds: int, queries: float, eps: float) -> float:
    """The worst answer error that holds with probability 1 - 2 rounds / queries."""
    return 2 * n * np.sqrt(np.log(components) / rounds) + 10 * rounds * np.log(queries) / eps


def partition_bound(n: float, alpha: float, eps: float, best: float) -> float:
    return best + 16 * n * np.log(n / alpha) / eps


def least_rounds(components: float) -> float:
    """Rounds from which the bound's first term is at most n."""
    return 4 * np.log(components)
