"""Histograms of bounded size as arrays: faces (s, s), V (s, s - 1), H (s - 1, s)."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from ..functions import noise
from ..operators.quadtree import PartitionParams, threshold

MOST = 1 << 22  # components that fit the driver


@dataclass
class DenseHist:
    f: np.ndarray
    v: np.ndarray
    h: np.ndarray

    @property
    def side(self) -> int:
        return len(self.f)

    @property
    def size(self) -> int:
        return self.f.size + self.v.size + self.h.size

    def copy(self) -> DenseHist:
        return DenseHist(self.f.copy(), self.v.copy(), self.h.copy())

    def parts(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.f, self.v, self.h

    @staticmethod
    def zeros(side: int) -> DenseHist:
        return DenseHist(np.zeros((side, side)), np.zeros((side, max(0, side - 1))), np.zeros((max(0, side - 1), side)))

    def answers(self, q: np.ndarray) -> np.ndarray:
        """Answers of all queries (rows r1, r2, c1, c2) from summed-area tables."""
        r1, r2, c1, c2 = q[:, 0], q[:, 1], q[:, 2], q[:, 3]
        return box_sums(self.f, r1, r2, c1, c2) - box_sums(self.v, r1, r2, c1, c2 - 1) - box_sums(self.h, r1, r2 - 1, c1, c2)

    def face_answers(self, q: np.ndarray) -> np.ndarray:
        return box_sums(self.f, q[:, 0], q[:, 1], q[:, 2], q[:, 3])

    def violated(self) -> int:
        f = self.f
        return int((self.v > np.minimum(f[:, :-1], f[:, 1:]) + 1e-9).sum() + (self.h > np.minimum(f[:-1], f[1:]) + 1e-9).sum())

    def excess(self) -> float:
        f = self.f
        return float(np.maximum(self.v - np.minimum(f[:, :-1], f[:, 1:]), 0).sum() + np.maximum(self.h - np.minimum(f[:-1], f[1:]), 0).sum())


def box_sums(x: np.ndarray, r1, r2, c1, c2) -> np.ndarray:
    """Sums over boxes with inclusive ends; 0 where an end lies before its start."""
    s = np.zeros((x.shape[0] + 1, x.shape[1] + 1))
    s[1:, 1:] = x.cumsum(0).cumsum(1)
    r, c = np.maximum(r2 + 1, r1), np.maximum(c2 + 1, c1)
    c, r = np.minimum(c, x.shape[1]), np.minimum(r, x.shape[0])
    a, b = np.minimum(r1, r), np.minimum(c1, c)
    return s[r, c] - s[a, c] - s[r, b] + s[a, b]


def collected(hist: DataFrame, side: int) -> DenseHist:
    """The histogram on the driver; the grid's size, not the data's, bounds it."""
    if 3 * side * side > MOST:
        raise ValueError(f"{3 * side * side} components are more than the driver takes; use plans.frames")
    rows = hist.toPandas()
    out = DenseHist.zeros(side)
    for comp, x in zip("FVH", out.parts()):
        part = rows[rows["comp"] == comp]
        x[part["row"].to_numpy(int), part["col"].to_numpy(int)] = part["cnt"].to_numpy(float)
    return out


def rows_of(hist: DenseHist) -> pd.DataFrame:
    frames = []
    for comp, x in zip("FVH", hist.parts()):
        r, c = np.indices(x.shape)
        frames.append(pd.DataFrame({"comp": comp, "row": r.ravel().astype(np.int32), "col": c.ravel().astype(np.int32), "cnt": x.ravel()}))
    return pd.concat(frames, ignore_index=True)


def framed(spark: SparkSession, hist: DenseHist) -> DataFrame:
    return spark.createDataFrame(rows_of(hist), "comp string, row int, col int, cnt double")


def query_array(queries: DataFrame, most: int = 1_000_000) -> tuple[np.ndarray, np.ndarray]:
    """qids and (r1, r2, c1, c2) on the driver; refuses more queries than ``most``."""
    rows = queries.limit(most + 1).toPandas().sort_values("qid")
    if len(rows) > most:
        raise ValueError(f"more than {most} queries")
    return rows["qid"].to_numpy(np.int64), rows[["r1", "r2", "c1", "c2"]].to_numpy(np.int64)


def partitioned(hist: DenseHist, shares: np.ndarray, n: int, p: PartitionParams, count: str = "range", source=None) -> pd.DataFrame:
    """As quadtree.partition, over arrays: pid, level, br, bc, r1, r2, c1, c2, size, total, b of the leaves by pid.

    The whole tree is a few sums over blocks of each level. source: where noise comes from, if not from the seed.
    """
    side, source = hist.side, source or noise.draws(p.seed)
    res = side.bit_length() - 1
    eps = p.eps1 / (res + 1) if p.scope == "per_level" else p.eps1
    scale = p.sensitivity / (eps if p.parent_noise == "reuse" else eps / 2)
    child, parent, totals = [], [], []
    for level in range(res + 1):
        k, w = 1 << level, side >> level
        blocks = shares.reshape(k, w, k, w)
        total = blocks.sum(axis=(1, 3))
        cost = np.abs(blocks - (total / (w * w))[:, None, :, None]).sum(axis=(1, 3))
        br, bc = (x.ravel() for x in np.indices((k, k)))
        noisy = lambda stream, cost=cost, keys=(np.full(k * k, level), br, bc), k=k: cost + noise.laplace_value(source.uniforms(stream, *keys), scale).reshape(k, k) if p.noise else cost
        child.append(noisy("cost"))
        parent.append(child[-1] if p.parent_noise == "reuse" or not p.noise else noisy("parent"))
        totals.append(total)
    alive, rows = np.ones((1, 1), bool), []
    for level in range(res + 1):
        k, w = 1 << level, side >> level
        split = np.zeros((k, k), bool)
        if level < res:
            split = parent[level] - child[level + 1].reshape(k, 2, k, 2).mean(axis=(1, 3)) > threshold(p)
        br, bc = np.nonzero(alive & ~split)
        pid = ((1 << (2 * level)) - 1) // 3 + br * k + bc
        rows.append(pd.DataFrame({"pid": pid, "level": level, "br": br, "bc": bc, "r1": br * w, "r2": (br + 1) * w - 1, "c1": bc * w, "c2": (bc + 1) * w - 1, "size": w * w, "total": totals[level][br, bc]}))
        alive = (alive & split).repeat(2, axis=0).repeat(2, axis=1)
    out = pd.concat(rows, ignore_index=True)
    q = out[["r1", "r2", "c1", "c2"]].to_numpy(np.int64)
    b = (hist.answers(q) if count == "range" else hist.face_answers(q)) / n
    if p.noise:
        b = b + noise.laplace_value(source.uniforms("density", out["pid"].to_numpy()), p.runs / p.eps2 / (n if p.density_on == "count" else 1))
        b = np.maximum(b, 0.0) if p.clamp else b
    return out.assign(b=b)
