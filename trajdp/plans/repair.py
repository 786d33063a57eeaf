"""Consistency: every edge at most its two faces.

The nearest consistent histogram in L1 is a linear programme whose dual is a
maximum-weight matching of edges and faces over the violated incidences, at
weight edge - face. Its potentials are the answer: edges go down by theirs,
faces go up by theirs, and the moved amount equals the matching's weight, which
certifies that nothing nearer exists.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import kept
from .dense import DenseHist


@dataclass
class Repair:
    hist: DenseHist
    moved: float
    matched: float
    edges: int
    components: int = 0
    largest: int = 0

    @property
    def certified(self) -> bool:
        return self.hist.violated() == 0 and abs(self.moved - self.matched) <= 1e-6 * max(1.0, self.moved)


def matched_potentials(near: list[list[int]], weight: list[list[float]], rights: int) -> tuple[list[float], list[float], float]:
    """Potentials of a maximum-weight matching (left i to near[i]); nodes may stay alone. Shortest paths on reduced costs."""
    u = [max([0.0, *w]) for w in weight]
    v = [0.0] * rights
    mate = [-1] * rights
    partner = [-1] * len(near)
    for root in range(len(near)):
        at_left, at_right, parent = {root: 0.0}, {}, {}
        heap: list[tuple[float, int, int]] = []  # distance, right (or -1: the left node stays alone), left that reached it

        def reach(i: int, d: float, heap=heap) -> None:
            heapq.heappush(heap, (d + u[i], -1, i))
            for j, w in zip(near[i], weight[i]):
                if j not in at_right:
                    heapq.heappush(heap, (d + max(0.0, u[i] + v[j] - w), j, i))

        reach(root, 0.0)
        while True:
            d, j, i = heapq.heappop(heap)
            if j >= 0 and j in at_right:
                continue
            if j < 0 or mate[j] < 0:
                break
            at_right[j], parent[j] = d, i
            at_left[mate[j]] = d
            reach(mate[j], d)
        for k, dk in at_left.items():
            u[k] -= d - dk
        for k, dk in at_right.items():
            v[k] += d - dk
        # along the path every left node takes the right node that reached it
        take, left = j, i
        while True:
            before = partner[left]
            partner[left] = take
            if take >= 0:
                mate[take] = left
            if left == root:
                break
            take, left = before, parent[before]
    total = sum(w for i, j in enumerate(partner) if j >= 0 for k, w in zip(near[i], weight[i]) if k == j)
    return u, v, total


def incidences(hist: DenseHist):
    """Edges with their two faces as flat numbers: (array, index, face, face)."""
    s = hist.side
    number = np.arange(s * s).reshape(s, s)
    return ((hist.v, number[:, :-1], number[:, 1:]), (hist.h, number[:-1], number[1:]))


def joined_faces(pairs: np.ndarray, faces: np.ndarray) -> np.ndarray:
    """A label for each of ``faces``: equal for faces that ``pairs`` (two columns) join, over any number of steps."""
    parent = {int(f): int(f) for f in faces}

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in pairs.tolist():
        x, y = find(a), find(b)
        if x != y:
            parent[max(x, y)] = min(x, y)
    return np.array([find(int(f)) for f in faces], np.int64)


def component_moves(edge: np.ndarray, face: np.ndarray, weight: np.ndarray) -> tuple[dict[int, float], dict[int, float], float]:
    """How far each edge falls and each face rises in one component of violated incidences (edge, face, weight)."""
    lefts, rights = {int(e): i for i, e in enumerate(dict.fromkeys(edge.tolist()))}, {int(f): j for j, f in enumerate(dict.fromkeys(face.tolist()))}
    near: list[list[int]] = [[] for _ in lefts]
    cost: list[list[float]] = [[] for _ in lefts]
    for e, f, w in zip(edge.tolist(), face.tolist(), weight.tolist()):
        near[lefts[e]].append(rights[f])
        cost[lefts[e]].append(w)
    u, v, total = matched_potentials(near, cost, len(rights))
    return {e: u[i] for e, i in lefts.items()}, {f: v[j] for f, j in rights.items()}, total


def optimal(hist: DenseHist) -> Repair:
    """The L1-nearest consistent histogram, component by component of the violated incidences.

    Where every violated edge of a component has one violated face (a star), the
    face rises to the second largest of its violated edges and they come down
    to it: all stars at once. Other components are matched one by one.
    """
    out, faces = hist.copy(), hist.f.ravel()
    parts = []
    for k, (edges, a, b) in enumerate(incidences(hist)):
        for face in (a, b):
            at = np.flatnonzero((edges > faces[face] + 1e-12).ravel())
            parts.append(np.c_[np.full(len(at), k), at, face.ravel()[at]])
    rows = np.concatenate(parts) if parts else np.zeros((0, 3), np.int64)
    flat = [out.v.ravel(), out.h.ravel()]
    value = np.where(rows[:, 0] == 0, hist.v.ravel()[np.where(rows[:, 0] == 0, rows[:, 1], 0)], hist.h.ravel()[np.where(rows[:, 0] == 1, rows[:, 1], 0)]) if len(rows) else np.zeros(0)
    edge = rows[:, 0] * hist.v.size + rows[:, 1]
    moved_faces, total = out.f.ravel(), 0.0
    found, where, times = np.unique(edge, return_inverse=True, return_counts=True) if len(rows) else (np.zeros(0), np.zeros(0, int), np.zeros(0))
    double = times[where] > 1 if len(rows) else np.zeros(0, bool)
    order = np.argsort(edge[double], kind="stable")
    pairs = rows[double][order, 2].reshape(-1, 2)
    label = np.arange(faces.size)
    if len(pairs):
        linked = np.unique(pairs)
        label[linked] = joined_faces(pairs, linked)
    mine = label[rows[:, 2]]
    tangled = np.isin(mine, np.unique(label[pairs])) if len(pairs) else np.zeros(len(rows), bool)
    sizes = np.unique(mine, return_counts=True)[1] if len(rows) else np.zeros(0, int)

    star = ~tangled
    if star.any():
        by = np.lexsort((-value[star], rows[star, 2]))
        f, x = rows[star, 2][by], value[star][by]
        second = np.r_[False, f[1:] == f[:-1]] & ~np.r_[False, False, f[2:] == f[:-2]][: len(f)]
        moved_faces[f[second]] = np.maximum(moved_faces[f[second]], x[second])
        first = np.r_[True, f[1:] != f[:-1]]
        total += float((x[first] - faces[f[first]]).sum())  # the matching takes each star's largest edge
        for k in (0, 1):
            of = star & (rows[:, 0] == k)
            np.minimum.at(flat[k], rows[of, 1], moved_faces[rows[of, 2]])
    for c in np.unique(mine[tangled]):
        of = mine == c
        down, up, weight = component_moves(edge[of], rows[of, 2], value[of] - faces[rows[of, 2]])
        for e, by_ in down.items():
            flat[0 if e < hist.v.size else 1][e if e < hist.v.size else e - hist.v.size] -= by_
        for f_, by_ in up.items():
            moved_faces[f_] += by_
        total += weight
    # sums of floats may leave an edge a last digit above
    np.minimum(out.v, np.minimum(out.f[:, :-1], out.f[:, 1:]), out=out.v, where=out.v - np.minimum(out.f[:, :-1], out.f[:, 1:]) < 1e-9)
    np.minimum(out.h, np.minimum(out.f[:-1], out.f[1:]), out=out.h, where=out.h - np.minimum(out.f[:-1], out.f[1:]) < 1e-9)
    moved = float(sum(np.abs(a - b).sum() for a, b in zip(out.parts(), hist.parts())))
    return Repair(out, moved, total, len(found), len(sizes), int(sizes.max()) if len(sizes) else 0)


def greedy(hist: DenseHist, how: str = "lower") -> DenseHist:
    """lower: edges down to their smaller face; raise: faces up to their largest edge."""
    out, f = hist.copy(), hist.f
    if how == "lower":
        out.v, out.h = np.minimum(hist.v, np.minimum(f[:, :-1], f[:, 1:])), np.minimum(hist.h, np.minimum(f[:-1], f[1:]))
        return out
    for edge, a, b in ((hist.v, np.s_[:, :-1], np.s_[:, 1:]), (hist.h, np.s_[:-1], np.s_[1:])):
        out.f[a], out.f[b] = np.maximum(out.f[a], edge), np.maximum(out.f[b], edge)
    return out


def edge_faces(hist: DataFrame) -> DataFrame:
    """comp, row, col, cnt, fr, fc, face: each edge with each of its two faces."""
    edges = hist.where("comp <> 'F'")
    second = edges.select("comp", "row", "col", "cnt", (F.col("row") + (F.col("comp") == "H").cast("int")).alias("fr"), (F.col("col") + (F.col("comp") == "V").cast("int")).alias("fc"))
    both = edges.select("comp", "row", "col", "cnt", F.col("row").alias("fr"), F.col("col").alias("fc")).unionByName(second)
    faces = hist.where("comp = 'F'").select(F.col("row").alias("fr"), F.col("col").alias("fc"), F.col("cnt").alias("face"))
    return both.join(faces, ["fr", "fc"])


def greedy_frame(hist: DataFrame, how: str = "lower") -> DataFrame:
    ties = edge_faces(hist)
    if how == "lower":
        low = ties.groupBy("comp", "row", "col").agg(F.min("face").alias("low"))
        return hist.join(low, ["comp", "row", "col"], "left").select("comp", "row", "col", F.least("cnt", F.coalesce("low", "cnt")).alias("cnt"))
    high = ties.groupBy(F.lit("F").alias("comp"), F.col("fr").alias("row"), F.col("fc").alias("col")).agg(F.max("cnt").alias("high"))
    return hist.join(high, ["comp", "row", "col"], "left").select("comp", "row", "col", F.greatest("cnt", F.coalesce("high", "cnt")).alias("cnt"))


def star_frame(hist: DataFrame) -> DataFrame:
    """The nearest consistent histogram where every violated edge has one violated face: the face rises to the
    second largest of its violated edges, and the edges come down to it."""
    bad = edge_faces(hist).where("cnt > face")
    w = Window.partitionBy("fr", "fc").orderBy(F.desc("cnt"), "comp", "row", "col")
    second = bad.withColumn("k", F.row_number().over(w)).where("k = 2").select(F.lit("F").alias("comp"), F.col("fr").alias("row"), F.col("fc").alias("col"), F.col("cnt").alias("up"))
    faces = hist.where("comp = 'F'").join(second, ["comp", "row", "col"], "left").select("comp", "row", "col", F.greatest("cnt", F.coalesce("up", "cnt")).alias("cnt"))
    edges = greedy_frame(faces.unionByName(hist.where("comp <> 'F'").select("comp", "row", "col", "cnt"))).where("comp <> 'F'")
    return faces.unionByName(edges)


def merged_labels(links: DataFrame) -> DataFrame:
    """id, label: the smallest id that links (a, b) lead to. Each round merges every id into its smallest neighbour."""
    links = kept(links.select("a", "b").where("a <> b").distinct())
    label = kept(links.select(F.col("a").alias("id")).union(links.select(F.col("b").alias("id"))).distinct().withColumn("label", F.col("id")))
    while not links.isEmpty():
        both = links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        to = kept(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("to")))
        label = kept(label.join(to.withColumnRenamed("a", "label"), "label", "left").select("id", F.coalesce("to", "label").alias("label")))
        ends = links.join(to.select("a", F.col("to").alias("x")), "a").join(to.select(F.col("a").alias("b"), F.col("to").alias("y")), "b")
        links = kept(ends.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct())
    return label


def optimal_frame(hist: DataFrame, side: int) -> tuple[DataFrame, DataFrame]:
    """The L1-nearest consistent histogram, and moves: component, comp, row, col, change, matched.

    Components of violated incidences are found by merging faces that share an
    edge too large for both, and repaired each in a group of its own: a
    component, not the grid, must fit a task. matched, the weight of its
    matching, stands on one row of each component; its sum certifies the cost.
    """
    face = F.col("fr").cast("long") * side + F.col("fc")
    bad = kept(edge_faces(hist).where("cnt > face + 1e-12").withColumn("at", face))
    both = bad.groupBy("comp", "row", "col").agg(F.min("at").alias("a"), F.max("at").alias("b"))
    label = merged_labels(both)
    grouped = bad.join(label, bad["at"] == label["id"], "left").withColumn("component", F.coalesce("label", "at"))

    def match(rows: pd.DataFrame) -> pd.DataFrame:
        edge = (rows["comp"].eq("H").to_numpy() * side + rows["row"].to_numpy(np.int64)) * side + rows["col"].to_numpy(np.int64)
        down, up, total = component_moves(edge, rows["at"].to_numpy(np.int64), (rows["cnt"] - rows["face"]).to_numpy(float))
        out = [("H" if e >= side * side else "V", e // side % side, e % side, -x) for e, x in down.items()] + [("F", f // side, f % side, x) for f, x in up.items()]
        out = pd.DataFrame(out, columns=["comp", "row", "col", "change"]).assign(component=rows["component"].iloc[0], matched=0.0)
        out.loc[0, "matched"] = total
        return out[["component", "comp", "row", "col", "change", "matched"]]

    columns = ["component", "comp", "row", "col", "at", "cnt", "face"]
    moves = kept(grouped.select(*columns).groupBy("component").applyInPandas(match, "component long, comp string, row int, col int, change double, matched double"))
    fixed = hist.join(moves.groupBy("comp", "row", "col").agg(F.sum("change").alias("change")), ["comp", "row", "col"], "left")
    fixed = fixed.select("comp", "row", "col", (F.col("cnt") + F.coalesce("change", F.lit(0.0))).alias("cnt"))
    # sums of floats may leave an edge a last digit above
    low = edge_faces(fixed).groupBy("comp", "row", "col").agg(F.min("face").alias("low"))
    out = fixed.join(low, ["comp", "row", "col"], "left").select("comp", "row", "col", F.when(F.col("cnt") - F.col("low") < 1e-9, F.least("cnt", "low")).otherwise(F.col("cnt")).alias("cnt"))
    return out, moves
