"""Sums over whole walks, taken by arrays in tasks: a walk's steps meet in one task in order, and only sums by component leave it."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .walks import along

CHUNK = 1 << 18  # rows looked at together
WIDE = 1 << 30  # rows and columns below it fit packed keys
SPAN = 1 << 17  # steps of walks that are looked at together
TABLE = 1 << 23  # cells of walks that are looked at together


def in_order(steps: DataFrame) -> DataFrame:
    """traj_id, row, col with each walk in one partition, in order; a frame that is so already is not dealt out again."""
    numbered = steps.select("traj_id", "step", "row", "col", F.row_number().over(along()).alias("k"))
    return numbered.sortWithinPartitions("traj_id", "step").where("k > 0").select("traj_id", "row", "col")


def chunks(batches: Iterator[pd.DataFrame], least: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """traj_id, row, col of successive batches put together to ``least`` rows or more."""
    parts, size = [], 0
    for batch in batches:
        if len(batch):
            parts.append(tuple(batch[c].to_numpy(np.int64) for c in ("traj_id", "row", "col")))
            size += len(batch)
        if size >= least:
            yield tuple(np.concatenate(x) for x in zip(*parts))
            parts, size = [], 0
    if parts:
        yield tuple(np.concatenate(x) for x in zip(*parts))


def crossed(t: np.ndarray, row: np.ndarray, col: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The steps that cross a border to the next one, and its component (1: V, 2: H), row and col."""
    dr, dc = np.abs(np.diff(row)), np.abs(np.diff(col))
    at = np.flatnonzero((t[1:] == t[:-1]) & (dr + dc == 1))
    return at, np.where(dr[at] == 0, 1, 2), np.minimum(row[at], row[at + 1]), np.minimum(col[at], col[at + 1])


def packed(comp: np.ndarray, row: np.ndarray, col: np.ndarray) -> np.ndarray:
    if min(row.min(), col.min()) < -WIDE or max(row.max(), col.max()) >= WIDE:
        raise ValueError(f"rows and columns must lie between {-WIDE} and {WIDE - 1}")
    return (comp.astype(np.uint64) << np.uint64(62)) | ((row + WIDE).astype(np.uint64) << np.uint64(31)) | (col + WIDE).astype(np.uint64)


def unpacked(key: np.ndarray) -> pd.DataFrame:
    low = lambda x: ((x & np.uint64((1 << 31) - 1)).astype(np.int64) - WIDE).astype(np.int32)
    return pd.DataFrame({"comp": np.array(["F", "V", "H"])[(key >> np.uint64(62)).astype(np.int64)], "row": low(key >> np.uint64(31)), "col": low(key)})


def distinct_counts(steps: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """comp, row, col, cnt: how many walks have each component.

    What is held of a walk that reaches over chunks is its last step and its distinct components, which the grid bounds.
    """

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        open_id, last, seen = None, None, np.zeros(0, np.uint64)
        for traj, row, col in chunks(batches, chunk):
            fresh = len(traj)
            if traj[0] == open_id:  # the crossing from the chunk before
                traj, row, col = (np.concatenate([[a], b]) for a, b in zip((open_id, *last), (traj, row, col)))
            else:
                seen = seen[:0]
            walk = np.concatenate([[0], np.cumsum(traj[1:] != traj[:-1])])
            at, comp, er, ec = crossed(walk, row, col)
            key = packed(np.concatenate([np.zeros(fresh, np.int64), comp]), np.concatenate([row[-fresh:], er]), np.concatenate([col[-fresh:], ec]))
            names, key = np.unique(key, return_inverse=True)
            pairs = np.unique(np.concatenate([walk[-fresh:], walk[at]]) * len(names) + key)
            walks, found = pairs // len(names), names[pairs % len(names)]
            again = (walks == 0) & np.isin(found, seen)
            ends = found[walks == walk[-1]]
            seen = np.union1d(seen, ends) if walk[-1] == 0 else ends
            open_id, last = traj[-1], (row[-1], col[-1])
            kinds, n = np.unique(found[~again], return_counts=True)
            yield unpacked(kinds).assign(n=n.astype(float))

    partial = in_order(steps).mapInPandas(count, "comp string, row int, col int, n double")
    return partial.groupBy("comp", "row", "col").agg(F.sum("n").alias("cnt"))


def staircases(walk: np.ndarray, row: np.ndarray, col: np.ndarray, side: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """As walks.collapse and walks.fill (staircase) over arrays of points in order, walks numbered from 0: for some walks at a
    time the code of each step (number among them * side^2 + row * side + col) and the number of steps of each walk."""
    keep = np.ones(len(walk), bool)
    keep[1:] = (walk[1:] != walk[:-1]) | (row[1:] != row[:-1]) | (col[1:] != col[:-1])
    walk, row, col = walk[keep], row[keep], col[keep]
    on = np.append(walk[1:] == walk[:-1], False)
    dr, dc = (np.where(on, np.append(np.diff(x), 0), 0) for x in (row, col))
    starts = np.flatnonzero(np.append(True, walk[1:] != walk[:-1]))
    lengths = np.add.reduceat(np.abs(dr) + np.abs(dc) + ~on, starts)
    cells, ends = side * side, np.cumsum(lengths)
    # along the row, then along the column; a walk's last step leads to the first one of the next walk
    times = np.stack([np.abs(dc) + ~on, np.abs(dr)], axis=1)
    by = np.stack([np.sign(dc), side * np.sign(dr)], axis=1)
    place = row * side + col
    by[np.append(starts[1:], len(walk)) - 1, 0] = np.append(place[starts[1:]], 0) - place[~on] + cells
    a = 0
    while a < len(starts):
        done = ends[a - 1] if a else 0
        b = max(a + 1, min(a + max(1, TABLE // cells), int(np.searchsorted(ends, done + SPAN, "right"))))
        of = slice(starts[a], starts[b] if b < len(starts) else len(walk))
        moves = np.repeat(by[of].ravel(), times[of].ravel())
        yield np.cumsum(np.append(place[starts[a]], moves[:-1])), lengths[a:b]
        a = b


def without_loops(code: np.ndarray, lengths: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What walks.erase_loops keeps of walks given as by ``staircases``. last: a table with a place for each code.

    Only steps in cells that come again end a stretch; all walks go from stretch to stretch together.
    """
    at = np.arange(len(code), dtype=last.dtype)
    last[code] = -1
    np.maximum.at(last, code, at)
    again = last[code]
    back = np.flatnonzero(again > at)
    if not len(back):
        return code, lengths
    beyond = np.cumsum(lengths)
    now, starts = beyond - lengths, beyond - lengths
    gone = np.zeros(len(code) + 1, np.int8)
    while len(now):
        k = np.searchsorted(back, now)
        stop = np.append(back, len(code))[k]
        going = stop < beyond
        stop, beyond = stop[going], beyond[going]
        now = again[stop].astype(np.int64) + 1
        gone[stop + 1], gone[now] = 1, -1
        going = now < beyond
        now, beyond = now[going], beyond[going]
    keep = np.cumsum(gone[:-1], dtype=np.int8) == 0
    return code[keep], np.add.reduceat(keep, starts, dtype=np.int64)


def walk_sums(cells: DataFrame, side: int, policy: str = "erase", chunk: int | None = None, most: int = 1 << 22) -> DataFrame:
    """part, row, col, value of walks given by their points' cells on a square grid, staircases filled and loops taken out.

    Parts F, V and H: visits; S: shares of faces, each walk adding one in all; N: walks; K: the most steps of a walk;
    L: above 0 if a walk has more than ``most`` steps or an eighth of it in points, and then the other parts are not whole.
    Tasks hold arrays of the grid's size, and the steps of a walk or of a few walks at a time.
    """
    chunk, size = chunk or CHUNK >> 2, side * side

    def add(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        f, edges, share = np.zeros(size, np.int64), np.zeros(2 * size + 1, np.int64), np.zeros(size)
        last = np.empty(max(TABLE, size), np.int32)
        n = longest = 0
        wide = False
        waiting: list[tuple[np.ndarray, ...]] = []

        def flush() -> None:
            for cell, edge, weight in [tuple(np.concatenate(x) for x in zip(*waiting))] if waiting else []:
                f[:] += np.bincount(cell, minlength=size)
                edges[:] += np.bincount(edge, minlength=2 * size + 1)
                share[:] += np.bincount(cell, weight, size)
            waiting.clear()

        held = tuple(np.zeros(0, np.int64) for _ in range(3))
        for part in itertools.chain(chunks(batches, chunk), [None]):
            now = held if part is None else tuple(np.concatenate(x) for x in zip(held, part))
            if not len(now[0]):
                continue
            cut = len(now[0]) if part is None else int(np.flatnonzero(np.append(True, now[0][1:] != now[0][:-1]))[-1])
            held = tuple(x[cut:] for x in now)
            if 8 * len(held[0]) > most:  # its last point stays
                wide = True
                held = tuple(x[-1:] for x in held)
            if not cut or wide:  # one walk so far
                continue
            traj, row, col = (x[:cut] for x in now)
            for code, lengths in staircases(np.append(0, np.cumsum(traj[1:] != traj[:-1])), row, col, side):
                if lengths.max() > most:
                    wide = True
                    break
                if policy == "erase":
                    code, lengths = without_loops(code, lengths, last)
                first = np.repeat(np.arange(len(lengths)) * size, lengths)
                cell, weight = code - first, np.repeat(1.0 / lengths, lengths)
                if policy != "erase":  # each cell of a walk once
                    own, times = np.unique(code, return_inverse=True, return_counts=True)[1:]
                    weight = (1.0 / np.bincount(np.unique(code) // size))[code // size] / times[own]
                step = np.abs(np.diff(cell))
                edge = np.minimum(cell[1:], cell[:-1]) + size * (step != 1)
                edge[np.cumsum(lengths)[:-1] - 1] = 2 * size
                waiting.append((cell, np.append(edge, 2 * size), weight))
                n, longest = n + len(lengths), max(longest, int(lengths.max()))
                if sum(len(x[0]) for x in waiting) >= SPAN:
                    flush()
        flush()
        for kind, x in (("F", f), ("V", edges[:size]), ("H", edges[size:-1]), ("S", share)):
            at = np.flatnonzero(x)
            yield pd.DataFrame({"part": kind, "row": (at // side).astype(np.int32), "col": (at % side).astype(np.int32), "value": x[at].astype(float)})
        yield pd.DataFrame({"part": ["N", "K", "L"], "row": np.zeros(3, np.int32), "col": np.zeros(3, np.int32), "value": [float(n), float(longest), float(wide)]})

    # points that their numbering has dealt out by walk are not dealt out again; each task gives a histogram, so they are not many
    dealt = in_order(cells).coalesce(4 * cells.sparkSession.sparkContext.defaultParallelism)
    partial = dealt.mapInPandas(add, "part string, row int, col int, value double")
    return partial.groupBy("part", "row", "col").agg(F.when(F.col("part") == "K", F.max("value")).otherwise(F.sum("value")).alias("value"))
