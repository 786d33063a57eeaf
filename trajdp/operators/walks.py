"""From points to 4-connected walks over grid cells."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.trajectories import GridSpec


def assign(points: DataFrame, grid: GridSpec) -> DataFrame:
    """traj_id, step, row, col of each point. Points without coordinates go; those outside are clamped or dropped."""
    place = lambda v, lo, hi: F.floor((F.col(v) - F.lit(lo)) / F.lit(hi - lo) * grid.side).cast("int")
    rows = points.where("x is not null and y is not null").select("traj_id", F.col("seq").alias("step"), place("y", grid.y0, grid.y1).alias("row"), place("x", grid.x0, grid.x1).alias("col"))
    if grid.outside == "drop":
        return rows.where(F.col("row").between(0, grid.side - 1) & F.col("col").between(0, grid.side - 1))
    clamp = lambda c: F.least(F.greatest(F.col(c), F.lit(0)), F.lit(grid.side - 1)).alias(c)
    return rows.select("traj_id", "step", clamp("row"), clamp("col"))


def along() -> Window:
    return Window.partitionBy("traj_id").orderBy("step")


def renumbered(steps: DataFrame, *order: str) -> DataFrame:
    w = Window.partitionBy("traj_id").orderBy(*(order or ("step",)))
    return steps.select("traj_id", (F.row_number().over(w) - 1).cast("long").alias("step"), "row", "col")


def collapse(steps: DataFrame) -> DataFrame:
    """Consecutive steps in the same cell count once."""
    before = lambda c: F.lag(c).over(along())
    kept = steps.withColumns({"_r": before("row"), "_c": before("col")}).where("_r is null or _r <> row or _c <> col")
    return renumbered(kept.drop("_r", "_c"))


def sign(x: Column) -> Column:
    return F.signum(x.cast("double")).cast("int")


def fill(steps: DataFrame, how: str = "staircase") -> DataFrame:
    """Makes collapsed walks 4-connected.

    staircase: along the row to the next column, then along the column.
    drop: a hop between cells that don't share a side ends the piece; pieces
    get ids of their own, traj_id * 1000 + number.
    """
    after = steps.withColumns({"_r": F.lead("row").over(along()), "_c": F.lead("col").over(along())})
    if how == "drop":
        before = steps.withColumns({"_r": F.lag("row").over(along()), "_c": F.lag("col").over(along())})
        gap = F.coalesce((F.abs(F.col("row") - F.col("_r")) + F.abs(F.col("col") - F.col("_c")) != 1).cast("int"), F.lit(0))
        piece = before.withColumn("_gap", gap).withColumn("_piece", F.sum("_gap").over(along()))
        return renumbered(piece.select((F.col("traj_id") * 1000 + F.col("_piece")).alias("traj_id"), "step", "row", "col"))
    if how != "staircase":
        raise ValueError(f"unknown way to fill: {how}")
    dr, dc = F.col("_r") - F.col("row"), F.col("_c") - F.col("col")
    far = F.coalesce(F.abs(dr) + F.abs(dc), F.lit(1))
    cells = after.withColumns({"_dr": dr, "_dc": dc}).withColumn("_k", F.explode(F.sequence(F.lit(0), F.greatest(far - 1, F.lit(0)))))
    across = F.least(F.col("_k"), F.abs("_dc"))
    row = F.coalesce(F.col("row") + sign(F.col("_dr")) * (F.col("_k") - across), F.col("row"))
    col = F.coalesce(F.col("col") + sign(F.col("_dc")) * across, F.col("col"))
    return renumbered(cells.select("traj_id", "step", "_k", row.alias("row"), col.alias("col")), "step", "_k")


def fill_segments(points: DataFrame, grid: GridSpec) -> DataFrame:
    """The cells that straight lines between successive points pass, in order; through a corner first along the row."""
    w = Window.partitionBy("traj_id").orderBy("seq")
    scaled = lambda v, lo, hi: F.least(F.greatest((F.col(v) - lo) / (hi - lo) * grid.side, F.lit(0.0)), F.lit(grid.side - 1e-9))
    rows = points.where("x is not null and y is not null").select("traj_id", "seq", scaled("x", grid.x0, grid.x1).alias("x"), scaled("y", grid.y0, grid.y1).alias("y"))
    rows = rows.withColumns({"x2": F.lead("x").over(w), "y2": F.lead("y").over(w)})

    def trace(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for t, s, x, y, x2, y2 in batch[["traj_id", "seq", "x", "y", "x2", "y2"]].itertuples(index=False):
                cells = [(int(y), int(x))] if np.isnan(x2) else segment_cells(x, y, x2, y2)
                out += [(t, s, k, r, c) for k, (r, c) in enumerate(cells)]
            yield pd.DataFrame(out, columns=["traj_id", "seq", "k", "row", "col"])

    cells = rows.mapInPandas(trace, "traj_id long, seq long, k int, row int, col int")
    w = Window.partitionBy("traj_id").orderBy("seq", "k")
    return collapse(cells.select("traj_id", F.row_number().over(w).cast("long").alias("step"), "row", "col"))


def segment_cells(x: float, y: float, x2: float, y2: float) -> list[tuple[int, int]]:
    """Cells (row, col) of unit side that a segment passes, 4-connected."""
    row, col, end_row, end_col = int(y), int(x), int(y2), int(x2)
    cuts = []
    if col != end_col:
        for g in range(min(col, end_col) + 1, max(col, end_col) + 1):
            cuts.append(((g - x) / (x2 - x), 0, 1 if x2 > x else -1))
    if row != end_row:
        for g in range(min(row, end_row) + 1, max(row, end_row) + 1):
            cuts.append(((g - y) / (y2 - y), 1, 1 if y2 > y else -1))
    out = [(row, col)]
    for _, axis, by in sorted(cuts):
        row, col = (row + by, col) if axis else (row, col + by)
        out.append((row, col))
    return out


def erase_loops(steps: DataFrame) -> DataFrame:
    """Walks without loops: from each cell on to what follows its last visit.

    Steps must be numbered from 0 without gaps. Each gets the last visit of its cell; one pass over a
    trajectory's steps in order then keeps those that the one kept before leads to. A step is looked at once.
    """
    last = Window.partitionBy("traj_id", "row", "col")
    # the window over whole trajectories deals the rows by trajectory, the other needs no more than that
    numbered = steps.select("traj_id", "step", "row", "col", F.row_number().over(along()).alias("k"))
    order = numbered.withColumn("last", F.max("step").over(last)).sortWithinPartitions("traj_id", "step")

    def follow(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now, after, number = None, 0, 0
        for batch in batches:
            take, numbers = [], []
            for i, (t, s, l) in enumerate(zip(batch["traj_id"].tolist(), batch["step"].tolist(), batch["last"].tolist())):
                if t != now:
                    now, after, number = t, s, 0
                if s == after:
                    take.append(i)
                    numbers.append(number)
                    after, number = l + 1, number + 1
            out = batch.iloc[take]
            yield pd.DataFrame({"traj_id": out["traj_id"].to_numpy(), "step": np.array(numbers, np.int64), "row": out["row"].to_numpy(), "col": out["col"].to_numpy()})

    return order.mapInPandas(follow, "traj_id long, step long, row int, col int")


def bounded_runs(steps: DataFrame, most: int) -> DataFrame:
    """Each walk up to where it has turned back ``most`` times, along rows or along columns.

    To come back into a rectangle a walk must turn back along an axis, so that what
    is left meets every rectangle in at most ``most`` runs: its answers' sensitivity.
    """
    moves = steps.withColumns({f"_d{k}": F.signum((F.lead(k).over(along()) - F.col(k)).cast("double")) for k in ("row", "col")})
    before = along().rowsBetween(Window.unboundedPreceding, -1)
    turned = F.lit(0)
    for k in ("row", "col"):
        last = F.last(F.when(F.col(f"_d{k}") != 0, F.col(f"_d{k}")), ignorenulls=True).over(before)
        turned = turned + F.coalesce((F.col(f"_d{k}") * last < 0).cast("int"), F.lit(0))
    turns = moves.withColumn("_turn", turned).withColumn("_turns", F.coalesce(F.sum("_turn").over(before), F.lit(0)))
    return turns.where(F.col("_turns") < most).select("traj_id", "step", "row", "col")


def loops(steps: DataFrame, policy: str = "erase") -> DataFrame:
    return erase_loops(steps) if policy == "erase" else steps


def walk_steps(points: DataFrame, grid: GridSpec, how: str = "staircase", policy: str = "erase") -> DataFrame:
    """Points to 4-connected steps: grid, collapse, fill, loops."""
    if how == "segment":
        return loops(fill_segments(points, grid), policy)
    return loops(fill(collapse(assign(points, grid)), how), policy)


def length(steps: DataFrame) -> DataFrame:
    """traj_id, k: steps of each trajectory."""
    return steps.groupBy("traj_id").agg(F.count(F.lit(1)).alias("k"))
