"""Joins and functions around the methods that Spark lacks or that pay for a plan of their own."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..functions import noise
from .walks import segment_cells


def range_binned(steps: DataFrame, queries: DataFrame, width: int) -> DataFrame:
    """Steps with the rectangles that hold them, by equality of tiles of ``width`` cells; for query sets too large to broadcast."""
    tiles = lambda lo, hi: F.sequence(F.floor(F.col(lo) / width).cast("int"), F.floor(F.col(hi) / width).cast("int"))
    q = queries.withColumn("tr", F.explode(tiles("r1", "r2"))).withColumn("tc", F.explode(tiles("c1", "c2")))
    s = steps.withColumns({"tr": F.floor(F.col("row") / width).cast("int"), "tc": F.floor(F.col("col") / width).cast("int")})
    return s.join(q, ["tr", "tc"]).where(F.col("row").between(F.col("r1"), F.col("r2")) & F.col("col").between(F.col("c1"), F.col("c2")))


def as_of(probes: DataFrame, known: DataFrame, key: str, at: str, since: str, value: str) -> DataFrame:
    """Probes with the last value known at their time: a union in time order and the last value before each probe."""
    left = probes.withColumns({"_t": F.col(at), "_p": F.lit(1), "_v": F.lit(None).cast(dict(known.dtypes)[value])})
    right = known.select(key, F.col(since).alias("_t"), F.lit(0).alias("_p"), F.col(value).alias("_v"))
    w = Window.partitionBy(key).orderBy("_t", "_p").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right, allowMissingColumns=True).withColumn(value, F.last("_v", ignorenulls=True).over(w))
    return both.where("_p = 1").drop("_t", "_p", "_v")


BLOCK = 4096  # keys on each side of a table of pairs


def overlapping(spans: DataFrame, key: str, start: str, end: str, block: int = BLOCK) -> DataFrame:
    """key, other, n: how often spans of two keys overlap. Days that both touch meet; a pair counts on the first of them.

    Most pairs of keys overlap somewhere, so a join's rows would be nearly all pairs on every day. Keys are dealt into
    blocks instead; a task takes two blocks, counts the pairs of a day by arrays and gives each pair once.
    """
    kind = dict(spans.dtypes)[key]
    valid = spans.where(F.col(key).isNotNull() & F.col(start).isNotNull() & F.col(end).isNotNull())
    many = valid.select(key).distinct().count()
    blocks = max(1, -(-many // block), min(8, many // 256))
    first = lambda c: F.datediff(F.to_date(c), F.lit("1970-01-01").cast("date")).cast("int")
    own = valid.select(F.col(key).alias("key"), F.col(start).alias("s"), F.col(end).alias("e"), first(start).alias("f"), F.explode(F.sequence(first(start), first(end))).alias("d"), F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int").alias("g"))
    rows = own.withColumn("h", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("pair", F.least("g", "h") * blocks + F.greatest("g", "h")).drop("h")
    dealt = rows.repartition(min(2000, blocks * (blocks + 1) // 2), "pair").sortWithinPartitions("pair")

    def tables(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, now = [], None
        for batch in batches:
            pair = batch.column("pair").to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(pair)) + 1).tolist(), len(pair)]
            for lo, hi in zip(cuts, cuts[1:]):
                if lo == hi:
                    continue
                if held and pair[lo] != now:
                    yield from pairs_of(pa.Table.from_batches(held), int(now) // blocks, int(now) % blocks)
                    held = []
                now = pair[lo]
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from pairs_of(pa.Table.from_batches(held), int(now) // blocks, int(now) % blocks)

    found = dealt.mapInArrow(tables, f"key {kind}, other {kind}, n long")
    return found.select(F.col("key").alias(key), "other", "n")


def pairs_of(rows: pa.Table, g: int, h: int, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """key, other, n of all pairs between the keys of two blocks, or within one."""
    names, place = np.unique(rows.column("key").to_numpy(), return_inverse=True)
    at = {c: rows.column(c).to_numpy() for c in ("d", "f", "g")}
    ends = [rows.column(c).combine_chunks().cast(pa.int64()).to_numpy() for c in ("s", "e")]
    sides = [np.unique(place[at["g"] == k]) for k in (g, h)]
    if not all(map(len, sides)):
        return
    counts = np.zeros([len(x) for x in sides], np.int32)
    order = np.lexsort((place, at["d"]))
    cuts = [0, *(np.flatnonzero(np.diff(at["d"][order])) + 1).tolist(), len(order)]
    for lo, hi in zip(cuts, cuts[1:]):
        day = order[lo:hi]
        # ranks keep the order of the day's times and take two bytes where they can
        _, rank = np.unique(np.concatenate([x[day] for x in ends]), return_inverse=True)
        rank = (rank + 1).astype(np.uint16 if len(rank) < 65_000 else np.int64)
        s, e, f, own = rank[: len(day)], rank[len(day) :], at["f"][day], place[day]
        number = np.arange(len(day)) - np.searchsorted(own, own)  # of a key's spans of the day
        plain, d = bool((f == at["d"][day[0]]).all()), at["d"][day[0]]
        turns = [[(np.searchsorted(side, own[x]), x) for k in range(number.max() + 1) if len(x := np.flatnonzero((number == k) & (at["g"][day] == b)))] for side, b in zip(sides, (g, h))]
        for pa_, a in turns[0]:
            for pb, b in turns[1]:
                if plain and 2 * len(pa_) > len(sides[0]) and 2 * len(pb) > len(sides[1]):  # keys without a span begin after all and end before
                    (sa, ea), (sb, eb) = (wide(len(x), p, s[i], e[i]) for x, p, i in ((sides[0], pa_, a), (sides[1], pb, b)))
                    counts += (sa[:, None] <= eb[None, :]) & (sb[None, :] <= ea[:, None])
                    continue
                meet = (s[a][:, None] <= e[b][None, :]) & (s[b][None, :] <= e[a][:, None])
                if not plain:
                    meet &= np.maximum(f[a][:, None], f[b][None, :]) == d
                counts[np.ix_(pa_, pb)] += meet
    if g == h:
        counts = np.triu(counts, 1)
    step = max(1, most // counts.shape[1])
    for lo in range(0, len(counts), step):
        i, j = np.nonzero(counts[lo : lo + step])
        if len(i):
            u, v = sides[0][i + lo], sides[1][j]
            yield pa.RecordBatch.from_arrays([pa.array(names[np.minimum(u, v)]), pa.array(names[np.maximum(u, v)]), pa.array(counts[i + lo, j].astype(np.int64))], names=["key", "other", "n"])


def wide(n: int, place: np.ndarray, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    starts, ends = np.full(n, np.iinfo(s.dtype).max, s.dtype), np.zeros(n, s.dtype)
    starts[place], ends[place] = s, e
    return starts, ends


def histogram_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """comp, row, col, diff over the components of either histogram."""
    keys = ["comp", "row", "col"]
    return a.join(b.withColumnRenamed("cnt", "other"), keys, "full").select(*keys, (F.coalesce("cnt", F.lit(0.0)) - F.coalesce("other", F.lit(0.0))).alias("diff"))


def hash_fraction(key: str, seed: int) -> Column:
    return noise.uniform(seed, "rows", key)


def hilbert_twin(cells: DataFrame, res: int) -> DataFrame:
    """Hilbert places by a vectorised function: for comparison with the column arithmetic."""

    @F.pandas_udf("long")
    def place(row: pd.Series, col: pd.Series) -> pd.Series:
        from ..plans.baselines import hilbert_order

        r, c = hilbert_order(res)
        table = pd.Series(range(len(r)), index=pd.MultiIndex.from_arrays([r, c]))
        return pd.Series(table.reindex(pd.MultiIndex.from_arrays([row, col])).to_numpy())

    return cells.withColumn("pos", place("row", "col"))


def deviation_by(rows: DataFrame, key: str, value: str) -> DataFrame:
    """key, dev: summed distance to the mean by a grouped aggregate function over vectors."""

    @F.pandas_udf("double")
    def deviation(v: pd.Series) -> float:
        return float((v - v.mean()).abs().sum())

    return rows.groupBy(key).agg(deviation(value).alias("dev"))


@F.udtf(returnType="k int, row int, col int")
class CellsOfSegment:
    """k, row, col: cells of unit side that the segment (x1, y1)-(x2, y2) passes."""

    def eval(self, x1: float, y1: float, x2: float, y2: float):
        for k, (r, c) in enumerate(segment_cells(x1, y1, x2, y2)):
            yield k, r, c


@F.udtf(returnType="level int, br int, bc int")
class QuadAncestors:
    """level, br, bc: the blocks of a quadtree of 2^res cells a side that hold a cell, from the whole grid down."""

    def eval(self, row: int, col: int, res: int):
        for level in range(res + 1):
            yield level, row >> (res - level), col >> (res - level)


@F.pandas_udf(LongType())
def hilbert_places(row: pd.Series, col: pd.Series, res: pd.Series) -> pd.Series:
    """Places along the Hilbert curve, by the bits of all rows at once; for SQL."""
    x, y, out = col.to_numpy("int64").copy(), row.to_numpy("int64").copy(), np.zeros(len(row), np.int64)
    top = int(res.max()) if len(res) else 0
    own = res.to_numpy("int64")
    for level in range(top - 1, -1, -1):
        on, s = level < own, np.int64(1 << level)
        rx, ry = (x >> level) & 1, (y >> level) & 1
        out = np.where(on, out + s * s * ((3 * rx) ^ ry), out)
        mx, my = x % s, y % s
        flip = (ry == 0) & (rx == 1)
        fx, fy = np.where(flip, s - 1 - mx, mx), np.where(flip, s - 1 - my, my)
        x, y = np.where(on, np.where(ry == 0, fy, fx), x), np.where(on, np.where(ry == 0, fx, fy), y)
    return pd.Series(out)


def arrow_cells(points: DataFrame, grid) -> DataFrame:
    """traj_id, row, col of points inside the grid, over Arrow batches: a twin of the column arithmetic for comparison."""

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = {}
            for name, column, lo, hi in (("row", "y", grid.y0, grid.y1), ("col", "x", grid.x0, grid.x1)):
                v = np.floor((batch.column(column).to_numpy(zero_copy_only=False) - lo) / (hi - lo) * grid.side)
                at[name] = pa.array(np.clip(v, 0, grid.side - 1).astype(np.int32))
            yield pa.RecordBatch.from_arrays([batch.column("traj_id"), at["row"], at["col"]], names=["traj_id", "row", "col"])

    rows = points.where("x is not null and y is not null").select("traj_id", "x", "y")
    return rows.mapInArrow(place, "traj_id long, row int, col int")


def segment_table(spark, segments: list[tuple[float, float, float, float]]) -> DataFrame:
    """seg, k, row, col of each segment, through SQL with LATERAL."""
    spark.udtf.register("cells_of_segment", CellsOfSegment)
    frame = spark.createDataFrame([(i, *s) for i, s in enumerate(segments)], "seg int, x1 double, y1 double, x2 double, y2 double")
    frame.createOrReplaceTempView("trajdp_segments")
    return spark.sql("SELECT seg, k, row, col FROM trajdp_segments, LATERAL cells_of_segment(x1, y1, x2, y2)")
