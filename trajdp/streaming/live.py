"""Histograms of a live feed: windows, sessions, crossings with state, deduplication, joins, sinks and releases."""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import noise
from ..operators.mechanisms import Ledger
from ..storage import checkpoint_folder

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def scratch(spark: SparkSession) -> str:
    return f"{checkpoint_folder(spark).rstrip('/')}/trajdp-stream-{uuid.uuid4().hex}"


def source(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """Event files as a stream, ``files`` a micro-batch, in the order in which they were written."""
    schema = spark.read.parquet(path).schema
    one = f"{path[:-1]}[{path[-1]}]"  # as a pattern the path may be a file or a folder
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(one).withColumn("ts", F.col("ts").cast("timestamp"))


def feed(events: DataFrame, parts: int = 4, behind: DataFrame | None = None) -> str:
    """A folder with ``parts`` files of events in the order of time, and one of rows that come ``behind`` them all.

    Rows are late by the watermark of the batch before the last, so the last event comes alone before the late ones.
    """
    spark, path = events.sparkSession, scratch(events.sparkSession)
    cuts = events.agg(F.percentile_approx(F.col("ts").cast("timestamp").cast("double"), [k / parts for k in range(1, parts)], 10_000)).first()[0] if parts > 1 else []
    at, before = F.col("ts").cast("timestamp").cast("double"), None
    if behind is not None:
        last = events.agg(F.max(at)).first()[0]
        cuts = [*cuts, *([] if last is None else [math.nextafter(last, 0.0)])]
    for cut in [*cuts, None]:
        part = events
        part = part if before is None else part.where(at > before)
        part = part if cut is None else part.where(at <= cut)
        part.coalesce(1).write.mode("append").parquet(path)
        before = cut
    if behind is not None:
        behind.coalesce(1).write.mode("append").parquet(path)
    return path


def cells(events: DataFrame, side: int = 16) -> DataFrame:
    """event_id, ts, user_id, row, col of events on the public box of the skewed feed."""
    k = F.get_json_object("props", "$.k").cast("double")
    place = lambda v, top: F.least(F.greatest(F.floor(v / top * side), F.lit(0)), F.lit(side - 1)).cast("int")
    return events.select("event_id", "ts", "user_id", place(F.col("value"), 256.0).alias("row"), place(k, 100.0).alias("col"))


def tumbling(events: DataFrame, late: str = "1 hour", length: str = "1 day") -> DataFrame:
    """day, row, col, cnt of windows that don't overlap."""
    w = events.withWatermark("ts", late) if events.isStreaming else events
    return w.groupBy(F.window("ts", length).alias("w"), "row", "col").agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), "row", "col", "cnt")


def sliding(events: DataFrame, late: str = "1 hour", length: str = "2 days", every: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late) if events.isStreaming else events
    return w.groupBy(F.window("ts", length, every).alias("w"), "row").agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), "row", "cnt")


def sessions(events: DataFrame, late: str = "1 hour", gap: str = "6 hours") -> DataFrame:
    """user_id, start, cnt of runs of events less than a gap apart."""
    w = events.withWatermark("ts", late) if events.isStreaming else events
    return w.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("cnt")).select("user_id", F.col("w.start").alias("start"), "cnt")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


CROSSING = "traj_id long, comp string, row int, col int"


def crossings(events: DataFrame, idle: str | None = None, late: str = "1 hour") -> DataFrame:
    """traj_id, comp, row, col of the borders that each user's walk crosses, with the last cell of each kept as state.

    Batches must come in time order; hops are filled along the row first, as in batch. With ``idle`` a walk ends
    after that much silence: a later event begins a new one, and the watermark clears the state of ended walks.
    """
    wait = None if idle is None else pd.Timedelta(idle)

    def cross(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        columns = ["traj_id", "comp", "row", "col"]
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame([], columns=columns).astype({"traj_id": "int64", "comp": "object", "row": "int32", "col": "int32"})
            return
        rows = pd.concat(list(frames), ignore_index=True).sort_values(["ts", "event_id"])
        last = state.get if state.exists else None
        out = []
        for r, c, at in zip(rows["row"].tolist(), rows["col"].tolist(), rows["ts"].astype("int64").tolist() if rows["ts"].dtype == "datetime64[us]" else (rows["ts"].astype("datetime64[us]").astype("int64")).tolist()):
            if last is not None and (wait is None or at - last[2] <= wait.value // 1000):
                r0, c0, _ = last
                out += [("V", r0, x) for x in range(min(c0, c), max(c0, c))]
                out += [("H", y, c) for y in range(min(r0, r), max(r0, r))]
            last = (r, c, at)
        state.update(last)
        if wait is not None:
            state.setTimeoutTimestamp(max(last[2] // 1000 + wait.value // 1_000_000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame([(key[0], *o) for o in out], columns=columns)

    rows = events if idle is None else events.withWatermark("ts", late)
    return rows.select("user_id", "event_id", "ts", "row", "col").groupBy("user_id").applyInPandasWithState(
        cross, CROSSING, "row int, col int, at long", "append", GroupStateTimeout.NoTimeout if idle is None else GroupStateTimeout.EventTimeTimeout)


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Events with the segment of a static table."""
    return events.join(customers, events["user_id"] == customers["c_custkey"]).select("event_id", "user_id", "c_mktsegment")


def clicks_to_purchases(events: DataFrame, within: str = "2 days", late: str = "1 hour") -> DataFrame:
    """click, purchase: ids of purchases that follow a click of the same user in time."""
    def side(kind: str, *columns) -> DataFrame:
        rows = events.where(F.col("event_type") == kind).select(*columns)
        return rows.withWatermark(rows.columns[1], late) if events.isStreaming else rows

    a = side("click", F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("event_id").alias("click"))
    b = side("purchase", "user_id", "ts", F.col("event_id").alias("purchase"))
    return a.join(b, F.expr(f"u = user_id AND ts >= t AND ts <= t + interval {within}")).select("click", "purchase")


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there, into files, and reads them: the last state of all groups, or all rows appended."""
    spark, path = stream.sparkSession, scratch(stream.sparkSession)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", f"{path}/out").start()
    else:
        query = writer.foreachBatch(lambda batch, number: batch.write.mode("overwrite").parquet(f"{path}/out")).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


class RunningHistogram:
    """A sink for foreachBatch that adds each micro-batch's counts to a table of its own, once for each batch number."""

    def __init__(self, path: str):
        self.path = path

    def __call__(self, batch: DataFrame, number: int) -> None:
        counts = batch.groupBy("row", "col").agg(F.count(F.lit(1)).alias("cnt")).withColumn("batch", F.lit(number))
        counts.write.mode("overwrite").parquet(f"{self.path}/batch={number}")

    def total(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(self.path).groupBy("row", "col").agg(F.sum("cnt").alias("cnt"))


def released_windows(counts: DataFrame, eps: float, windows_each: int, cut: bool = False, seed: int | None = None) -> tuple[DataFrame, Ledger]:
    """Noisy counts of each window and the ledger; without a seed the noise is the operating system's. A trajectory may lie in ``windows_each`` windows, whose budgets
    add up; only if trajectories are cut at the windows' ends, and a piece is what is protected, does each get all."""
    ledger = Ledger(eps)
    each = eps if cut else eps / windows_each
    for i in range(1 if cut else windows_each):
        ledger.spend("window", each, 1.0, i, "parallel" if cut else "sequential")
    keyed = counts.withColumns({"_t": F.unix_timestamp("start"), "_r": F.col("row").cast("long"), "_c": F.col("col").cast("long")})
    drawn = noise.draws(seed).drawn(keyed, "_u", "window", "_t", "_r", "_c")
    return drawn.withColumn("cnt", F.col("cnt") + noise.laplace(F.col("_u"), 1.0 / each)).drop("_t", "_r", "_c", "_u"), ledger
