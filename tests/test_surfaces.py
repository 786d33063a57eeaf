"""Files, SQL and streams."""

import pytest
from pyspark.sql import functions as F

from trajdp import sql
from trajdp.functions import noise
from trajdp.sources import files
from trajdp.streaming import live


def test_polylines_and_formats(spark, tmp_path):
    rows = spark.createDataFrame([(1, "[[0.5, 1.5], [2, 3]]"), (2, None), (3, "[]"), (4, "broken")], "traj_id long, polyline string")
    pts = files.from_polylines(rows)
    assert [tuple(r) for r in pts.orderBy("seq").collect()] == [(1, 0, 0.5, 1.5), (1, 1, 2.0, 3.0)]
    for fmt in ("parquet", "csv", "json", "orc"):
        pts.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert files.read_points(spark, f"{tmp_path}/{fmt}", fmt).count() == 2
    with pytest.raises(ValueError):
        files.read_points(spark, str(tmp_path), "xml")


def test_release_sink_refuses_true_values(spark, tmp_path):
    hist = spark.createDataFrame([("F", 0, 0, 1.0)], "comp string, row int, col int, cnt double")
    files.write_release(hist, f"{tmp_path}/out")
    assert spark.read.parquet(f"{tmp_path}/out").count() == 1
    with pytest.raises(ValueError):
        files.write_release(hist.withColumn("cnt_true", F.lit(1.0)), f"{tmp_path}/bad")


def test_sql_surface(spark, data):
    sql.register(spark, data, "cv", 3, 20)
    whole = spark.sql("SELECT sum(CASE WHEN comp = 'F' THEN cnt ELSE -cnt END) AS n FROM hist").first()["n"]
    assert whole == spark.sql("SELECT count(DISTINCT traj_id) AS n FROM steps").first()["n"]
    assert spark.sql("SELECT portable_uniform('7|t|3') AS u").first()["u"] == noise.uniform_value(7, "t", 3)
    assert spark.sql("SELECT count(*) AS n FROM range_answers").first()["n"] == 20


def test_stream_with_batches_equals_batch_and_restarts(spark, data, tmp_path):
    events = spark.read.parquet(f"{data}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    for i in range(3):  # three files in time order
        events.where(F.col("event_id") % 3 >= 0).orderBy("ts").where((F.col("event_id") >= 334 * i) & (F.col("event_id") < 334 * (i + 1))).coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    parts = [str(next((tmp_path / "in" / str(i)).glob("*.parquet"))) for i in range(3)]
    (tmp_path / "feed").mkdir()
    sink = live.RunningHistogram(f"{tmp_path}/sink")
    for i, part in enumerate(parts):  # each time the stream starts anew from its checkpoint
        (tmp_path / "feed" / f"{i}.parquet").write_bytes(open(part, "rb").read())
        stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/feed")
        q = live.cells(stream).writeStream.foreachBatch(sink).option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start()
        q.awaitTermination()
    want = live.cells(events).groupBy("row", "col").count()
    got = sink.total(spark)
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()


def test_window_release_adds_up(spark):
    counts = spark.createDataFrame([(0, 0, 0, 5)], "d int, row int, col int, cnt long").withColumn("start", F.lit("2020-01-01").cast("timestamp"))
    shared, book = live.released_windows(counts, 1.0, 4)
    assert book.total() == pytest.approx(1.0) and shared.count() == 1
    assert live.released_windows(counts, 1.0, 4, cut=True)[1].total() == pytest.approx(1.0)
