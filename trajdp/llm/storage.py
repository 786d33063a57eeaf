"""Intermediate tables in the folder that the driver and all executors share."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from weakref import WeakKeyDictionary

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_PLACES: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()
_LEFT: dict[str, SparkSession] = {}  # what no one has deleted yet


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir. Unset, a local master (tests) gets a temporary folder and any other an error."""
    context = spark.sparkContext
    root = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not root:
        if not (context.master == "local" or context.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="trajdp-")
        context.setCheckpointDir(root)
    return root


def _place(spark: SparkSession, path: str):
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), place


def written(df: DataFrame, label: str, codec: str = "zstd") -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it again: cuts lineage, survives lost executors.

    The table goes with the application, or before by ``discarded``.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/trajdp/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    files, place = _place(spark, path)
    files.deleteOnExit(place)
    _PLACES[out], _LEFT[path] = path, spark
    return out


def discarded(*tables: DataFrame | None) -> None:
    """Delete tables that ``written`` made and nothing reads any more."""
    for table in tables:
        path = _PLACES.pop(table, None) if table is not None else None
        if path:
            _delete(path)


def _delete(path: str) -> None:
    files, place = _place(_LEFT.pop(path), path)
    files.delete(place, True)
    files.cancelDeleteOnExit(place)


def only_kept(docs: DataFrame) -> None:
    """Delete all tables of ``written`` in this session that ``docs`` doesn't read: what was made of them has been written since."""
    read = docs.inputFiles()
    for path, spark in list(_LEFT.items()):
        if spark is docs.sparkSession and not any(path.rsplit("/", 1)[1] in f for f in read):
            _delete(path)


def by_size(rows: DataFrame, groups: DataFrame, on: list[str], size: str) -> DataFrame:
    """Inner join of rows to their groups. No more groups than 4 for each partition hold so many rows that
    they are large; these are broadcast, and their rows stay where they are."""
    large = max(1000, rows.count() // (4 * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    hot = rows.join(F.broadcast(groups.where(F.col(size) >= large)), on)
    cold = rows.join(F.broadcast(groups.where(F.col(size) >= large).select(*on)), on, "left_anti").join(groups.where(F.col(size) < large), on)
    return hot.unionByName(cold)


@contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """No more rows in an Arrow batch than this while the block runs: both sides of the exchange hold a batch of whole
    texts in memory. What the block makes must be written in it."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    if not 0 < int(before) <= rows:
        spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def free_name(columns: list[str], name: str) -> str:
    """``name``, with underscores before it until no column has it, in any case of letters."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def release_memory() -> None:
    """Gives freed memory of a Python worker back to the system: idle workers share the executor's limit."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass
