"""Frames that are read more than once, cut from their lineage in the shared checkpoint folder."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir. Unset, a local master (tests) gets a temporary folder and any other an error."""
    context = spark.sparkContext
    if context.getCheckpointDir():
        return context.getCheckpointDir()
    root = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not (context.master == "local" or context.master.startswith("local[")):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="trajdp-")
    context.setCheckpointDir(root)
    return root


def kept(df: DataFrame) -> DataFrame:
    """``df`` computed once and read from the checkpoint folder from then on: plans stay small, lost executors do no harm,
    and noise that was drawn stays the same."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)
