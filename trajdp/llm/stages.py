"""The stages of the training-data pipeline: toxicity, repeated lines, near duplicates, source mixing, packing.

Each stage takes the documents that the one before kept and gives back their
columns; the last gives pieces. Rows with null texts have no words: they pass
every stage but mixing, which samples them with their cell, and are packed as
one token. Rows with a null doc_id are scored, lose repeated lines and are
packed like others; of near duplicates they stay, as nothing tells them apart.
Rows that repeat both doc_id and text stay or go together. Other columns stay, whatever their names. Empty
tables stay empty.

A stage's result must be written before the next stage is called, which deletes
the intermediate tables of those before.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import jaccard_join, line_dedup, mixing, packing, toxicity
from .storage import free_name, only_kept, written

#: Half of the tokens would do for a mix; here nine tenths stay, so that little else than over-weighted cells is thinned.
MIX = mixing.MixParams(rate=0.9)


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are not predicted toxic. Learned from labelled documents outside the held-out fold."""
    only_kept(docs)
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.fit_toxicity(docs, labels)
    predicted = toxicity.score_names(docs.columns)[1]
    return toxicity.toxicity_scores(docs, model, docs.columns).where(F.col(predicted) == 0).select(*docs.columns)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that an earlier one repeats; n_chars follows the text."""
    only_kept(docs)
    out = line_dedup.without_repeated_lines(docs)
    if "n_chars" not in docs.columns:
        return out
    kind = dict(docs.dtypes)["n_chars"]
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(kind))).select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of linked documents the one with the smallest doc_id; documents without shingles stay."""
    only_kept(docs)
    found = jaccard_join.near_duplicates(docs)
    key, text = free_name(docs.columns, "gone_id"), free_name(docs.columns, "gone_hash")
    gone = found.where("n_shingles > 0 and doc_id <> component_id").select(F.col("doc_id").alias(key), F.col("text_hash").alias(text)).distinct()
    return docs.join(gone, (docs["doc_id"] == gone[key]) & (F.xxhash64(docs["text"]) == gone[text]), "left_anti")


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents sampled towards the target weights of sources, languages and topics; at this rate most are missed, see mixing.margin_report."""
    only_kept(docs)
    return mixing.mixed(docs, MIX).where(F.col(mixing.names(docs.columns)["kept"])).select(*docs.columns)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in windows of 2048 tokens."""
    only_kept(docs)
    return packing.packed(docs)


STAGES = [
    ("toxicity", toxicity_stage),
    ("line_dedup", line_stage),
    ("near_duplicates", near_duplicate_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]

#: Scores of a fitted classifier and token ids can't be had in SQL; the tests hold each stage against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents; each stage's table is written and read by the next, and then goes."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = written(docs, f"pipeline-{name}")
    return docs
