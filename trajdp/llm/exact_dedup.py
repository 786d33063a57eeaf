"""Exact duplicates by two passes over a Bloom filter of content hashes.

The first pass counts exactly how often every bit pattern was set in its 64-bit
block; patterns set twice make the filter of possibly repeated hashes. It shuffles
one key for nearly every distinct hash, so unique rows do shuffle once, as keys.
The second pass tests each row against it: only rows that it accepts are
shuffled by content hash, and the others pass as unique without another shuffle.
The filter's size is bounded by ``max_blocks``. With more repeated hashes than
it can hold it accepts more rows, which costs shuffling and never correctness.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import written
from .text import ascii_lower, documents

BITS = 6  # set in a 64-bit block by each hash


def block_pattern(h: Column, h2: Column, blocks: int) -> tuple[Column, Column]:
    """Block number and bit pattern of a hash: a Bloom filter whose bits of a key share one block."""
    block = F.pmod(h, F.lit(blocks))
    one = F.lit(1).cast("long")
    bits = [F.call_function("shiftleft", one, F.pmod(F.shiftright(h2, 6 * i), F.lit(64)).cast("int")) for i in range(BITS)]
    pattern = bits[0]
    for b in bits[1:]:
        pattern = pattern.bitwiseOR(b)
    return block, pattern


def exact_duplicates(docs: DataFrame, max_blocks: int = 1 << 20, rows_per_block: int = 4) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    ``docs`` needs doc_id and text; other columns are ignored. Null text counts
    as empty, so null and empty texts are equal. Texts equal after lower-casing
    A-Z form a group, whose row with the largest doc_id stays (a null doc_id
    is smaller than any other). Rows that repeat both text and the largest
    doc_id can't be told apart and all stay. An empty table gives no rows.
    """
    text = ascii_lower(F.coalesce(F.col("text"), F.lit("")))
    hashed = docs.select("doc_id", F.sha2(text, 256).alias("text_sha256"))
    hashed = hashed.withColumn("h", F.xxhash64("text_sha256")).withColumn("h2", F.xxhash64(F.lit(1), "text_sha256"))
    thin = written(hashed, "dedup-hashes")
    rows = thin.count()
    blocks = 1 << 10
    while blocks < min(max_blocks, rows // rows_per_block):
        blocks *= 2
    block, pattern = block_pattern(F.col("h"), F.col("h2"), blocks)
    thin = thin.withColumn("block", block).withColumn("pattern", pattern)

    repeated = (
        thin.groupBy("block", "pattern").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        .groupBy("block").agg(F.bit_or("pattern").alias("filter"))
    )  # at most ``blocks`` rows of 16 bytes: bounded, so it may be broadcast
    tested = thin.join(F.broadcast(repeated), "block", "left").withColumn(
        "maybe", F.coalesce(F.col("filter").bitwiseAND(F.col("pattern")) == F.col("pattern"), F.lit(False))
    )
    # counts by hash and partition meet first, so that a group of any size is one row for each task
    groups = tested.where("maybe").groupBy("text_sha256").agg(
        F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size")
    ).where("group_size > 1")
    # no more groups than 4 for each partition can be as large as this: their rows are matched where they are
    large = max(1000, rows // (4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    maybe = tested.where("maybe").select("doc_id", "text_sha256")
    hot = maybe.join(F.broadcast(groups.where(F.col("group_size") >= large)), "text_sha256", "left")
    met = hot.where("group_size is not null")
    rest = hot.where("group_size is null").select("doc_id", "text_sha256").join(groups.where(F.col("group_size") < large), "text_sha256", "left")
    again = met.unionByName(rest).select(
        "doc_id", F.coalesce("keep_id", "doc_id").alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"), "text_sha256",
    )
    single = tested.where("not maybe").select(
        "doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), "text_sha256"
    )
    return single.unionByName(again).select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"
    )


def op3_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return exact_duplicates(documents(spark, sf_dir))


ORACLE = """
WITH d AS (
  SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
  FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
