"""Space-filling curves over a square of 2^res cells a side, as column arithmetic."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hilbert_index(df: DataFrame, res: int, row: str = "row", col: str = "col", name: str = "pos") -> DataFrame:
    """``df`` with the cell's place along the Hilbert curve: one step of bit arithmetic for each level.

    At each level the quadrant gives two bits; the lower quadrants then swap the
    axes, the lower right one also mirrors them.
    """
    df = df.withColumn("_x", F.col(col).cast("long")).withColumn("_y", F.col(row).cast("long")).withColumn(name, F.lit(0).cast("long"))
    for level in range(res - 1, -1, -1):
        s = 1 << level
        rx, ry = F.shiftright("_x", level).bitwiseAND(F.lit(1)), F.shiftright("_y", level).bitwiseAND(F.lit(1))
        df = df.withColumns({"_rx": rx, "_ry": ry})
        df = df.withColumn(name, F.col(name) + F.lit(s * s) * (3 * F.col("_rx")).bitwiseXOR(F.col("_ry")))
        mx = F.when((F.col("_ry") == 0) & (F.col("_rx") == 1), F.lit(s - 1) - F.pmod("_x", F.lit(s))).otherwise(F.pmod("_x", F.lit(s)))
        my = F.when((F.col("_ry") == 0) & (F.col("_rx") == 1), F.lit(s - 1) - F.pmod("_y", F.lit(s))).otherwise(F.pmod("_y", F.lit(s)))
        df = df.withColumns({"_mx": mx, "_my": my})
        df = df.withColumns({
            "_x": F.when(F.col("_ry") == 0, F.col("_my")).otherwise(F.col("_mx")),
            "_y": F.when(F.col("_ry") == 0, F.col("_mx")).otherwise(F.col("_my")),
        })
    return df.drop("_x", "_y", "_rx", "_ry", "_mx", "_my")


def hilbert_cell(df: DataFrame, res: int, pos: str = "pos") -> DataFrame:
    """``df`` with the row and col of a place along the Hilbert curve."""
    df = df.withColumns({"_x": F.lit(0).cast("long"), "_y": F.lit(0).cast("long")})
    for level in range(res):
        s = 1 << level
        quadrant = F.shiftright(pos, 2 * level).bitwiseAND(F.lit(3))
        df = df.withColumn("_q", quadrant).withColumns({"_rx": F.shiftright("_q", 1), "_ry": F.col("_q").bitwiseXOR(F.shiftright("_q", 1)).bitwiseAND(F.lit(1))})
        flip = (F.col("_ry") == 0) & (F.col("_rx") == 1)
        df = df.withColumns({"_fx": F.when(flip, F.lit(s - 1) - F.col("_x")).otherwise(F.col("_x")), "_fy": F.when(flip, F.lit(s - 1) - F.col("_y")).otherwise(F.col("_y"))})
        df = df.withColumns({
            "_x": F.when(F.col("_ry") == 0, F.col("_fy")).otherwise(F.col("_fx")) + s * F.col("_rx"),
            "_y": F.when(F.col("_ry") == 0, F.col("_fx")).otherwise(F.col("_fy")) + s * F.col("_ry"),
        })
    return df.withColumns({"row": F.col("_y").cast("int"), "col": F.col("_x").cast("int")}).drop("_x", "_y", "_q", "_rx", "_ry", "_fx", "_fy")


def morton_index(row: Column, col: Column, res: int) -> Column:
    """Place along the Z curve: the bits of row and column interleaved."""
    out = F.lit(0).cast("long")
    for k in range(res):
        bit = lambda c, k=k: F.shiftright(c.cast("long"), k).bitwiseAND(F.lit(1))
        out = out + bit(col) * (1 << (2 * k)) + bit(row) * (1 << (2 * k + 1))
    return out
