"""The methods from SQL: views of a source's points, steps, histogram and queries, and functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .operators import answering, histogram, walks, workload
from .operators.relational import CellsOfSegment, QuadAncestors, hilbert_places
from .plans.dense import collected
from .sources import trajectories


def register(spark: SparkSession, sf_dir: str, source: str = "li", res: int = 4, m: int = 200, loops: str = "erase") -> None:
    """Views points, steps, hist, queries and range_answers; functions portable_uniform, laplace_noise,
    range_count (a rectangle's answer from summed-area tables of hist), hilbert_index, cells_of_segment and quad_ancestors."""
    points = trajectories.points(spark, sf_dir, source)
    steps = walks.walk_steps(points, trajectories.box(spark, sf_dir, source, res), policy=loops)
    hist, queries = histogram.build(steps), workload.random_rectangles(spark, 1 << res, m)
    for name, df in (("points", points), ("steps", steps), ("hist", hist), ("queries", queries), ("range_answers", answering.from_hist(hist, queries))):
        df.createOrReplaceTempView(name)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION portable_uniform(key STRING) RETURNS DOUBLE RETURN (CAST(conv(substring(md5(key), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION laplace_noise(u DOUBLE, scale DOUBLE) RETURNS DOUBLE RETURN -scale * signum(u - 0.5D) * ln(1 - 2 * abs(u - 0.5D))")
    spark.udtf.register("cells_of_segment", CellsOfSegment)
    spark.udtf.register("quad_ancestors", QuadAncestors)
    spark.udf.register("hilbert_index", hilbert_places)
    table = collected(histogram.densify(hist, 1 << res), 1 << res)  # bounded by the grid; larger ones have range_answers

    @F.pandas_udf("double")
    def range_count(r1: pd.Series, r2: pd.Series, c1: pd.Series, c2: pd.Series) -> pd.Series:
        return pd.Series(table.answers(np.stack([r1, r2, c1, c2], axis=1).astype(np.int64)))

    spark.udf.register("range_count", range_count)
