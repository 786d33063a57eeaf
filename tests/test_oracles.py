"""Every registered query of the library with SQL against DuckDB on the smallest tables, rows compared as multisets."""

import math
from pathlib import Path

import duckdb
import pytest

from trajdp import queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SQL = queries.oracle_sql()
NAMES = [k for k in queries.queries() if k in SQL]


def norm(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6) + 0.0
    return v


def rows(found, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(norm(r[i]) for i in order)) for r in found)


@pytest.mark.parametrize("name", NAMES)
def test_same_rows(spark, data, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{Path(data) / t}.parquet'")
    df = queries.queries()[name](spark, data)
    want = con.sql(SQL[name])
    assert sorted(df.columns) == sorted(want.columns)
    assert rows(df.collect(), df.columns) == rows(want.fetchall(), want.columns)
