"""Queries that made their rows up read a given table in Spark's tasks."""

import pytest

from trajdp import queries

NAMES = ["b_hilbert_decode", "b_hilbert_encode", "b_morton", "b_query_runs", "m_budget_split", "m_generate", "m_geometric", "m_gumbel", "m_laplace", "m_ledger", "m_secure_shape"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table(spark, data, name):
    assert queries.queries()[name](spark, data).inputFiles()
