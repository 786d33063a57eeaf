"""Registered queries by name, and SQL that gives the same rows."""

from __future__ import annotations

from . import histograms, privacy, relational, streams


def queries() -> dict:
    return histograms.QUERIES | privacy.QUERIES | relational.QUERIES | streams.QUERIES


def oracle_sql() -> dict[str, str]:
    return histograms.SQL | privacy.SQL | relational.SQL | streams.SQL
