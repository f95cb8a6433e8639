"""All queries of the repair engine by name, with the SQL that gives the same rows."""

from __future__ import annotations

from unscramble.plans import operator_queries
from unscramble.plans import queries as method_queries


def queries() -> dict:
    assert operator_queries  # its import adds its queries to the same tables
    return dict(method_queries.QUERIES)


def oracle_sql() -> dict:
    return dict(method_queries.SQL)
