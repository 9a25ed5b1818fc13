"""All named queries of the engine and, where SQL can express them, the SQL that recomputes them."""

from __future__ import annotations

from . import graph_queries, measure_queries, relational_queries


def queries() -> dict:
    return graph_queries.QUERIES | measure_queries.QUERIES | relational_queries.QUERIES


def oracle_sql() -> dict:
    return graph_queries.SQL | measure_queries.SQL | relational_queries.SQL
