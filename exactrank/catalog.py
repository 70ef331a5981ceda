"""All registered queries and their DuckDB statements, without the document operators'."""

from __future__ import annotations

from exactrank import operator_queries, quantile_queries
from exactrank.streaming import queries as stream_queries

_PARTS = (quantile_queries, operator_queries, stream_queries)


def queries() -> dict:
    return {k: q for part in _PARTS for k, q in part.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for part in _PARTS for k, q in part.SQL.items()}
