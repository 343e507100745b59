"""All queries of the library itself and their SQL."""

from __future__ import annotations

from codetrees.operators import ops_queries
from codetrees.plans import certificates, core_queries, wide_queries
from codetrees.plans.core_queries import flagship
from codetrees.streaming import stream_queries

__all__ = ["flagship", "oracle_sql", "queries"]


def queries() -> dict:
    return core_queries.Q | certificates.Q | wide_queries.Q | ops_queries.Q | stream_queries.Q


def oracle_sql() -> dict[str, str]:
    return core_queries.SQL | certificates.SQL | wide_queries.SQL | ops_queries.SQL | stream_queries.SQL
