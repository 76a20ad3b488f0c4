"""Registered queries of the sparse product engine and their SQL."""

from sparsetier.queries import accumulation, applications, around, core, measures, streams, workloads  # noqa: F401
from sparsetier.queries.base import oracle_sql, queries

__all__ = ["queries", "oracle_sql"]
