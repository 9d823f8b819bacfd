"""All queries of the vector-search engine, with their SQL for DuckDB."""

from __future__ import annotations

from vecengine.workloads import flows, methods, relational, search, tables, theory  # noqa: F401  modules register their queries
from vecengine.workloads.base import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES"]
