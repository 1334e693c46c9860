"""SQL twins of the queries, for DuckDB."""

from __future__ import annotations


def oracle_sql() -> dict[str, str]:
    from . import workloads

    return workloads.sql()
