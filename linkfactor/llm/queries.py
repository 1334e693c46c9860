"""All queries of the subpackage; __spark_entry__ adds them where the subpackage is installed."""

from __future__ import annotations

from importlib import import_module

_MODULES = ("queries_near", "queries_pieces", "queries_rules", "queries_text", "queries_native", "queries_tokens")


def queries() -> dict:
    return {k: v for m in _MODULES for k, v in import_module(f"{__package__}.{m}").QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in _MODULES for k, v in import_module(f"{__package__}.{m}").SQL.items()}
