"""Queries over the given tables, module by module, each beside its SQL twin."""

from __future__ import annotations

from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

MODULES = ("model", "strategies", "serving", "graphs", "streams", "surface", "experiments")


def _all(what: str) -> dict:
    return {k: v for m in MODULES for k, v in getattr(import_module(f"{__name__}.{m}"), what).items()}


def queries() -> dict:
    return _all("QUERIES")


def sql() -> dict[str, str]:
    return _all("SQL")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .experiments import recall_against_popularity

    return recall_against_popularity(spark, sf_dir, "documents", rank=8, epochs=4)
