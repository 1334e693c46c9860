"""Queries of the near-duplicate operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import lines, near_docs
from .cluster import table


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text without the lines that it loses, and their number."""
    return lines.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op8_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_docs.near_components(table(spark, sf_dir, "documents").select("doc_id", "text"), width=4)


QUERIES = {"op1_line_dedup": op1_line_dedup, "op8_near_dedup": op8_near_dedup}
SQL: dict[str, str] = {}
