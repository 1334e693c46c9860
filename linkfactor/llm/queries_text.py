"""Queries of the operators on single texts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import media, secrets
from .cluster import scratch, table


def op4_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text stored as WAV under a wrong declared type, sniffed and read back."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    stored = media.store_texts(docs).withColumn("declared", F.lit("image/png"))
    return media.media_digests(media.sniff_media(stored))


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    ledger = secrets.extend_ledger(docs, scratch(spark, "ledger"))
    return secrets.digests(secrets.findings_by_path(docs, ledger, ["doc_id"]))


QUERIES = {"op4_media": op4_media, "op10_secrets": op10_secrets}
SQL: dict[str, str] = {}
