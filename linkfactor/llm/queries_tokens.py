"""Query of the token-id output."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import tokens
from .cluster import scratch, settle, table

BYTE_BPE = "byte_bpe_50k.json"


def op6_token_ids(spark: SparkSession, sf_dir: str, vocabulary: str | None = None) -> DataFrame:
    """Write all documents as token-id shards, then read each back by its key."""
    if vocabulary is None:
        import public_tokenizers

        vocabulary = public_tokenizers.path(BYTE_BPE)
    folder = scratch(spark, "token-ids")
    manifest = settle(tokens.write_shards(table(spark, sf_dir, "documents").select("doc_id", "text"), folder, vocabulary))
    return tokens.read_shards(manifest, folder).withColumnRenamed("key", "doc_id").select("doc_id", F.col("start"), "n_tokens", "ids_crc32")


QUERIES = {"op6_token_ids": op6_token_ids}
SQL: dict[str, str] = {}
