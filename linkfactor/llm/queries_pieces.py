"""Query of the SentencePiece coder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import pieces
from .cluster import table

PIECE_BPE = "piece_bpe_32k.model"


def model_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(PIECE_BPE)


def op2_sentencepiece(spark: SparkSession, sf_dir: str, model_file: str | None = None) -> DataFrame:
    """All documents with merge-dropout, decoded again: doc_id, ids, n_tokens and lossless."""
    return pieces.encode_pieces(table(spark, sf_dir, "documents").select("doc_id", "text"), model_file or model_path())


QUERIES = {"op2_sentencepiece": op2_sentencepiece}
SQL: dict[str, str] = {}
