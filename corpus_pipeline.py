"""A corpus pipeline of five stages: from raw documents to token ids.

Each stage takes (spark, docs, sf_dir) and returns the documents that it leaves, with the
columns of the table ``documents``; the last returns token ids. ``run`` chains them through
Parquet in the shared folder, so a lost executor costs a task and not the chain.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from linkfactor.llm import lines, mixing, near_docs, pieces, toxicity
from linkfactor.llm.cluster import drop, scratch, table
from linkfactor.llm.queries_pieces import model_path

#: No stage but mixing can be put in SQL, so the chain is tested against plain versions.
ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity score of 0.5 or more go; the model learns from the labelled rows among docs."""
    return toxicity.drop_toxic(docs, toxicity.fit_toxicity(docs, table(spark, sf_dir, "labels")))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One line of each group of equal or similar lines stays; all documents stay."""
    return lines.dedup_lines(docs).drop("lines_lost")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays; sets of five words, similarity 0.8."""
    return near_docs.drop_near_copies(docs, width=5)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All sources get equal weight; documents are repeated or left out by their Poisson counts."""
    return mixing.mix_sources(docs).drop("copy", "shuffle_key")


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids with merge-dropout of every document that is left."""
    return pieces.encode_pieces(docs, model_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", dedup_lines),
    ("near_dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("sentencepiece", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        path = scratch(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before:  # the stage after it is written by now
            drop(spark, before)
        before = path
    return STAGES[-1][1](spark, docs, sf_dir)
