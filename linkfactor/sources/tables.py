"""Loaders: each returns unique (row, column) cells with a label y."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("row_id"))
    lines = read_table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("col_id"), "l_quantity")
    return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"))


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer by part, 1 for each pair that occurs."""
    return _order_lines(spark, sf_dir).select("row_id", "col_id").distinct().withColumn("y", F.lit(1.0))


def weighted_purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer by part, with the bought quantity as label."""
    return _order_lines(spark, sf_dir).groupBy("row_id", "col_id").agg(F.sum("l_quantity").alias("y"))


def link_observations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page by link target as written, one row a pair."""
    pages = read_table(spark, sf_dir, "pages").select("page_id", "html")
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("path")).where("path != ''").distinct()


def tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id and each distinct lower-cased word of its text."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return docs.select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))).alias("word")).distinct()


def document_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same as one row a document: row_id, words."""
    docs = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), "text")
    words = docs.select("row_id", F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))).alias("words")).where(F.size("words") > 0)
    if docs.groupBy("row_id").count().where("count > 1").limit(1).count():
        words = words.groupBy("row_id").agg(F.array_distinct(F.flatten(F.collect_list("words"))).alias("words"))
    return words


def purchase_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each customer's parts in one row: row_id, col_ids."""
    return _order_lines(spark, sf_dir).select("row_id", "col_id").groupBy("row_id").agg(F.sort_array(F.collect_set("col_id")).alias("col_ids"))


def word_observations(spark: SparkSession, sf_dir: str, min_count: int = 5) -> DataFrame:
    """doc_id and words after one pass of the least-count filter on both sides."""
    from ..operators.graph import min_degree

    return min_degree(tokens(spark, sf_dir), "doc_id", "word", min_count)


def events_as_observations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User by props.k with the number of events as label."""
    events = read_table(spark, sf_dir, "events").select("user_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"))
    return events.where("k is not null").groupBy(F.col("user_id").alias("row_id"), F.col("k").alias("col_id")).agg(F.count(F.lit(1)).cast("double").alias("y"))
