"""Streams of observations: sources, sinks to tables, windows, joins and fold-in against frozen factors."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import smallrank
from ..runtime import scratch


def _typed(frame: DataFrame) -> DataFrame:
    """Event time as a timestamp with a zone (watermarks need one), and the column key."""
    return frame.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("bigint").alias("k"))


def event_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", files_per_batch: int | None = None) -> DataFrame:
    schema = spark.read.parquet(f"{folder}/{pattern}").schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", pattern)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return _typed(reader.parquet(folder))


def batch_twin(spark: SparkSession, folder: str) -> DataFrame:
    return _typed(spark.read.parquet(f"{folder}/events.parquet"))


def run_available(stream: DataFrame, mode: str = "append", change: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Run a stream over all that is there and return its result as a table.

    In complete mode a batch replaces the result, in append mode it adds to it. Batches are written under their number, so one that runs again overwrites itself.
    """
    spark, out = stream.sparkSession, scratch(stream.sparkSession, "stream")
    seen: list[int] = []
    kept: list = []

    def sink(frame: DataFrame, number: int) -> None:
        made = change(frame) if change else frame
        made.write.mode("overwrite").parquet(f"{out}/batch={number}")
        seen.append(number)
        kept[:] = [made.schema]

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", scratch(spark, "stream-state")).trigger(availableNow=True).foreachBatch(sink).start()
    query.awaitTermination()
    if not seen:
        return spark.createDataFrame([], stream.schema)
    names = kept[0].names
    if mode == "complete":
        return spark.read.schema(kept[0]).parquet(f"{out}/batch={max(seen)}").select(*names)
    return spark.read.schema(kept[0]).parquet(*[f"{out}/batch={n}" for n in sorted(set(seen))]).select(*names)


def tumbling(events: DataFrame, size: str = "1 day", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sliding(events: DataFrame, size: str = "1 day", step: str = "12 hours", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size, step)).agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def deduplicated(events: DataFrame, late: str = "60 days") -> DataFrame:
    """The first event of each (user, key) within the watermark."""
    return events.where("k is not null").withWatermark("ts", late).dropDuplicatesWithinWatermark(["user_id", "k"]).select("user_id", "k")


def interval_join(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Events of the left followed by one of the same user on the right within the time."""
    a = left.select(F.col("event_id").alias("left_id"), F.col("user_id").alias("left_user"), F.col("ts").alias("left_ts")).withWatermark("left_ts", late)
    b = right.select(F.col("event_id").alias("right_id"), F.col("user_id").alias("right_user"), F.col("ts").alias("right_ts")).withWatermark("right_ts", late)
    soon = (F.col("right_ts") >= F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, (F.col("left_user") == F.col("right_user")) & soon).select("left_id", "right_id")


def normal_systems(events: DataFrame, fac: DataFrame) -> DataFrame:
    """Running (A, b) of every user against frozen column factors (a stream-static join); rank 2."""
    obs = events.where("k is not null").select(F.col("user_id").alias("row_id"), F.col("k").alias("col_id"), F.lit(1.0).alias("y"))
    return smallrank.normal_system(obs, fac, 2)


def fold_in_change(gram: DataFrame, reg: float, unobserved: float) -> Callable[[DataFrame], DataFrame]:
    """Solves the systems of a batch."""

    def change(systems: DataFrame) -> DataFrame:
        solved = smallrank.add_ridge(systems, gram, reg, unobserved)
        return solved.select(F.col("row_id").alias("id"), *[x.alias(f"f{k}") for k, x in enumerate(smallrank.solve2())])

    return change


def counts_with_state(events: DataFrame) -> DataFrame:
    """Users' event counts and value sums kept in an operator's own state, in update mode."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for part in parts:
            n, total = n + len(part), total + float(part["value"].fillna(0.0).sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, total double", "n long, total double", "update", "NoTimeout")
