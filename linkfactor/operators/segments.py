"""Fixed-width segments of sparse rows, padding baselines and their waste."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PAD_ID, PAD_Y = -1, 0.0


def pack(obs: DataFrame, width: int = 16) -> DataFrame:
    """row_id, seg_no, col_ids, ys (each of exactly ``width``) and n_valid, columns in order within a row.

    The window needs one row's cells in one task; its records stay narrow.
    """
    place = F.row_number().over(Window.partitionBy("row_id").orderBy("col_id"))
    cells = obs.withColumn("place", place).withColumn("seg_no", F.floor((F.col("place") - 1) / F.lit(width)).cast("int"))
    grouped = cells.groupBy("row_id", "seg_no").agg(F.array_sort(F.collect_list(F.struct("place", "col_id", "y"))).alias("cells"), F.count(F.lit(1)).cast("int").alias("n_valid"))
    pad = F.lit(width) - F.col("n_valid")
    ids = F.concat(F.transform("cells", lambda c: c["col_id"]), F.array_repeat(F.lit(PAD_ID).cast("bigint"), pad))
    ys = F.concat(F.transform("cells", lambda c: c["y"]), F.array_repeat(F.lit(PAD_Y), pad))
    return grouped.select("row_id", "seg_no", ids.alias("col_ids"), ys.alias("ys"), "n_valid")


def unpack(segments: DataFrame) -> DataFrame:
    cells = segments.select("row_id", F.explode(F.slice(F.arrays_zip("col_ids", "ys"), F.lit(1), F.col("n_valid"))).alias("c"))
    return cells.select("row_id", F.col("c.col_ids").alias("col_id"), F.col("c.ys").alias("y"))


def row_map(segments: DataFrame) -> DataFrame:
    """Which and how many segments belong to a row."""
    return segments.groupBy("row_id").agg(F.count(F.lit(1)).alias("n_segments"))


def pad_to_max(obs: DataFrame) -> DataFrame:
    """Baseline: every row padded to the longest of the table."""
    longest = obs.groupBy("row_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 1
    return pack(obs, int(longest))


def row_lengths(obs: DataFrame) -> DataFrame:
    return obs.groupBy("row_id").agg(F.count(F.lit(1)).alias("n"))


def waste(obs: DataFrame, widths: tuple[int, ...] = (4, 8, 16, 32), batch_rows: int = 64) -> DataFrame:
    """strategy, width, segments, slots, nnz, waste for segments of each width, padding to the longest row, and to the longest of a batch of rows."""
    lengths = row_lengths(obs)
    frames = []
    for w in widths:
        n = F.ceil(F.col("n") / F.lit(w))
        frames.append(lengths.agg(F.sum(n).cast("bigint").alias("segments"), F.sum(n * w).cast("bigint").alias("slots"), F.sum("n").alias("nnz")).withColumns({"strategy": F.lit("segments"), "width": F.lit(w)}))
    whole = lengths.agg(F.count(F.lit(1)).alias("segments"), (F.count(F.lit(1)) * F.max("n")).alias("slots"), F.sum("n").alias("nnz"), F.max("n").cast("int").alias("width"))
    frames.append(whole.withColumn("strategy", F.lit("pad_to_max")))
    batches = lengths.groupBy(F.floor(F.col("row_id") / F.lit(batch_rows)).alias("batch")).agg(F.count(F.lit(1)).alias("rows"), F.max("n").alias("longest"), F.sum("n").alias("n"))
    frames.append(batches.agg(F.sum("rows").alias("segments"), F.sum(F.col("rows") * F.col("longest")).alias("slots"), F.sum("n").alias("nnz")).withColumns({"strategy": F.lit("pad_per_batch"), "width": F.lit(batch_rows)}))
    names = ["strategy", "width", "segments", "slots", "nnz"]
    out = frames[0].select(*names)
    for f in frames[1:]:
        out = out.unionByName(f.select(*names))
    return out.withColumn("waste", F.round(F.lit(1.0) - F.col("nnz") / F.col("slots"), 6))


def segment_system(segments: DataFrame, fac: DataFrame, rank: int = 2) -> DataFrame:
    """Normal systems from segments: partial sums by (row, segment), then by row, so that a long row is shared by many tasks."""
    cells = segments.select("row_id", "seg_no", F.explode(F.slice(F.arrays_zip("col_ids", "ys"), F.lit(1), F.col("n_valid"))).alias("c"))
    gathered = cells.select("row_id", "seg_no", F.col("c.col_ids").alias("col_id"), F.col("c.ys").alias("y")).join(fac, F.col("col_id") == F.col("id"))
    parts = {f"a{i}{j}": F.col(f"f{i}") * F.col(f"f{j}") for i in range(rank) for j in range(i, rank)} | {f"b{i}": F.col("y") * F.col(f"f{i}") for i in range(rank)}
    partial = gathered.groupBy("row_id", "seg_no").agg(*[F.sum(x).alias(k) for k, x in parts.items()], F.count(F.lit(1)).alias("n"))
    return partial.groupBy("row_id").agg(*[F.sum(k).alias(k) for k in parts], F.sum("n").alias("n"))
