"""Gram matrices as sums of partition products."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrays import to_lists, to_matrix
from .solvers import pack, unpack


def partial_grams(fac: DataFrame, rank: int) -> DataFrame:
    """One packed triangle a partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((rank, rank))
        for batch in batches:
            x = to_matrix(batch.column("vec"), rank)
            total += x.T @ x
        yield pa.RecordBatch.from_arrays([to_lists(pack(total)[None, :])], names=["gram"])

    return fac.select("vec").mapInArrow(run, "gram array<double>")


def gram_cells(fac: DataFrame, rank: int, fan_in: int | None = None) -> DataFrame:
    """pos and g of the packed triangle; with fan_in a middle level sums that many groups of partitions first."""
    parts = partial_grams(fac, rank)
    if fan_in:
        cells = parts.select(F.pmod(F.spark_partition_id(), F.lit(fan_in)).alias("group"), F.posexplode("gram").alias("pos", "g"))
        cells = cells.groupBy("group", "pos").agg(F.sum("g").alias("g"))
    else:
        cells = parts.select(F.posexplode("gram").alias("pos", "g"))
    return cells.groupBy("pos").agg(F.sum("g").alias("g"))


def gram(fac: DataFrame, rank: int) -> np.ndarray:
    """The rank x rank matrix on the driver: rank * (rank + 1) / 2 numbers."""
    packed = np.zeros(rank * (rank + 1) // 2)
    for row in gram_cells(fac, rank).collect():
        packed[row["pos"]] = row["g"]
    return unpack(packed[None, :], rank)[0]


def grams_by(fac: DataFrame, rank: int, n: int, scaled: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> list[np.ndarray]:
    """The matrix of each group (column group, 0 to n - 1) of vectors: n * rank * (rank + 1) / 2 numbers on the driver. scaled: makes of vectors and their ids what is summed."""
    size = rank * (rank + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((n, rank, rank))
        for batch in batches:
            group, x = batch.column("group").to_numpy(), to_matrix(batch.column("vec"), rank)
            x = x if scaled is None else scaled(x, batch.column("id").to_numpy())
            for g in np.unique(group):
                part = x[group == g]
                total[g] += part.T @ part
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n, dtype=np.int32)), to_lists(pack(total))], names=["group", "gram"])

    cells = fac.select("group", "vec", *([] if scaled is None else ["id"])).mapInArrow(run, "group int, gram array<double>").select("group", F.posexplode("gram").alias("pos", "g")).groupBy("group", "pos").agg(F.sum("g").alias("g"))
    packed = np.zeros((n, size))
    for row in cells.collect():
        packed[row["group"], row["pos"]] = row["g"]
    return list(unpack(packed, rank))
