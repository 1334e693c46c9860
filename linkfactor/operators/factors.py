"""Factor tables: start, storage precision, dictionaries, shards and commits."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import hash_unit
from ..runtime import generation, shared_folder
from .arrays import stored_type, to_matrix, to_stored


def init_vectors(ids: DataFrame, rank: int, seed: int = 42, scale: float | None = None, id_col: str = "id", precision: str = "float64") -> DataFrame:
    """(id, vec): near-Gaussian coordinates (sums of four hashed uniforms) of standard deviation ``scale``, 1/sqrt(rank) by default; a function of id, coordinate and seed alone. The table is as store_table makes it at a precision."""
    scale = rank**-0.5 if scale is None else scale

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dims = np.arange(rank, dtype=np.uint64)
        for batch in batches:
            key = batch.column("id").to_numpy().astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + dims * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(seed)
            total = np.zeros(key.shape)
            for _ in range(4):
                key = (key ^ key >> np.uint64(31)) * np.uint64(0xBF58476D1CE4E5B9)
                key ^= key >> np.uint64(29)
                total += (key >> np.uint64(11)).astype(np.float64) / (1 << 53) - 0.5
            yield pa.RecordBatch.from_arrays([batch.column("id"), to_stored(total * (3**0.5) * scale, precision)], names=["id", "vec"])

    return ids.select(F.col(id_col).cast("bigint").alias("id")).mapInArrow(run, stored_type(precision))


def is_packed(fac: DataFrame) -> bool:
    return dict(fac.dtypes)["vec"] == "binary"


def store_table(fac: DataFrame, rank: int, precision: str) -> DataFrame:
    """The table as it is stored, shuffled and broadcast at a precision: packed numbers of 4 or 2 bytes, or doubles."""
    if precision == "float64" and not is_packed(fac):
        return fac

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("id"), to_stored(to_matrix(batch.column("vec"), rank), precision)], names=["id", "vec"])

    return fac.select("id", "vec").mapInArrow(run, stored_type(precision))


@dataclass
class Held:
    """A stored table in a worker's memory; index has the place of each id where ids are dense, else names are sorted and order tells their places."""

    vectors: np.ndarray
    names: np.ndarray
    order: np.ndarray | None
    index: np.ndarray | None

    def places(self, need: np.ndarray) -> np.ndarray:
        """The place of each id, -1 where it has none."""
        if not len(self.names):
            return np.full(len(need), -1)
        if self.index is not None:
            inside = (need >= 0) & (need < len(self.index))
            return np.where(inside, self.index[np.where(inside, need, 0)], -1)
        at = np.minimum(np.searchsorted(self.names, need), len(self.names) - 1)
        return np.where(self.names[at] == need, self.order[at], -1)

    def of(self, need: np.ndarray) -> np.ndarray:
        """Vectors of the ids, zeros where there are none."""
        at = self.places(need)
        out = np.zeros((len(need), self.vectors.shape[1]))
        out[at >= 0] = self.vectors[at[at >= 0]]
        return out


_HELD: dict[str, Held] = {}


def held_vectors(path: str, rank: int, precision: str, keep: tuple[str | None, ...]) -> Held:
    """The table stored at path, read once a worker; tables that aren't to be kept go first."""
    for old in [p for p in _HELD if p not in keep]:
        del _HELD[old]
    if path not in _HELD:
        _HELD[path] = _read_vectors(path, rank, precision)
    return _HELD[path]


def _parquet_files(path: str, buffer: int = 0) -> list[pq.ParquetFile]:
    """The table's files; buffer: bytes that are read at a time instead of whole columns of a row group."""
    store, root = pafs.FileSystem.from_uri(path.replace("s3a://", "s3://", 1) if "://" in path or path.startswith("file:") else f"file://{path}")
    return [pq.ParquetFile(store.open_input_file(f.path), buffer_size=buffer) for f in store.get_file_info(pafs.FileSelector(root)) if f.base_name.endswith(".parquet")]


def word_ids(lists: DataFrame, path: str) -> DataFrame:
    """(row_id, words) to (row_id, col_ids) by the dictionary (key, id) stored at path, which every task reads once; words that it doesn't hold go, and so do rows without any."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = numbers = None
        for batch in batches:
            if keys is None:
                table = pa.concat_tables([f.read(columns=["key", "id"]) for f in _parquet_files(path)])
                keys, numbers = table.column("key").combine_chunks(), table.column("id").to_numpy()
            words = batch.column("words")
            owner = np.repeat(np.arange(batch.num_rows), words.value_lengths().fill_null(0).to_numpy())
            at = pc.fill_null(pc.index_in(words.flatten(), value_set=keys), -1).to_numpy()
            counts = np.bincount(owner, at >= 0, batch.num_rows).astype(np.int64)
            cols = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]), type=pa.int32()), pa.array(numbers[at[at >= 0]], type=pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("row_id"), cols], names=["row_id", "col_ids"])

    return lists.select("row_id", "words").mapInArrow(run, "row_id long, col_ids array<long>").where(F.size("col_ids") > 0)


def _read_vectors(path: str, rank: int, precision: str) -> Held:
    files = _parquet_files(path)
    n, at = sum(f.metadata.num_rows for f in files), 0
    names, vectors = np.empty(n, dtype=np.int64), np.empty((n, rank), dtype=np.float64 if precision == "float64" else np.float32)
    for f in files:
        for batch in f.iter_batches(1 << 15, columns=["id", "vec"]):
            names[at : at + len(batch)], vectors[at : at + len(batch)] = batch.column("id").to_numpy(), to_matrix(batch.column("vec"), rank)
            at += len(batch)
        f.close()
    return held_table(names, vectors)


def packed_doubles(fac: DataFrame, rank: int) -> DataFrame:
    """The table with the doubles of a vector as bytes, which are read many times as fast as lists; only picked_vectors reads them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, n = np.ascontiguousarray(to_matrix(batch.column("vec"), rank), dtype="<f8"), batch.num_rows
            ends = np.arange(n + 1, dtype=np.int32) * (8 * rank)
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(raw.tobytes())])], names=["id", "vec"])

    return fac.select("id", "vec").mapInArrow(run, "id long, vec binary")


def _unpacked(column: pa.Array, rank: int) -> np.ndarray:
    if pa.types.is_binary(column.type) and len(column):
        ends = np.frombuffer(column.buffers()[1], dtype=np.int32)[column.offset : column.offset + len(column) + 1]
        if ends[-1] - ends[0] == len(column) * rank * 8:
            return np.frombuffer(column.buffers()[2], dtype=np.uint8)[ends[0] : ends[-1]].view("<f8").reshape(-1, rank)
    return to_matrix(column, rank)


#: Rows of a table, and bytes of its file, that are read at a time where vectors are picked from it.
PICK_ROWS, PICK_BUFFER = 1 << 12, 1 << 20


def picked_vectors(path: str, rank: int, precision: str, need: np.ndarray) -> Held:
    """The ids' vectors from the table stored at path, by one pass over it that keeps nothing else."""
    names = np.unique(need)
    vectors, there = np.zeros((len(names), rank), dtype=np.float64 if precision == "float64" else np.float32), np.zeros(len(names), dtype=bool)
    table = held_table(names, vectors)
    for f in _parquet_files(path, PICK_BUFFER):
        for batch in f.iter_batches(PICK_ROWS, columns=["id", "vec"]):
            at = table.places(batch.column("id").to_numpy())
            hit = np.flatnonzero(at >= 0)
            if len(hit):
                vectors[at[hit]], there[at[hit]] = _unpacked(batch.column("vec"), rank)[hit], True
        f.close()
    return table if there.all() else held_table(names[there], vectors[there])


def ordered_vectors(path: str, rank: int, precision: str) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of the table stored at path, in order of id."""
    held = _read_vectors(path, rank, precision)
    if held.order is not None:
        return held.names, held.vectors[held.order]
    order = np.argsort(held.names, kind="stable")
    return held.names[order], held.vectors[order]


def held_table(names: np.ndarray, vectors: np.ndarray) -> Held:
    n = len(names)
    if n and names.min() >= 0 and names.max() < 4 * n + (1 << 20):
        index = np.full(int(names.max()) + 1, -1, dtype=np.int32)
        index[names] = np.arange(n)
        return Held(vectors, names, None, index)
    order = np.argsort(names)
    return Held(vectors, names[order], order, None)


def as_lists(fac: DataFrame, rank: int) -> DataFrame:
    """The table with plain lists of doubles, for column expressions."""
    return store_table(fac, rank, "float64")


def dictionary(keys: DataFrame, column: str) -> DataFrame:
    """(key, id) with ids 0, 1, ... in key order, without a global window: a range sort, then each partition's offset.

    The driver sees one count a partition.
    """
    ordered = keys.select(F.col(column).alias("key")).where("key is not null").distinct().repartitionByRange("key").sortWithinPartitions("key")
    numbered = generation(ordered.select("key", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("mono")), "dictionary")
    counts = {r["part"]: r["n"] for r in numbered.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()}
    offset, bases = 0, {}
    for part in sorted(counts):
        bases[part] = offset
        offset += counts[part]
    if not bases:
        return numbered.select("key", F.lit(0).cast("bigint").alias("id"))
    table = F.create_map(*[F.lit(x) for kv in bases.items() for x in kv])
    return numbered.select("key", (F.element_at(table, F.col("part")) + F.col("mono").bitwiseAND(F.lit((1 << 33) - 1))).alias("id"))


def shard_of(entity, n: int, how: str = "hash", total: int | None = None):
    """Shard of an id: by hash (hot ids spread) or by even ranges of dense ids."""
    return F.pmod(entity, F.lit(n)).cast("int") if how == "hash" else F.floor(entity * F.lit(n) / F.lit(total)).cast("int")


def shard_balance(ids: DataFrame, n: int, id_col: str = "id") -> DataFrame:
    return ids.groupBy(shard_of(F.col(id_col), n).alias("shard")).agg(F.count(F.lit(1)).alias("n"))


def commit(fac: DataFrame, shards: int, label: str = "factors") -> DataFrame:
    """Replace the side's table: rows go to their owner shard and are written as the next generation."""
    return generation(fac.repartition(shards, shard_of(F.col("id"), shards)), label)


def masked_add(solved: DataFrame, shards: int) -> DataFrame:
    """The collective form of the commit, for equivalence tests: all shards see all solved rows, blank the foreign ones and add."""
    spark = solved.sparkSession
    seen = solved.crossJoin(spark.range(shards).withColumnRenamed("id", "shard"))
    mine = shard_of(F.col("id"), shards) == F.col("shard")
    names = [c for c in solved.columns if c != "id"]
    blanked = seen.select("id", *[F.when(mine, F.col(c)).otherwise(F.lit(0.0)).alias(c) for c in names])
    return blanked.groupBy("id").agg(*[F.sum(c).alias(c) for c in names])


def sample_ids(ids: DataFrame, share: float, id_col: str = "id", salt: str = "s") -> DataFrame:
    return ids.where(hash_unit(F.lit(salt), F.col(id_col).cast("string")) < int(share * 2**32))


__all__ = ["as_lists", "commit", "dictionary", "init_vectors", "is_packed", "masked_add", "sample_ids", "shard_balance", "shard_of", "shared_folder", "store_table"]
