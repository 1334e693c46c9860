"""One half-step of the array path: gather the frozen side's vectors, build and solve each row's system.

Ways to gather: ``broadcast`` (the whole frozen table, within the limit), ``shuffle`` (a
vector for each observation), ``routed`` (a vector once for each block of rows that needs
it), ``hot_cold`` (the most used columns broadcast, the others shuffled), ``masked_sum``
(the collective form, for tests) and ``partial_stats`` (no vectors move; partial systems
are summed by row), ``held`` (every worker reads the frozen side's stored table from the
shared folder once a generation, and rows come as stored records, so nothing is shuffled or
sent through the driver), ``picked`` (the same for a table that no worker can hold: of it a
worker keeps the vectors of the rows at hand, by a pass over the table). All give the same factors. Vectors are stored, shuffled and broadcast
as they are: packed in 2 or 4 bytes a number at low precisions.

Rows stream through the solver sorted by row. Their observations are laid into segments of
``segment_width`` places, padded with zero vectors, so that a batch of rows of any lengths is
one dense batch of products; a row's segments are summed, across Arrow batches too. Memory is
one group of systems. Rows with more observations than ``heavy_row`` are summed in parts by
many tasks first.

Systems of several models can be solved in one job (``base`` with a matrix for each): the
ids of a model's rows and columns then carry its number above POINT_BITS.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import suppress
from dataclasses import dataclass
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import FactorConfig
from ..runtime import generation_at
from .arrays import ids, rounded_to, stored_type, to_lists, to_matrix, to_stored
from .factors import held_table, held_vectors, is_packed, packed_doubles, picked_vectors, shard_of, store_table
from .solvers import bf16_round, pack, solve_batch, solve_cg_free, unpack

POINT_BITS = 40


def bases_of(base: np.ndarray, names: np.ndarray) -> np.ndarray:
    """The matrix that is added to the systems of the named rows: the same for all, or their model's."""
    return base if base.ndim == 2 else base[names >> POINT_BITS]


def solved_type(precision: str) -> str:
    return f"{stored_type(precision)}, err double"


@dataclass
class Systems:
    """Normal systems of rows: names, sums of outer products, sums of label times vector, sums of squared labels, counts, and vectors to start from."""

    names: np.ndarray
    a: np.ndarray
    b: np.ndarray
    yy: np.ndarray
    n: np.ndarray
    start: np.ndarray

    def parts(self) -> tuple[np.ndarray, ...]:
        return self.names, self.a, self.b, self.yy, self.n, self.start

    def take(self, which) -> Systems:
        return Systems(*(x[which] for x in self.parts()))

    def add_first(self, other: Systems) -> None:
        """Add another part of the first row."""
        for mine, theirs in zip(self.parts()[1:], other.parts()[1:], strict=True):
            mine[0] += theirs[0]


class RowSolver:
    """Collects systems and solves them in groups of bounded bytes; ``err`` is the squared error of a row's own observations."""

    def __init__(self, base: np.ndarray, cfg: FactorConfig) -> None:
        self.cfg, self.base = cfg, base
        self.kind = np.float64 if cfg.precision == "float64" else np.float32
        self.group = system_group(cfg)
        self.held: list[Systems] = []
        self.count = 0

    def add(self, found: Systems) -> Iterator[pa.RecordBatch]:
        """Take systems, and give back solutions whenever a group is full."""
        for at in range(0, len(found.names), self.group):
            part = found.take(slice(at, at + self.group))
            self.held.append(part)
            self.count += len(part.names)
            if self.count >= self.group:
                yield self.drain()

    def drain(self) -> pa.RecordBatch:
        names, a, b, yy, _, start = (np.concatenate(x) for x in zip(*(h.parts() for h in self.held), strict=True))
        whole = a + bases_of(self.base, names)
        right = b
        if self.cfg.precision == "bf16_all":
            whole, right = bf16_round(whole), bf16_round(b)
        x = self.solve(whole.astype(self.kind), right.astype(self.kind), start.astype(self.kind))
        self.held, self.count = [], 0
        kept = rounded_to(x, self.cfg.precision).astype(np.float64)
        err = yy - 2 * np.einsum("nd,nd->n", kept, b) + np.einsum("nd,nde,ne->n", kept, a, kept, optimize=True)
        return solved_batch(names, kept, err, self.cfg.precision)

    def solve(self, a: np.ndarray, b: np.ndarray, start: np.ndarray) -> np.ndarray:
        """Solutions of a group. Rounding to 16 bits can make a system singular; with ``bf16_all`` its row then has no numbers, which is the collapse that this mode is there to show."""
        kind, steps, tol = self.cfg.chosen_solver(), self.cfg.iterations(), self.cfg.cg_tol
        try:
            return solve_batch(a, b, kind, steps, tol, start)
        except np.linalg.LinAlgError:
            if self.cfg.precision != "bf16_all":
                raise
        x = np.full_like(b, np.nan)
        for i in range(len(a)):
            with suppress(np.linalg.LinAlgError):
                x[i] = solve_batch(a[i : i + 1], b[i : i + 1], kind, steps, tol, start[i : i + 1])[0]
        return x

    def rest(self) -> Iterator[pa.RecordBatch]:
        if self.count:
            yield self.drain()


def system_group(cfg: FactorConfig) -> int:
    """Rows whose matrices, with the copies that solving makes of them, are within the batch's bytes."""
    return max(1, cfg.solve_batch_bytes // (4 * cfg.rank * cfg.rank * 8))


def solved_batch(names: np.ndarray, x: np.ndarray, err: np.ndarray, precision: str) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(names, type=pa.int64()), to_stored(x, precision), pa.array(np.maximum(err, 0.0), type=pa.float64())], names=["id", "vec", "err"])


def dense_systems(names: np.ndarray, y: np.ndarray, x: np.ndarray, width: int, limit: int) -> Systems:
    """Systems of observations sorted by row.

    Each row's observations fill segments of ``width`` places; the last one is padded with
    zeros. The segments of all rows are one batched product, taken in portions of ``limit`` bytes.
    """
    rank = x.shape[1]
    starts = np.flatnonzero(np.concatenate([[True], names[1:] != names[:-1]]))
    counts = np.diff(np.append(starts, len(names)))
    segments = -(-counts // width)
    # Place of each observation among the padded ones.
    lead = np.cumsum(segments) - segments
    place = np.arange(len(names)) + np.repeat(lead * width - starts, counts)
    total = int(segments.sum())
    a, b = np.zeros((len(starts), rank, rank)), np.zeros((len(starts), rank))
    owner = np.repeat(np.arange(len(starts)), segments)
    portion = max(1, limit // (8 * rank * max(rank, width)))
    for at in range(0, total, portion):
        until = min(total, at + portion)
        lo, hi = np.searchsorted(place, (at * width, until * width))
        dense, label = np.zeros(((until - at) * width, rank)), np.zeros((until - at) * width)
        dense[place[lo:hi] - at * width], label[place[lo:hi] - at * width] = x[lo:hi], y[lo:hi]
        dense, label = dense.reshape(until - at, width, rank), label.reshape(until - at, 1, width)
        rows, first = np.unique(owner[at:until], return_index=True)
        a[rows] += np.add.reduceat(np.swapaxes(dense, 1, 2) @ dense, first, axis=0)
        b[rows] += np.add.reduceat((label @ dense)[:, 0, :], first, axis=0)
    return Systems(names[starts], a, b, np.add.reduceat(y * y, starts), counts, np.zeros_like(b))


def _systems(batches: Iterator[pa.RecordBatch], cfg: FactorConfig) -> Iterator[Systems]:
    """Systems of gathered rows sorted by row; each row comes once, however many Arrow batches hold it.

    A gathered row without a label is the row's start vector.
    """
    rank, group, open_row = cfg.rank, system_group(cfg), None
    for batch in batches:
        every, x = ids(batch.column("row_id")), to_matrix(batch.column("vec"), rank)
        y = batch.column("y").to_numpy(zero_copy_only=False).astype(np.float64)
        edges = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]])) if len(every) else []
        for k in range(0, len(edges), group):
            part = slice(edges[k], edges[k + group] if k + group < len(edges) else len(every))
            rows, begins = every[edges[k : k + group]], np.isnan(y[part])
            found = Systems(rows, np.zeros((len(rows), rank, rank)), np.zeros((len(rows), rank)), np.zeros(len(rows)), np.zeros(len(rows), dtype=np.int64), np.zeros((len(rows), rank)))
            if not begins.all():
                known = dense_systems(every[part][~begins], y[part][~begins], x[part][~begins], cfg.segment_width, cfg.solve_batch_bytes)
                at = np.searchsorted(rows, known.names)
                for mine, theirs in zip(found.parts()[1:5], known.parts()[1:5], strict=True):
                    mine[at] = theirs
            found.start[np.searchsorted(rows, every[part][begins])] = x[part][begins]
            if open_row is not None:
                if open_row.names[0] == rows[0]:
                    found.add_first(open_row)
                else:
                    yield open_row
            if len(rows) > 1:
                yield found.take(slice(None, -1))
            open_row = found.take(slice(-1, None))
    if open_row is not None:
        yield open_row


def dealt(frame: DataFrame, cfg: FactorConfig) -> DataFrame:
    """Whole rows to one task each."""
    return frame.repartition(*([cfg.blocks] if cfg.blocks else []), F.col("row_id"))


def solve_batches(batches: Iterator[pa.RecordBatch], base: np.ndarray, cfg: FactorConfig) -> Iterator[pa.RecordBatch]:
    """Solutions of gathered batches (row_id, y, vec) that are sorted by row."""
    if cfg.chosen_solver() == "cg_free":
        yield from _solved_free(batches, base, cfg)
        return
    solver = RowSolver(base, cfg)
    for found in _systems(batches, cfg):
        yield from solver.add(found.take(found.n > 0))
    yield from solver.rest()


def _solved_free(batches: Iterator[pa.RecordBatch], base: np.ndarray, cfg: FactorConfig) -> Iterator[pa.RecordBatch]:
    """Matrix-free: whole rows are kept back until a batch ends between two rows."""
    rest: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        names, y, x = ids(batch.column("row_id")), batch.column("y").to_numpy(zero_copy_only=False).astype(np.float64), to_matrix(batch.column("vec"), cfg.rank)
        cut = int(np.searchsorted(names, names[-1]))
        if cut or (rest and rest[-1][0][-1] != names[0]):
            ready = [*rest, (names[:cut], y[:cut], x[:cut])]
            yield solve_free([p for p in ready if len(p[0])], base, cfg)
            rest = []
        rest.append((names[cut:], y[cut:], x[cut:]))
    if rest:
        yield solve_free(rest, base, cfg)


def solve_gathered(gathered: DataFrame, base: np.ndarray, cfg: FactorConfig) -> DataFrame:
    """gathered (row_id, y, vec) to (id, vec, err); base is unobserved * Gram + reg * identity. A row without a label holds the start of conjugate gradients."""
    sorted_rows = dealt(gathered.select("row_id", "y", "vec"), cfg).sortWithinPartitions("row_id")
    return sorted_rows.mapInArrow(lambda batches: solve_batches(batches, base, cfg), solved_type(cfg.precision))


def met_batch(rows: np.ndarray, y: np.ndarray, at: np.ndarray, vectors: np.ndarray) -> pa.RecordBatch:
    """Cells whose vectors are at the places ``at`` of a table; those without one (-1) go."""
    known = at >= 0
    return pa.RecordBatch.from_arrays([pa.array(rows[known], type=pa.int64()), pa.array(y[known], type=pa.float64()), to_lists(vectors[at[known]].astype(np.float64, copy=False))], names=["row_id", "y", "vec"])


#: Bytes of vectors in one broadcast of a part of a table: the driver holds one part at a time while it sends them.
SENT_BYTES = 32 << 20


def sent_parts(fac: DataFrame, cfg: FactorConfig) -> list:
    """The table as broadcasts to the Python workers, cut by pmod(id, number of parts). A relation of all rows in the driver's heap would need several times the table's bytes."""
    size = fac.count() * cfg.rank * cfg.bytes_per_number
    if size > cfg.broadcast_limit:
        raise ValueError(f"a table of {size} bytes is beyond the broadcast limit of {cfg.broadcast_limit}")
    n, out = max(1, ceil(size / SENT_BYTES)), []
    for k in range(n):
        part = fac.where(F.pmod("id", F.lit(n)) == k).select("id", "vec").toArrow()
        names = ids(part.column("id"))
        out.append(fac.sparkSession.sparkContext.broadcast(held_table(names, to_matrix(part.column("vec"), cfg.rank).astype(np.float64 if cfg.precision == "float64" else np.float32, copy=False))))
    return out


def refit_sent(obs: DataFrame, fac: DataFrame, base: np.ndarray, cfg: FactorConfig) -> DataFrame:
    """Half-step against a broadcast table: the narrow observations are dealt and sorted, and meet their vectors in the worker that solves them."""
    parts = sent_parts(fac, cfg)

    def met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, need, y = ids(batch.column("row_id")), ids(batch.column("col_id")), batch.column("y").to_numpy(zero_copy_only=False)
            x, known = np.zeros((len(rows), cfg.rank)), np.zeros(len(rows), dtype=bool)
            for k, part in enumerate(parts):
                mine = np.flatnonzero(need % len(parts) == k)
                at = part.value.places(need[mine])
                x[mine[at >= 0]], known[mine] = part.value.vectors[at[at >= 0]], at >= 0
            yield met_batch(rows, y, np.where(known, np.arange(len(rows)), -1), x)

    narrow = dealt(obs.select("row_id", "col_id", "y"), cfg).sortWithinPartitions("row_id")
    return narrow.mapInArrow(lambda batches: solve_batches(met(batches), base, cfg), solved_type(cfg.precision))


def solve_free(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]], base: np.ndarray, cfg: FactorConfig) -> pa.RecordBatch:
    """Solutions of whole rows (ascending names, labels, vectors) without their matrices; a row without a label is a start."""
    names, y, x = (np.concatenate([p[k] for p in parts]) for k in range(3))
    begins = np.isnan(y)
    every, owner = np.unique(names[~begins], return_inverse=True)
    start = np.zeros((len(every), cfg.rank))
    if len(every):
        at = np.minimum(np.searchsorted(every, names[begins]), len(every) - 1)
        same = every[at] == names[begins]
        start[at[same]] = x[begins][same]
    kind = np.float64 if cfg.precision == "float64" else np.float32
    out = solve_cg_free(x[~begins].astype(kind), owner, y[~begins].astype(kind), bases_of(base, every).astype(kind), len(every), cfg.iterations(), cfg.cg_tol, start.astype(kind))
    kept = rounded_to(out, cfg.precision).astype(np.float64)
    miss = y[~begins] - np.einsum("nd,nd->n", x[~begins], kept[owner])
    return solved_batch(every, kept, np.bincount(owner, miss * miss, minlength=len(every)), cfg.precision)


def partial_batch(found: Systems) -> pa.RecordBatch:
    stats = np.concatenate([pack(found.a), found.b, found.yy[:, None]], axis=1)
    return pa.RecordBatch.from_arrays([pa.array(found.names, type=pa.int64()), to_lists(stats), pa.array(found.n, type=pa.int64())], names=["row_id", "stats", "n"])


def partial_sums(gathered: DataFrame, cfg: FactorConfig) -> DataFrame:
    """(row_id, stats, n) once for each row and partition: packed triangle, the right side, and the sum of squared labels. Nothing is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for found in _systems(batches, cfg):
            yield partial_batch(found)

    return gathered.select("row_id", "y", "vec").sortWithinPartitions("row_id").mapInArrow(run, "row_id long, stats array<double>, n long")


def solve_partial(parts: DataFrame, base: np.ndarray, cfg: FactorConfig) -> DataFrame:
    """Sum partial systems by row and solve. Where only sums are at hand, matrix-free conjugate gradients run on the summed matrices."""
    size = cfg.rank * (cfg.rank + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        solver, group, open_name, total = RowSolver(base, cfg), system_group(cfg), None, None

        def systems(names: np.ndarray, stats: np.ndarray) -> Iterator[pa.RecordBatch]:
            for at in range(0, len(names), group):
                part = stats[at : at + group]
                b = part[:, size : size + cfg.rank]
                yield from solver.add(Systems(names[at : at + group], unpack(part[:, :size], cfg.rank), b, part[:, -1], np.ones(len(part), dtype=np.int64), np.zeros_like(b)))

        for batch in batches:
            if not batch.num_rows:
                continue
            names, stats = ids(batch.column("row_id")), to_matrix(batch.column("stats"), size + cfg.rank + 1)
            starts = np.flatnonzero(np.concatenate([[True], names[1:] != names[:-1]]))
            rows, sums = names[starts], np.add.reduceat(stats, starts, axis=0)
            if open_name is not None:
                if open_name[0] == rows[0]:
                    sums[0] += total[0]
                else:
                    yield from systems(open_name, total)
            yield from systems(rows[:-1], sums[:-1])
            open_name, total = rows[-1:], sums[-1:]
        if open_name is not None:
            yield from systems(open_name, total)
        yield from solver.rest()

    return parts.repartition("row_id").sortWithinPartitions("row_id").mapInArrow(run, solved_type(cfg.precision))


def hot_columns(obs: DataFrame, cfg: FactorConfig) -> DataFrame:
    """hot_id of the most used columns, as many as may be broadcast; the same for all epochs."""
    rows = min(cfg.hot_columns, max(1, cfg.broadcast_limit // (cfg.rank * cfg.bytes_per_number)))
    return obs.groupBy("col_id").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "col_id").limit(rows).select(F.col("col_id").alias("hot_id"))


def gather(obs: DataFrame, fac: DataFrame, cfg: FactorConfig, how: str, hot: DataFrame | None = None) -> DataFrame:
    """obs with each column's vector: row_id, col_id, y, vec. hot: the columns to broadcast, where they are known."""
    table = fac.select(F.col("id").alias("vec_id"), "vec")
    on = F.col("col_id") == F.col("vec_id")
    if how == "broadcast":
        size = fac.count() * cfg.rank * cfg.bytes_per_number
        if size > cfg.broadcast_limit:
            raise ValueError(f"a table of {size} bytes is beyond the broadcast limit of {cfg.broadcast_limit}")
        joined = obs.join(F.broadcast(table), on)
    elif how == "shuffle":
        joined = obs.join(table.hint("merge"), on)
    elif how == "hot_cold":
        hot = F.broadcast(hot_columns(obs, cfg) if hot is None else hot)
        marked = obs.join(hot, F.col("col_id") == F.col("hot_id"), "left")
        near = F.broadcast(table.join(hot, F.col("vec_id") == F.col("hot_id"), "left_semi"))
        some = marked.where("hot_id is not null").drop("hot_id").join(near, on)
        joined = some.unionByName(marked.where("hot_id is null").drop("hot_id").join(table.hint("merge"), on))
    elif how == "masked_sum":
        shards = cfg.blocks or 4
        asked = obs.crossJoin(obs.sparkSession.range(shards).withColumnRenamed("id", "shard"))
        held = table.withColumn("held_by", shard_of(F.col("vec_id"), shards))
        seen = asked.join(held, on & (F.col("shard") == F.col("held_by")), "left")
        if is_packed(fac):
            raise ValueError("the collective form adds doubles")
        cells = [F.sum(F.coalesce(F.get("vec", k), F.lit(0.0))).alias(f"v{k}") for k in range(cfg.rank)]
        return seen.groupBy("row_id", "col_id", "y").agg(*cells).select("row_id", "col_id", "y", F.array(*[f"v{k}" for k in range(cfg.rank)]).alias("vec"))
    else:
        raise ValueError(f"{how!r} doesn't gather vectors")
    return joined.select("row_id", "col_id", "y", "vec")


def row_block(blocks: int):
    return F.pmod(F.col("row_id"), F.lit(blocks)).cast("int").alias("row_block")


def routing(obs: DataFrame, blocks: int) -> DataFrame:
    """(row_block, col_id): which vectors each block of rows needs; the same for all epochs."""
    return obs.select(row_block(blocks), "col_id").distinct()


def blocks_for(cells: int, vectors: int, cfg: FactorConfig, at_least: int = 1) -> int:
    """Blocks of rows whose observations and vectors stay within block_bytes on average."""
    return cfg.blocks or max(at_least, ceil((24 * cells + vectors * cfg.rank * 8) / cfg.block_bytes))


def refit_routed(obs: DataFrame, fac: DataFrame, base: np.ndarray, cfg: FactorConfig, routes: DataFrame | None = None, blocks: int | None = None) -> DataFrame:
    """Each vector travels once to every block that needs it; a block's vectors come before its cells, which stream, so a worker holds the vectors of one block.

    routes and the number of blocks they were made for are given where they are stored; heavy rows are to be taken out before.
    """
    if blocks is None:
        blocks = cfg.blocks or int(obs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    routes = routing(obs, blocks) if routes is None else routes
    none = lambda kind, name: F.lit(None).cast(kind).alias(name)
    sent = routes.join(fac.select(F.col("id").alias("vec_id"), "vec"), F.col("col_id") == F.col("vec_id")).select("row_block", none("bigint", "row_id"), F.col("vec_id").alias("col_id"), none("double", "y"), "vec")
    mine = obs.select(row_block(blocks), "row_id", "col_id", "y", none(fac.schema["vec"].dataType, "vec"))
    # A task for each block, so that one number is sorted by.
    both = sent.unionByName(mine).repartitionById(blocks, F.col("row_block")).sortWithinPartitions(F.col("row_id").asc_nulls_first())

    def met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, vectors, table = [np.zeros(0, dtype=np.int64)], [np.zeros((0, cfg.rank))], None
        for batch in batches:
            n = batch.column("row_id").null_count
            if n:
                names.append(ids(batch.column("col_id").slice(0, n)))
                vectors.append(to_matrix(batch.column("vec").slice(0, n), cfg.rank))
            if n == batch.num_rows:
                continue
            if table is None:
                table = held_table(np.concatenate(names), np.concatenate(vectors))
                names, vectors = [], []
            cells = batch.slice(n)
            yield met_batch(ids(cells.column("row_id")), cells.column("y").to_numpy(zero_copy_only=False), table.places(ids(cells.column("col_id"))), table.vectors)

    return both.mapInArrow(lambda batches: solve_batches(met(batches), base, cfg), solved_type(cfg.precision))


#: Records into which a heavy row's observations are dealt.
PIECES = 64


#: A row with its observations: their number, the packed ids of their columns (4 or 8 bytes each), and their labels as doubles, null where all are 1.
RECORD = "row_id long, n int, cells binary, labels binary"


def record_batch(names: np.ndarray, counts: np.ndarray, cells: np.ndarray, labels: np.ndarray | None) -> pa.RecordBatch:
    """Records of so many cells each, which lie one after the other."""
    small = not len(cells) or (cells.min() >= 0 and cells.max() < 1 << 31)
    cells, ends = cells.astype("<i4" if small else "<i8"), np.concatenate([[0], np.cumsum(counts)])
    blobs = lambda x: pa.Array.from_buffers(pa.binary(), len(names), [None, pa.py_buffer((ends * x.itemsize).astype(np.int32).tobytes()), pa.py_buffer(x.tobytes())])
    same = labels is None or (labels == 1.0).all()
    return pa.RecordBatch.from_arrays([pa.array(names, type=pa.int64()), pa.array(counts, type=pa.int32()), blobs(cells), pa.nulls(len(names), pa.binary()) if same else blobs(labels.astype("<f8"))], names=["row_id", "n", "cells", "labels"])


def raw_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a binary column one after the other, and where each value ends."""
    if not len(column):
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int32)
    ends = np.frombuffer(column.buffers()[1], dtype=np.int32)[column.offset : column.offset + len(column) + 1]
    return (np.frombuffer(column.buffers()[2], dtype=np.uint8)[ends[0] : ends[-1]] if ends[-1] > ends[0] else np.zeros(0, dtype=np.uint8)), ends - ends[0]


def cells_of(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
    """Names, counts, column ids and labels (None where all are 1) of a batch of records."""
    names, counts = ids(batch.column("row_id")), batch.column("n").to_numpy().astype(np.int64)
    raw, ends = raw_bytes(batch.column("cells"))
    width = np.diff(ends) // np.maximum(counts, 1)
    if (width == width[:1]).all():
        cells = raw.view("<i4" if len(width) and width[0] == 4 else "<i8").astype(np.int64)
    else:
        cells = np.concatenate([raw[lo:hi].view("<i4" if w == 4 else "<i8").astype(np.int64) for lo, hi, w in zip(ends[:-1], ends[1:], width, strict=True)])
    column = batch.column("labels")
    if column.null_count == len(column):
        return names, counts, cells, None
    labels, there = np.ones(len(cells)), np.repeat(column.is_valid().to_numpy(zero_copy_only=False), counts)
    labels[there] = raw_bytes(column)[0].view("<f8")
    return names, counts, cells, labels


def records(obs: DataFrame, pieces: int = 1) -> DataFrame:
    """One record a row with all its observations, or so many for its parts; labels of repeated cells are summed."""
    keys = ["row_id"] if pieces == 1 else ["row_id", "piece"]
    cells = obs if pieces == 1 else obs.withColumn("piece", F.pmod(F.xxhash64("col_id"), F.lit(pieces)))
    summed = cells.repartition(*keys).groupBy(*keys, "col_id").agg(F.sum("y").alias("y"))
    return list_records(summed.groupBy(*keys).agg(F.collect_list(F.struct("col_id", "y")).alias("cells")).select("row_id", F.col("cells.col_id").alias("col_ids"), F.col("cells.y").alias("ys")))


def list_records(lists: DataFrame) -> DataFrame:
    """Records of rows with lists: row_id, col_ids (each once) and, unless all labels are 1, ys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = batch.column("col_ids")
            labels = batch.column("ys").flatten().to_numpy(zero_copy_only=False).astype(np.float64) if "ys" in batch.schema.names else None
            yield record_batch(ids(batch.column("row_id")), cols.value_lengths().to_numpy(), cols.flatten().to_numpy(zero_copy_only=False), labels)

    return lists.where(F.size("col_ids") > 0).mapInArrow(run, RECORD)


def turned(stored: DataFrame) -> DataFrame:
    """Records of the columns, as many for a column as batches hold it, with the task that made them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, counts, cells, labels = cells_of(batch)
            order, owner = np.argsort(cells, kind="stable"), np.repeat(names, counts)
            columns, n = np.unique(cells, return_counts=True)
            yield record_batch(columns, n, owner[order], None if labels is None else labels[order])

    return stored.mapInArrow(run, RECORD).withColumn("task", F.spark_partition_id())


def joined_records(parts: DataFrame, *keys) -> DataFrame:
    """Parts of records (with equal keys row_id and others) as whole records; the parts are neighbours, so their bytes are copied and no cell is looked at unless widths differ."""

    def flush(kept: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in kept:
            names, counts, cells, labels = cells_of(batch)
            key = batch.column("piece").to_numpy()
            first = np.flatnonzero(np.concatenate([[True], (names[1:] != names[:-1]) | (key[1:] != key[:-1])]))
            yield record_batch(names[first], np.add.reduceat(counts, first), cells, labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: pa.Table | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            have = pa.Table.from_batches([batch]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([batch])])
            names, key = ids(have.column("row_id")), have.column("piece").to_numpy()
            cut = int(np.flatnonzero((names != names[-1]) | (key != key[-1]))[-1]) + 1 if ((names != names[-1]) | (key != key[-1])).any() else 0
            yield from flush(have.slice(0, cut).combine_chunks().to_batches() if cut else [])
            rest = have.slice(cut)
        if rest is not None:
            yield from flush(rest.combine_chunks().to_batches())

    sent = parts.repartition("row_id", "piece").sortWithinPartitions("row_id", "piece")
    return sent.select("row_id", "n", "cells", "labels", "piece").mapInArrow(run, RECORD)


def turned_records(stored: DataFrame, heavy_row: int) -> tuple[DataFrame, DataFrame | None, str]:
    """Records of the columns of stored records, those of heavy columns in pieces beside the others', and the folder of parts that they are made from."""
    parts, path = generation_at(turned(stored), "turned")
    heavy = parts.groupBy("row_id").agg(F.sum("n").alias("total")).where(F.col("total") > heavy_row).select(F.col("row_id").alias("heavy_id"))
    heavy = generation_at(heavy, "heavy-columns")[0]
    if not heavy.limit(1).count():
        return joined_records(parts.withColumn("piece", F.lit(0))), None, path
    on = F.col("row_id") == F.col("heavy_id")
    light = parts.join(heavy, on, "left_anti").withColumn("piece", F.lit(0))
    long = parts.join(heavy, on, "left_semi").withColumn("piece", F.pmod("task", F.lit(PIECES)).cast("int"))
    return joined_records(light), joined_records(long), path


#: Bytes of vectors that are gathered at a time: they are to stay in a core's cache.
GATHER_BYTES = 4 << 20


def row_systems(names: np.ndarray, counts: np.ndarray, at: np.ndarray, y: np.ndarray | None, table: np.ndarray) -> Systems:
    """Systems of rows whose vectors are at the places ``at`` of a table, so many a row (none is empty), without padding: a product for each row."""
    rank, ends = table.shape[1], np.cumsum(counts)
    a, b = np.empty((len(names), rank, rank)), np.empty((len(names), rank))
    begins, step, k = ends - counts, max(1, GATHER_BYTES // (8 * rank)), 0
    while k < len(names):
        until = max(k + 1, int(np.searchsorted(ends, begins[k] + step, "right")))
        lo = begins[k]
        x = table.take(at[lo : ends[until - 1]], axis=0).astype(np.float64, copy=False)
        for i, (first, last) in enumerate(zip((begins[k:until] - lo).tolist(), (ends[k:until] - lo).tolist(), strict=True), k):
            part = x[first:last]
            np.dot(part.T, part, out=a[i])
        b[k:until] = np.add.reduceat(x if y is None else x * y[lo : ends[until - 1], None], begins[k:until] - lo, axis=0)
        k = until
    yy = counts.astype(np.float64) if y is None else np.add.reduceat(y * y, begins)
    return Systems(names, a, b, yy, counts, np.zeros((len(names), rank)))


@dataclass(frozen=True)
class Points:
    """Models that are trained together on records whose ids carry the number of their part of the observations above POINT_BITS: of holds the models of each part, scale the folder of the frozen rows' scales (id, vec of one number), by which their vectors are multiplied."""

    of: tuple[tuple[int, ...], ...]
    scale: str | None = None

    def laid(self, names: np.ndarray, counts: np.ndarray, need: np.ndarray, y: np.ndarray | None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]]:
        """The records once for each model of their part."""
        part, low = names >> POINT_BITS, (1 << POINT_BITS) - 1
        for k in np.unique(part):
            mine = part == k
            inside = np.repeat(mine, counts)
            some, n, cells, label = names[mine] & low, counts[mine], need[inside] & low, None if y is None else y[inside]
            for point in self.of[k]:
                yield some | point << POINT_BITS, n, cells | point << POINT_BITS, label

    def plain(self, names: np.ndarray) -> np.ndarray:
        """Ids of models as ids of their parts."""
        part = np.zeros(1 + max((p for x in self.of for p in x), default=0), dtype=np.int64)
        for k, x in enumerate(self.of):
            part[list(x)] = k
        return names & ((1 << POINT_BITS) - 1) | part[names >> POINT_BITS] << POINT_BITS

    def scaled(self, x: np.ndarray, names: np.ndarray, keep: tuple[str | None, ...]) -> np.ndarray:
        return x if self.scale is None else x * held_vectors(self.scale, 1, "float64", keep).of(self.plain(names))


#: Bytes of vectors that a worker picks from a table at a time, and passes over the table beyond which shuffling a vector for each cell is cheaper.
PICK_BYTES, PICK_PASSES = 144 << 20, 16


def gather_of(columns: int, cfg: FactorConfig) -> str:
    """The way to a stored table of so many columns: held by the workers, picked from, or shuffled."""
    size = columns * cfg.rank * 8
    return "held" if size <= cfg.broadcast_limit else "picked" if size <= PICK_PASSES * PICK_BYTES else "shuffle"


def stored_for(fac: DataFrame, cfg: FactorConfig, how: str, label: str) -> str:
    """The folder of a table as held or picked vectors are read."""
    table = store_table(fac.select("id", "vec"), cfg.rank, cfg.precision)
    return generation_at(packed_doubles(table, cfg.rank) if how == "picked" and not is_packed(table) else table, label)[1]


def portions(counts: np.ndarray, most: int) -> Iterator[tuple[slice, slice]]:
    """Rows of at most so many cells together, or single ones, and their cells."""
    ends, k = np.concatenate([[0], np.cumsum(counts)]), 0
    while k < len(counts):
        until = max(k + 1, int(np.searchsorted(ends, ends[k] + most, "right")) - 1)
        yield slice(k, until), slice(ends[k], ends[until])
        k = until


def refit_held(rows: DataFrame, path: str, base: np.ndarray, cfg: FactorConfig, start: str | None = None, sums: bool = False, points: Points | None = None, pick: bool = False) -> DataFrame:
    """Half-step over records against the table stored at path; start: the folder of vectors to begin with. sums: partial systems instead of solutions. points: models that share the records. pick: tables aren't held, but the vectors in need are picked from them."""

    def with_tables(found: Iterator) -> Iterator[tuple]:
        """Records with the vectors of their columns and those to begin with."""
        kept = (path, start, points and points.scale)
        for names, counts, need, y in found:
            if not pick:
                yield names, counts, need, y, held_vectors(path, cfg.rank, cfg.precision, kept), start and held_vectors(start, cfg.rank, cfg.precision, kept)
                continue
            begins = start and picked_vectors(start, cfg.rank, cfg.precision, names)
            for some, cells in portions(counts, PICK_BYTES // (8 * cfg.rank)):
                yield names[some], counts[some], need[cells], None if y is None else y[cells], picked_vectors(path, cfg.rank, cfg.precision, need[cells]), begins

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        solver, kept = RowSolver(base, cfg), (path, start, points and points.scale)
        step = max(1, cfg.solve_batch_bytes // (8 * cfg.rank))
        found = (cells_of(batch) for batch in batches if batch.num_rows)
        for names, counts, need, y, table, begins in with_tables(found if points is None else (x for cells in found for x in points.laid(*cells))):
            at = table.places(need)
            known = at >= 0
            if not known.all():
                counts = np.bincount(np.repeat(np.arange(len(names)), counts), known, len(names)).astype(np.int64)
                at, need, y, names, counts = at[known], need[known], None if y is None else y[known], names[counts > 0], counts[counts > 0]
            ends, k = np.concatenate([[0], np.cumsum(counts)]), 0
            while k < len(names):
                until = min(max(k + 1, int(np.searchsorted(ends, ends[k] + step, "right")) - 1), k + system_group(cfg))
                part, who, n = slice(ends[k], ends[until]), names[k:until], counts[k:until]
                vectors, places = table.vectors, at[part]
                if points is not None and points.scale:
                    vectors, places = points.scaled(vectors[places], need[part], kept), np.arange(len(places))
                label = None if y is None else y[part]
                begin = begins.of(who) if begins else None
                if cfg.chosen_solver() == "cg_free" and not sums:
                    name, x = np.repeat(who, n), vectors[places].astype(np.float64, copy=False)
                    label = np.ones(len(name)) if label is None else label
                    order = np.argsort(who)
                    more = [] if begin is None else [(who[order], np.full(len(who), np.nan), begin[order])]
                    yield solve_free([(name, label, x), *more], base, cfg) if (np.diff(who) > 0).all() else solve_free_unsorted(name, label, x, more, base, cfg)
                else:
                    found = row_systems(who, n, places, label, vectors)
                    if sums:
                        yield partial_batch(found)
                    else:
                        if begin is not None:
                            found.start = begin
                        yield from solver.add(found)
                k = until
        yield from solver.rest()

    return rows.mapInArrow(run, "row_id long, stats array<double>, n long" if sums else solved_type(cfg.precision))


def solve_free_unsorted(name: np.ndarray, y: np.ndarray, x: np.ndarray, more: list, base: np.ndarray, cfg: FactorConfig) -> pa.RecordBatch:
    order = np.argsort(name, kind="stable")
    return solve_free([(name[order], y[order], x[order]), *more], base, cfg)


def heavy_rows(obs: DataFrame, limit: int) -> DataFrame:
    return obs.groupBy("row_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > limit).select(F.col("row_id").alias("heavy_id"))


def held_records(obs: DataFrame, heavy: DataFrame | None) -> tuple[DataFrame, DataFrame | None]:
    """Records of all rows, or of those that aren't heavy beside the heavy ones' in pieces."""
    if heavy is None:
        return records(obs), None
    on = F.col("row_id") == F.col("heavy_id")
    return records(obs.join(heavy, on, "left_anti")), records(obs.join(heavy, on, "left_semi"), PIECES)


def base_of(gram: np.ndarray | None, cfg: FactorConfig) -> np.ndarray:
    return cfg.reg * np.eye(cfg.rank) + (cfg.unobserved * gram if cfg.unobserved else 0.0)


def refit_side(obs: DataFrame, fac: DataFrame, gram: np.ndarray | None, cfg: FactorConfig, how: str = "shuffle", heavy: DataFrame | None = None, start: DataFrame | None = None, base: np.ndarray | None = None, plan: dict | None = None) -> DataFrame:
    """One half-step: (id, vec, err) of every row with an observation; err is the squared error over its own observations.

    heavy: rows (heavy_id) to sum in parts. start: vectors (id, vec) that conjugate gradients
    begin with; other solvers don't read them. base: the matrix to add to each system, made
    from gram where it isn't given. plan: routes, blocks or hot columns that all epochs share.
    """
    base, plan = base_of(gram, cfg) if base is None else base, plan or {}
    fac = store_table(fac, cfg.rank, cfg.precision)
    light, solved = obs, []
    if how in ("held", "picked"):
        path = plan.get("path") or stored_for(fac, cfg, how, "held")
        begin = None
        if start is not None and cfg.chosen_solver() in ("cg", "cg_free"):
            begin = plan.get("start") or stored_for(start, cfg, how, "held-start")
        whole, pieces = plan.get("records") or held_records(obs, heavy)
        first = refit_held(whole, path, base, cfg, begin, pick=how == "picked")
        return first if pieces is None else first.unionByName(solve_partial(refit_held(pieces, path, base, cfg, sums=True, pick=how == "picked"), base, cfg))
    if heavy is not None and how != "partial_stats":
        # Few rows are heavy, but how few isn't known here, so the planner decides how to join them.
        light = obs.join(heavy, F.col("row_id") == F.col("heavy_id"), "left_anti")
        long = obs.join(heavy, F.col("row_id") == F.col("heavy_id"), "left_semi")
        solved.append(solve_partial(partial_sums(gather(long, fac, cfg, "shuffle"), cfg), base, cfg))
    if how == "partial_stats":
        # A shard of columns for each block, which is what the planner counts.
        held = obs.repartition(*([cfg.blocks] if cfg.blocks else []), "col_id").join(fac.select(F.col("id").alias("vec_id"), "vec").hint("merge"), F.col("col_id") == F.col("vec_id"))
        return solve_partial(partial_sums(held, cfg), base, cfg)
    if how == "routed":
        first = refit_routed(light, fac, base, cfg, plan.get("routes"), plan.get("blocks"))
    else:
        warm = start is not None and cfg.chosen_solver() in ("cg", "cg_free")
        if how == "broadcast" and not warm:
            first = refit_sent(light, fac, base, cfg)
        else:
            gathered = gather(light, fac, cfg, how, plan.get("hot"))
            if warm:
                begins = store_table(start, cfg.rank, cfg.precision).select(F.col("id").alias("row_id"), F.lit(None).cast("bigint").alias("col_id"), F.lit(float("nan")).alias("y"), "vec")
                gathered = gathered.unionByName(begins)
            first = solve_gathered(gathered, base, cfg)
    return first.unionByName(solved[0]) if solved else first
