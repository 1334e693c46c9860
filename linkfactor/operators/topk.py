"""Retrieval by inner product: exact by blocks or by a sort, approximate by sign codes or by cells.

Both sides are dealt to blocks, a pair of blocks is scored at a time in arrays, and only each
row's best places of a block are sent on; the lists are merged. The number of blocks
follows from the tables' bytes and pairs. Against a stored column table within HELD_BYTES a
search needs no blocks: every worker reads it once, and a row's list is made where the row is. The approximate searches score blocks by short
codes and then take the best ``pool`` places of each row by their exact scores, which are
found where a block's vectors are at hand, so that no vector is shuffled for them.

Vectors may be lists or packed numbers. Ties go to the smaller column id. Rows with fewer
columns than asked for get what there is.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial
from math import ceil, sqrt
from uuid import uuid4

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import dot
from ..runtime import generation_at
from .arrays import ids, to_matrix
from .factors import as_lists, held_vectors, is_packed, ordered_vectors

RANKED = "row_id long, col_id long, score double"
_SCHEMA = pa.schema([("row_id", pa.int64()), ("col_id", pa.int64()), ("score", pa.float64())])
_POOLED = pa.schema([*_SCHEMA, ("exact", pa.float64())])
#: Bytes of one side's block, of the scores that are held at a time and of those that are sorted at a time; products of numbers that a task makes, and tiles of columns by whose best scores a row's places are narrowed.
BLOCK_BYTES, SCORE_BYTES, SORT_BYTES, TASK_PAIRS, TILE = 32 << 20, 16 << 20, 1 << 20, 1 << 32, 64


def best_places(scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of each row's k largest scores above minus infinity, columns in order of id; of equal scores the earlier column.

    k tiles reach at least the k-th best of the tiles' largest scores, so no place below that is among the k best.
    """
    n, m = scores.shape
    tiles = m // TILE
    if tiles > 2 * k and not np.isnan(scores).any():
        tops = scores[:, : tiles * TILE].reshape(n, tiles, TILE).max(axis=2)
        least = np.partition(tops, tiles - k, axis=1)[:, tiles - k, None]
        row, col = np.nonzero(scores >= least)
        value = scores[row, col]
        order = np.lexsort((col, -value, row))
        row, col, value = row[order], col[order], value[order]
        place = np.arange(len(row)) - np.searchsorted(row, np.arange(n))[row]
        keep = (place < k) & np.isfinite(value)
        order = np.lexsort((col[keep], row[keep]))
        return row[keep][order], col[keep][order]
    if m > k:
        edge = np.partition(scores, m - k, axis=1)[:, m - k, None]
        above = scores > edge
        level = scores == edge
        keep = above | (level & (np.cumsum(level, axis=1) <= k - above.sum(axis=1)[:, None]))
    else:
        keep = np.ones((n, m), dtype=bool)
    keep &= np.isfinite(scores)
    return np.nonzero(keep)


def _cell_keys(scores: np.ndarray, digits: int) -> np.ndarray | None:
    """A whole number for each cell of scores rounded to so many digits, in the order of falling scores and then of columns; None where 64 bits don't hold them."""
    bits = (scores.shape[1] - 1).bit_length()
    most, steps = 2.0 ** (62 - bits), np.rint(scores * -(10.0**digits))
    if not steps.min() > -most:
        return None
    if steps.max() >= most:
        if np.count_nonzero(steps >= most) != np.count_nonzero(scores == -np.inf):
            return None
        np.minimum(steps, most, out=steps)
    keys = steps.astype(np.int64)
    keys <<= bits
    keys |= np.arange(scores.shape[1])
    return keys


def sorted_places(scores: np.ndarray, k: int, digits: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The same by a sort of all of a row's scores; digits: those that they are rounded to, so that a score and its column are sorted as one number.

    Otherwise the order among equal scores is left open, and where the k-th place is tied, its earlier columns are taken.
    """
    if digits is not None and scores.size:
        step, col = max(1, SORT_BYTES // (8 * scores.shape[1])), []
        for at in range(0, len(scores), step):
            keys = _cell_keys(scores[at : at + step], digits)
            if keys is None:
                break
            keys.sort(axis=1)
            col.append(keys[:, :k] & ((1 << (scores.shape[1] - 1).bit_length()) - 1))
        else:
            col = np.concatenate(col)
            row = np.repeat(np.arange(len(scores)), col.shape[1])
            keep = np.isfinite(scores[row, col.reshape(-1)])
            return row[keep], col.reshape(-1)[keep]
    order = np.argsort(-scores, axis=1)
    col = order[:, :k]
    if scores.shape[1] > k > 0:
        every = np.arange(len(scores))
        tied = np.flatnonzero(scores[every, order[:, k - 1]] == scores[every, order[:, k]])
        if len(tied):
            some, edge = scores[tied], scores[tied, order[tied, k - 1]][:, None]
            above, level = some > edge, some == edge
            keep = above | (level & (np.cumsum(level, axis=1, dtype=np.int32) <= k - above.sum(axis=1)[:, None]))
            col[tied] = np.nonzero(keep)[1].reshape(-1, k)
    row = np.repeat(np.arange(len(scores)), col.shape[1])
    keep = np.isfinite(scores[row, col.reshape(-1)])
    return row[keep], col.reshape(-1)[keep]


def _merge(parts: DataFrame, k: int, by: str = "score") -> DataFrame:
    place = F.row_number().over(Window.partitionBy("row_id").orderBy(F.desc(by), "col_id"))
    return parts.withColumn("rank", place).where(F.col("rank") <= k)


def blocks_of(rows: int, rank: int) -> int:
    return max(1, ceil(rows * rank * 8 / BLOCK_BYTES))


def _excluded(exclude: DataFrame, col_blocks: int) -> DataFrame:
    """The excluded columns of each row, by the block of the columns."""
    block = F.pmod(F.xxhash64("col_id"), F.lit(col_blocks)).cast("int")
    return exclude.select("row_id", "col_id", block.alias("ex_block")).groupBy(F.col("row_id").alias("ex_row"), "ex_block").agg(F.collect_set("col_id").alias("gone"))


#: Given a block's columns, what scores rows against them.
Score = Callable[[np.ndarray], Callable[[np.ndarray], np.ndarray]]


def _best_of_blocks(left: DataFrame, right: DataFrame, k: int, rank: int, score: Score, exact: bool = False, places=best_places) -> DataFrame:
    """left (block, id, vec, gone) and right (block, id, vec), met by block: each row's k best places of every block; exact: with their products as a column."""
    schema = _POOLED if exact else _SCHEMA

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        found: list[tuple[np.ndarray, ...]] = []
        if a.num_rows and b.num_rows:
            names, table = ids(b.column("their_id")), to_matrix(b.column("their_vec"), rank)
            order = np.argsort(names, kind="stable")
            names, table = names[order], table[order]
            who, queries = ids(a.column("id")), to_matrix(a.column("vec"), rank)
            gone = a.column("gone").combine_chunks()
            ends = np.concatenate([[0], np.cumsum(np.array(gone.value_lengths().fill_null(0)))])
            left_out = gone.flatten().to_numpy(zero_copy_only=False)
            scored, step = score(table), max(1, SCORE_BYTES // (8 * len(names)))
            for at in range(0, len(who), step):
                until = min(len(who), at + step)
                scores = scored(queries[at:until])
                out = left_out[ends[at] : ends[until]]
                if len(out):
                    row = np.repeat(np.arange(until - at), np.diff(ends[at : until + 1]))
                    place = np.minimum(np.searchsorted(names, out), len(names) - 1)
                    there = names[place] == out
                    scores[row[there], place[there]] = -np.inf
                row, col = places(scores, k)
                more = (np.einsum("nd,nd->n", queries[at + row], table[col]),) if exact else ()
                found.append((who[at + row], names[col], scores[row, col], *more))
        if not found:
            return schema.empty_table()
        return pa.table([pa.array(np.concatenate([f[j] for f in found]), type=schema.field(j).type) for j in range(len(schema))], schema=schema)

    theirs = right.select(F.col("block").alias("their_block"), F.col("id").alias("their_id"), F.col("vec").alias("their_vec"))
    return left.groupBy("block").cogroup(theirs.groupBy("their_block")).applyInArrow(run, f"{RANKED}, exact double" if exact else RANKED)


def _dealt(rows: DataFrame, columns: DataFrame, rank: int, exclude: DataFrame | None, row_blocks: int | None, col_blocks: int | None) -> tuple[DataFrame, DataFrame]:
    """Both sides with the pairs of blocks that they belong to, and the rows with what they leave out."""
    if not (row_blocks and col_blocks):
        n, m = rows.count(), columns.count()
        col_blocks = col_blocks or blocks_of(m, rank)
        row_blocks = row_blocks or max(blocks_of(n, rank), min(n, ceil(n * m / (TASK_PAIRS // rank) / col_blocks)))
    spread = lambda own, other, n: F.explode(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda x: F.struct(own(x).alias("rb"), other(x).alias("cb"))))
    mine = F.pmod(F.xxhash64("id"), F.lit(row_blocks)).cast("int")
    theirs = F.pmod(F.xxhash64("id"), F.lit(col_blocks)).cast("int")
    left = rows.select("id", "vec", spread(lambda x: mine, lambda x: x, col_blocks).alias("block"))
    right = columns.select("id", "vec", spread(lambda x: x, lambda x: theirs, row_blocks).alias("block"))
    if exclude is None:
        return left.withColumn("gone", F.array().cast("array<bigint>")), right
    gone = _excluded(exclude, col_blocks)
    return left.join(gone, (F.col("id") == F.col("ex_row")) & (F.col("block.cb") == F.col("ex_block")), "left").select("block", "id", "vec", "gone"), right


def _product(digits: int | None = None) -> Score:
    return lambda b: lambda a: a @ b.T if digits is None else np.round(x := a @ b.T, digits, out=x)


def topk_exact(rows: DataFrame, columns: DataFrame, k: int, rank: int, exclude: DataFrame | None = None, row_blocks: int | None = None, col_blocks: int | None = None, digits: int | None = None, path: str | None = None) -> DataFrame:
    """row_id, col_id, score, rank. Each pair of blocks is one matrix product that keeps its k best.

    A row travels col_blocks times and a column row_blocks times; neither side is broadcast.
    exclude (row_id, col_id) is left out inside the blocks. Blocks follow from the tables' bytes unless they are given.
    path: the folder of the columns' stored table of doubles, which workers then hold; scores aren't rounded there.
    """
    if path is not None:
        return topk_held(rows, path, k, rank, "float64", exclude)
    left, right = _dealt(rows, columns, rank, exclude, row_blocks, col_blocks)
    return _merge(_best_of_blocks(left, right, k, rank, _product(digits)), k)


#: Columns that are scored at a time against a held table, and rows; bytes of a column table that workers may hold for a search, and rows that look into cells at a time.
HELD_COLUMNS, HELD_ROWS = 1 << 14, 128
HELD_BYTES, CELL_ROWS = 128 << 20, 1 << 10


def is_held(columns: DataFrame, rank: int) -> bool:
    """Whether a column table is small enough to be held by every worker."""
    return columns.count() * rank * 8 <= HELD_BYTES


def _asked(rows: DataFrame, path: str, rank: int, exclude: DataFrame | None) -> DataFrame:
    """The rows with what they leave out. They are few bytes but much work, so their number of tasks follows from the pairs."""
    if exclude is None:
        left = rows.select("id", "vec", F.array().cast("array<bigint>").alias("gone"))
    else:
        gone = exclude.groupBy(F.col("row_id").alias("ex_row")).agg(F.collect_set("col_id").alias("gone"))
        left = rows.select("id", "vec").join(gone, F.col("id") == F.col("ex_row"), "left").select("id", "vec", "gone")
    pairs = rows.count() * rows.sparkSession.read.parquet(path).count()
    return left.repartition(max(2 * rows.sparkSession.sparkContext.defaultParallelism, ceil(pairs * rank / (4 * TASK_PAIRS))), "id")


#: Given rows and the places that some of them leave out: rows and columns of the best places and their scores, columns in order of id where scores are equal. What makes it from a table of columns tells too how many rows it takes at a time.
Search = Callable[[np.ndarray, np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray, np.ndarray]]
Make = Callable[[np.ndarray], tuple[Search, int]]
_READY: dict[str, tuple[np.ndarray, np.ndarray, Search | None, int]] = {}


def _ready(key: str, path: str, rank: int, make: Make) -> tuple[np.ndarray, np.ndarray, Search | None, int]:
    """The columns' ids and vectors in order of id and the search over them, made once a worker."""
    if key not in _READY:
        _READY.clear()
        names, table = ordered_vectors(path, rank, "float64")
        _READY[key] = names, table, *(make(table) if len(names) else (None, 1))
    return _READY[key]


def _scan(score: Score, k: int, places=best_places, held: int = SCORE_BYTES) -> Make:
    """Search that scores a row against all columns, so many bytes of scores at a time."""

    def make(table: np.ndarray) -> tuple[Search, int]:
        scored = score(table)

        def search(queries: np.ndarray, gone_row: np.ndarray, gone_col: np.ndarray):
            scores = scored(queries)
            scores[gone_row, gone_col] = -np.inf
            row, col = places(scores, k)
            return row, col, scores[row, col]

        return search, max(1, held // (8 * max(1, len(table))))

    return make


def first_places(row: np.ndarray, col: np.ndarray, value: np.ndarray, n: int, k: int) -> tuple[np.ndarray, ...]:
    """Of places of n rows the k best of each, in order, and their rank."""
    turn = np.lexsort((col, -value, row))
    row, col, value = row[turn], col[turn], value[turn]
    place = np.arange(len(row)) - np.searchsorted(row, np.arange(n))[row]
    keep = place < k
    return row[keep], col[keep], value[keep], place[keep] + 1


def _best_held(rows: DataFrame, path: str, k: int, rank: int, make: Make, exclude: DataFrame | None = None, exact: bool = False) -> DataFrame:
    """row_id, col_id, score, rank of each row's k best places by a search over the columns stored at path; exact: with their products as a column."""
    key = uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, table, search, step = _ready(key, path, rank, make)
            if not len(names):
                continue
            who, queries, lists = ids(batch.column("id")), to_matrix(batch.column("vec"), rank), batch.column("gone")
            out, owner = lists.flatten().to_numpy(zero_copy_only=False), np.repeat(np.arange(len(who)), np.array(lists.value_lengths().fill_null(0)))
            place = np.minimum(np.searchsorted(names, out), len(names) - 1)
            there = names[place] == out
            place, owner = place[there], owner[there]
            for at in range(0, len(who), step):
                some, lo, hi = queries[at : at + step], *np.searchsorted(owner, (at, at + step))
                row, col, value, place_of = first_places(*search(some, owner[lo:hi] - at, place[lo:hi]), len(some), k)
                more = [pa.array(np.einsum("nd,nd->n", some[row], table[col]), type=pa.float64())] if exact else []
                yield pa.RecordBatch.from_arrays([pa.array(who[at + row], type=pa.int64()), pa.array(names[col], type=pa.int64()), pa.array(value, type=pa.float64()), *more, pa.array(place_of, type=pa.int32())], names=["row_id", "col_id", "score", *(["exact"] if exact else []), "rank"])

    return _asked(rows, path, rank, exclude).mapInArrow(run, f"{RANKED}{', exact double' if exact else ''}, rank int")


def topk_held(rows: DataFrame, path: str, k: int, rank: int, precision: str, exclude: DataFrame | None = None) -> DataFrame:
    """topk_exact against the column table stored at path, which every worker reads once: no vector is shuffled, and a row's list is made where the row is.

    Columns come in order of id, so after a row's first k only larger scores can enter its list.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = None
        for batch in batches:
            table = held_vectors(path, rank, precision, (path,))
            if order is None:
                order = np.argsort(table.names) if table.order is None else table.order
                names = table.names[order] if table.order is None else table.names
            who, queries, lists = ids(batch.column("id")), to_matrix(batch.column("vec"), rank), batch.column("gone")
            out, owner = lists.flatten().to_numpy(zero_copy_only=False), np.repeat(np.arange(len(who)), np.array(lists.value_lengths().fill_null(0)))
            place = np.minimum(np.searchsorted(names, out), max(0, len(names) - 1))
            there = names[place] == out if len(names) else np.zeros(len(out), dtype=bool)
            place, owner = place[there], owner[there]
            for at in range(0, len(who), HELD_ROWS):
                some, lo, hi = queries[at : at + HELD_ROWS], *np.searchsorted(owner, (at, at + HELD_ROWS))
                gone_row, gone_col = owner[lo:hi] - at, place[lo:hi]
                turn = np.argsort(gone_col)
                gone_row, gone_col = gone_row[turn], gone_col[turn]
                best = (np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0))
                least = np.full(len(some), -np.inf)
                for first in range(0, len(names), HELD_COLUMNS):
                    scores = some @ table.vectors[order[first : first + HELD_COLUMNS]].astype(np.float64, copy=False).T
                    lo, hi = np.searchsorted(gone_col, (first, first + HELD_COLUMNS))
                    scores[gone_row[lo:hi], gone_col[lo:hi] - first] = -np.inf
                    row, col = np.nonzero(scores > least[:, None]) if np.isfinite(least).all() else best_places(scores, k)
                    if not len(row):
                        continue
                    row, col, value = (np.concatenate(x) for x in zip(best, (row, col + first, scores[row, col]), strict=True))
                    turn = np.lexsort((col, -value, row))
                    row, col, value = row[turn], col[turn], value[turn]
                    begins = np.searchsorted(row, np.arange(len(some)))
                    keep = (np.arange(len(row)) - begins[row] < k) & np.isfinite(value)
                    best = row, col, value = row[keep], col[keep], value[keep]
                    sizes = np.bincount(row, minlength=len(some))
                    full = sizes >= k
                    least[full] = value[np.cumsum(sizes)[full] - 1]
                row, col, value = best
                rank_of = np.arange(len(row)) - np.searchsorted(row, np.arange(len(some)))[row] + 1
                yield pa.RecordBatch.from_arrays([pa.array(who[at + row], type=pa.int64()), pa.array(names[col], type=pa.int64()), pa.array(value, type=pa.float64()), pa.array(rank_of, type=pa.int32())], names=["row_id", "col_id", "score", "rank"])

    return _asked(rows, path, rank, exclude).mapInArrow(run, f"{RANKED}, rank int")


def topk_points(rows: DataFrame, columns: DataFrame, k: int, rank: int, exclude: DataFrame | None = None, bits: int = 40) -> DataFrame:
    """topk_exact within each point (the ids' part above the lower bits); a point's columns are one block."""
    point = F.shiftright("id", bits).cast("int")
    left, right = rows.select(point.alias("block"), "id", "vec"), columns.select(point.alias("block"), "id", "vec")
    if exclude is None:
        left = left.withColumn("gone", F.array().cast("array<bigint>"))
    else:
        left = left.join(_excluded(exclude, 1).drop("ex_block"), F.col("id") == F.col("ex_row"), "left").drop("ex_row")
    return _merge(_best_of_blocks(left, right, k, rank, _product()), k)


def topk_sort(rows: DataFrame, columns: DataFrame, k: int, exclude: DataFrame | None = None, digits: int | None = None) -> DataFrame:
    """The baseline that scores every cell and sorts all scores of a row; columns beyond HELD_BYTES go by blocks, of which only the best places are shuffled."""
    one = columns.select(F.size("vec").alias("n")).first()
    rank = one["n"] if one else 1
    places = partial(sorted_places, digits=digits)
    if is_held(columns, rank):
        return _best_held(rows, generation_at(columns.select("id", "vec"), "searched")[1], k, rank, _scan(_product(digits), k, places, 4 * SCORE_BYTES), exclude)
    left, right = _dealt(rows, columns, rank, exclude, None, None)
    return _merge(_best_of_blocks(left, right, k, rank, _product(digits), places=places), k)


def rerank(found: DataFrame, rows: DataFrame, columns: DataFrame, k: int, rank: int) -> DataFrame:
    """Exact scores of candidate pairs, and each row's k best. Candidates that carry their exact scores aren't joined with vectors."""
    if "exact" in found.columns:
        return _merge(found.select("row_id", "col_id", F.col("exact").alias("score")), k)
    rows, columns = (as_lists(x, rank) if is_packed(x) else x for x in (rows, columns))
    pairs = found.select("row_id", "col_id")
    scored = pairs.join(rows.select(F.col("id").alias("row_id"), F.col("vec").alias("v")), "row_id").join(columns.select(F.col("id").alias("col_id"), F.col("vec").alias("u")), "col_id")
    return _merge(scored.select("row_id", "col_id", dot("v", "u").alias("score")), k)


def pool_of(k: int) -> int:
    """Places of each row that are scored exactly: 1.8 times as many as asked for."""
    return k + ceil(0.8 * k)


#: Columns whose codes are compared at a time: what is counted stays in a core's cache.
CODE_COLUMNS = 1 << 12


def sign_codes(bits: int, rank: int, seed: int) -> Score:
    """The columns' lengths times the cosine that agreeing signs of random projections tell (of b bits, half for each right angle)."""

    def score(b: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
        planes = np.random.default_rng(seed).standard_normal((bits, rank))
        codes = lambda x: np.packbits(x @ planes.T > 0, axis=1).view(np.uint64)
        step = max(1, SCORE_BYTES // (8 * bits))
        theirs = np.ascontiguousarray(np.concatenate([codes(b[at : at + step]) for at in range(0, len(b), step)]).T)
        cosines, lengths = np.cos(np.pi * np.arange(bits + 1) / bits), np.linalg.norm(b, axis=1)

        def against(a: np.ndarray) -> np.ndarray:
            mine, out = codes(a), np.empty((len(a), len(b)))
            for at in range(0, len(b), CODE_COLUMNS):
                some = slice(at, at + CODE_COLUMNS)
                differ = np.zeros(out[:, some].shape, dtype=np.uint16 if bits < 1 << 16 else np.int64)
                for word, column in enumerate(theirs[:, some]):
                    differ += np.bitwise_count(mine[:, word, None] ^ column)
                np.multiply(cosines[differ], lengths[some], out=out[:, some])
            return out

        return against

    return score


def candidates_lsh(rows: DataFrame, columns: DataFrame, k: int, rank: int, bits: int = 2048, seed: int = 7, exclude: DataFrame | None = None, row_blocks: int | None = None, col_blocks: int | None = None, path: str | None = None) -> DataFrame:
    """(row_id, col_id, score, exact): the pool of each row by sign codes, with the exact products. path: as for topk_exact."""
    if path is not None:
        return _best_held(rows, path, pool_of(k), rank, _scan(sign_codes(bits, rank, seed), pool_of(k)), exclude, exact=True).drop("rank")
    left, right = _dealt(rows, columns, rank, exclude, row_blocks, col_blocks)
    return _merge(_best_of_blocks(left, right, pool_of(k), rank, sign_codes(bits, rank, seed), exact=True), pool_of(k)).drop("rank")


def topk_lsh(rows: DataFrame, columns: DataFrame, k: int, rank: int, **more) -> DataFrame:
    """Sign random projections: codes of ``bits`` bits are compared by blocks, and the pool is scored exactly."""
    return rerank(candidates_lsh(rows, columns, k, rank, **more), rows, columns, k, rank)


def _steps(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vectors as 127 steps of their largest number either way, and the size of a step."""
    size = np.abs(x).max(axis=1, keepdims=True)
    size[size == 0] = 1.0
    return np.round(x / size * 127).astype(np.float32), size / 127


def _eighths(b: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    """Products of vectors rounded to 127 steps of their largest number either way."""
    q, v = _steps(b)

    def against(a: np.ndarray) -> np.ndarray:
        p, u = _steps(a)
        return (p @ q.T).astype(np.float64) * u * v.T

    return against


def k_means(points: np.ndarray, cells: int, seed: int, rounds: int = 15) -> np.ndarray:
    rng = np.random.default_rng(seed)
    centres = points[rng.choice(len(points), min(cells, len(points)), replace=False)]
    for _ in range(rounds):
        near = (points @ centres.T - 0.5 * (centres**2).sum(axis=1)).argmax(axis=1)
        centres = np.array([points[near == c].mean(axis=0) if (near == c).any() else centres[c] for c in range(len(centres))])
    return centres


def probes_for(queries: np.ndarray, points: np.ndarray, centres: np.ndarray, k: int, recall: float) -> int:
    """The fewest cells a query must look into for the wanted mean share of its k best points, measured on samples of both."""
    home = (points @ centres.T - 0.5 * (centres**2).sum(axis=1)).argmax(axis=1)
    order = np.argsort(-(queries @ centres.T), axis=1)
    turn = np.argsort(order, axis=1)
    best = np.argsort(-(queries @ points.T), axis=1)[:, :k]
    needed = turn[np.arange(len(queries))[:, None], home[best]]
    share = [(needed < p).mean() for p in range(1, len(centres) + 1)]
    return int(np.searchsorted(share, min(recall, share[-1]))) + 1


def _look(centres: np.ndarray, probes: int, k: int) -> Make:
    """Search that scores a row against the columns of its best cells, by 8-bit products; a column is in its nearest cell."""

    def make(table: np.ndarray) -> tuple[Search, int]:
        half, step = 0.5 * (centres**2).sum(axis=1), max(1, SCORE_BYTES // (8 * len(centres)))
        home = np.concatenate([(table[at : at + step] @ centres.T - half).argmax(axis=1) for at in range(0, len(table), step)])
        order = np.argsort(home, kind="stable")
        members = np.split(order, np.searchsorted(home[order], np.arange(1, len(centres))))
        q, v = _steps(table)

        def search(queries: np.ndarray, gone_row: np.ndarray, gone_col: np.ndarray):
            cells = np.argsort(-(queries @ centres.T), axis=1)[:, :probes]
            who, cell = np.repeat(np.arange(len(queries)), cells.shape[1]), cells.reshape(-1)
            turn = np.argsort(cell, kind="stable")
            lookers, (p, u), gone_cell = np.split(who[turn], np.searchsorted(cell[turn], np.arange(1, len(centres)))), _steps(queries), home[gone_col]
            found = [(np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0))]
            for c, (mine, theirs) in enumerate(zip(lookers, members, strict=True)):
                portion = max(1, SCORE_BYTES // (8 * max(1, len(theirs))))
                for at in range(0, len(mine) if len(theirs) else 0, portion):
                    some = mine[at : at + portion]
                    scores = (p[some] @ q[theirs].T).astype(np.float64) * u[some] * v[theirs].T
                    out = (gone_cell == c) & np.isin(gone_row, some)
                    scores[np.searchsorted(some, gone_row[out]), np.searchsorted(theirs, gone_col[out])] = -np.inf
                    row, col = best_places(scores, k)
                    found.append((some[row], theirs[col], scores[row, col]))
            return tuple(np.concatenate(x) for x in zip(*found, strict=True))

        return search, CELL_ROWS

    return make


def candidates_ivf(rows: DataFrame, columns: DataFrame, k: int, rank: int, cells: int | None = None, probes: int | None = None, seed: int = 7, sample: int = 20_000, recall: float = 0.96, exclude: DataFrame | None = None, path: str | None = None) -> DataFrame:
    """(row_id, col_id, score, exact): the pool of each row from the cells that it looks into, by 8-bit products, with the exact ones. path: as for topk_exact.

    Cells (about the root of the columns' number) are fitted on at most ``sample`` columns,
    and every column is in its nearest one. Probes are the fewest that give the wanted recall on
    samples of both sides, unless they are given.
    """
    n = columns.count()
    some = lambda frame, most, total: frame if total <= most else frame.where(F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(1 << 30)) < int((1 << 30) * most / total))
    points = to_matrix(some(columns, sample, n).select("vec").toArrow().column("vec"), rank) if n else np.zeros((0, rank))
    centres = k_means(points, cells or max(1, round(sqrt(n))), seed) if len(points) else np.zeros((1, rank))
    if probes is None:
        queries = to_matrix(some(rows, 500, rows.count()).select("vec").toArrow().column("vec"), rank)
        probes = probes_for(queries, points[:20_000], centres, min(k, len(points)), recall) if len(queries) and len(points) else 1
    if path is not None:
        return _best_held(rows, path, pool_of(k), rank, _look(centres, probes, pool_of(k)), exclude, exact=True).drop("rank")

    def near(most: int):
        def run(batches):
            for batch in batches:
                x = to_matrix(batch.column("vec"), rank)
                order = np.argsort(-(x @ centres.T - (0.5 * (centres**2).sum(axis=1) if most == 1 else 0.0)), axis=1)[:, :most]
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(order.tolist(), type=pa.list_(pa.int64()))], names=[*batch.schema.names, "cells"])

        return run

    # A large cell's columns and a cell's many rows are dealt to blocks of bounded bytes.
    per_cell = max(1, len(centres))
    held = columns.select("id", "vec").mapInArrow(near(1), f"id long, vec {dict(columns.dtypes)['vec']}, cells array<long>")
    asked = rows.select("id", "vec").mapInArrow(near(probes), f"id long, vec {dict(rows.dtypes)['vec']}, cells array<long>")
    parts = max(1, ceil(blocks_of(n, rank) * 4 / per_cell))
    turns = max(1, ceil(blocks_of(rows.count() * probes, rank) / per_cell))
    theirs, mine = F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"), F.pmod(F.xxhash64("id"), F.lit(turns)).cast("int")
    right = held.select("id", "vec", F.get("cells", 0).alias("cell"), theirs.alias("part"), F.explode(F.sequence(F.lit(0), F.lit(turns - 1))).alias("turn")).select(F.struct("cell", "part", "turn").alias("block"), "id", "vec")
    left = asked.select("id", "vec", F.explode("cells").alias("cell"), mine.alias("turn")).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).select(F.struct("cell", "part", "turn").alias("block"), "id", "vec")
    if exclude is None:
        left = left.withColumn("gone", F.array().cast("array<bigint>"))
    else:
        left = left.join(_excluded(exclude, 1).drop("ex_block"), F.col("id") == F.col("ex_row"), "left").drop("ex_row")
    return _merge(_best_of_blocks(left, right, pool_of(k), rank, _eighths, exact=True), pool_of(k)).drop("rank")


def topk_ivf(rows: DataFrame, columns: DataFrame, k: int, rank: int, **more) -> DataFrame:
    """k-means cells: a row looks into its best cells only, where 8-bit products choose the pool that is scored exactly."""
    return rerank(candidates_ivf(rows, columns, k, rank, **more), rows, columns, k, rank)
