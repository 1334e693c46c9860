"""Line dedup: fuzzy lines by MinHash over character shingles.

Lines are what stands between newlines; those of white space alone never count as copies. A
line's set holds its distinct runs of SHINGLE characters (the whole line if it is shorter).
Its signature has one minimum per bin of a one-permutation MinHash over the whole set, empty
bins being filled from others by a fixed rule, so that all lines, short and long ones, have
signatures of the same kind and any two can meet. Bands of ROWS minima make candidates, finer
sketches of the same kind thin them, and exact Jaccard similarity on the texts' sets confirms
every link (100 * common >= PERCENT * union).
Components of equal and linked lines keep one line, the first by (doc_id, line number).

Equal lines are one item by a 64-bit hash of their bytes, and only hashes travel: texts of
lines are fetched for candidates alone, and only documents that lose a line are joined with
what they lose. A line that fills a third of the corpus is one item with a count.

Defined results: null texts stay null and empty ones empty; a document may lose all its
lines and then has an empty text; rows with one doc_id count as one document, and so do
rows without any; repeated rows get equal results; an empty table gives an empty result;
extra columns are carried, n_chars follows the text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bloom import prefilter, split
from .cluster import settle, settle_table
from .kernels import Block, blocks, distinct, frugal, mix, one_permutation, pack_rows, sorted_sets
from .near import components, fixed_filter
from .near_docs import band_hashes, list_array, sketch_longs

U64 = np.uint64
SHINGLE, PERCENT = 8, 80
ROWS, BANDS = 4, 18
LINE_BLOCK = 1 << 17
#: Registers and bits of the sketches of candidate lines, and differing samples of these that a pair may have: at the threshold 48 are expected, with a deviation of up to 6.2 for large sets; five of them are allowed.
SLOTS, SAMPLE_BITS, SKETCH_LIMIT = 256, 4, 79


def line_spans(block: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends, texts, numbers within the text and hashes of the lines that hold a word."""
    data = block.data
    newline = np.flatnonzero(data == 10)
    edges = distinct(np.concatenate([block.bounds, newline, newline + 1]))
    if len(edges) < 2:
        none = np.zeros(0, dtype=np.int64)
        return none, none, none, none, none.astype(U64)
    solid = ~((data == 32) | (data - np.uint8(9) < 5))
    keep = np.maximum.reduceat(solid.view(np.uint8), edges[:-1]) > 0
    lo, hi = edges[:-1][keep], edges[1:][keep]
    owner = np.searchsorted(block.bounds, lo, "right") - 1
    number = np.searchsorted(newline, lo) - np.searchsorted(newline, block.bounds[owner])
    return lo, hi, owner, number, block.span_hashes(lo, hi)


def character_sets(block: Block, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes (with repeats) of the given spans and their bounds."""
    sums, down = block.prefix_sums()  # kept by the block
    if len(block.data) and block.data.max() < 0x80:
        at, down, a, b = sums, down[: len(block.data)], lo, hi
    else:
        heads = np.flatnonzero((block.data & 0xC0) != 0x80)
        at = np.append(sums[heads], sums[-1])  # up to each character
        a, b, down = np.searchsorted(heads, lo), np.searchsorted(heads, hi), down[heads]
    counts = np.where(b - a >= SHINGLE, b - a - SHINGLE + 1, (b > a).astype(np.int64))
    bounds = np.concatenate([[0], np.cumsum(counts)])
    if not bounds[-1]:
        return np.zeros(0, dtype=U64), bounds
    runs = at[SHINGLE:] - at[:-SHINGLE] if len(at) > SHINGLE else np.zeros(0, dtype=U64)
    runs *= down[: len(runs)]
    short = np.flatnonzero((b - a < SHINGLE) & (b > a))
    whole = (at[b[short]] - at[a[short]]) * down[a[short]] ^ U64(0x2545F4914F6CDD1D)
    parts = [runs[x:y] for x, y in zip(a.tolist(), (a + counts).tolist(), strict=True)]
    for k, i in enumerate(short.tolist()):
        parts[i] = whole[k : k + 1]
    out = np.concatenate(parts)
    spread = out >> U64(29)
    out *= U64(0xD6E8FEB86659FD93)
    out ^= spread
    return out, bounds


def line_sets(block: Block) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of whole lines, and their bounds."""
    return sorted_sets(*character_sets(block, block.bounds[:-1], block.bounds[1:]))


def line_table(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, number and id (hash) of every line that holds a word; bands (packed longs) of its signature at one row of each line at least."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column("key")
            for block in blocks(batch.column("text"), LINE_BLOCK):
                lo, hi, owner, number, ids = line_spans(block)
                one = np.sort(np.unique(ids, return_index=True)[1])
                minima = one_permutation(*character_sets(block, lo[one], hi[one]), ROWS * BANDS)
                bands = pack_rows(band_hashes(minima.astype(U64), ROWS, BANDS))
                rest = np.setdiff1d(np.arange(len(ids)), one, assume_unique=True)
                place = np.concatenate([one, rest])
                if len(rest):
                    bands = pa.concat_arrays([bands, pa.nulls(len(rest), pa.binary())])
                yield pa.RecordBatch.from_arrays([keys.take(pa.array(owner[place] + block.first)), pa.array(number[place].astype(np.int32)), pa.array(ids[place].view(np.int64)), bands], names=["key", "number", "id", "bands"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(frugal(run), f"key {kind}, number int, id long, bands binary")


def line_texts(docs: DataFrame, wanted: DataFrame, text: str = "text") -> DataFrame:
    """id and text of the lines whose hash may be among the column id of wanted, each at least once."""
    likely = fixed_filter(wanted, "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("text")):
                lo, hi, _, _, ids = line_spans(block)
                some = np.flatnonzero(likely.passes(ids))
                ids, one = np.unique(ids[some], return_index=True)
                raw, one = block.data.tobytes(), some[one]
                yield pa.RecordBatch.from_arrays([pa.array(ids.view(np.int64)), pa.array([raw[a:b] for a, b in zip(lo[one].tolist(), hi[one].tolist(), strict=True)], type=pa.binary())], names=["id", "line"])

    return docs.select(F.col(text).alias("text")).mapInArrow(frugal(run), "id long, line binary")


def line_sketches(lines: DataFrame) -> DataFrame:
    """id, size of the set and sketch of lines."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("line"), LINE_BLOCK):
                values, bounds = line_sets(block)
                sketch = list_array(sketch_longs(one_permutation(values, bounds, SLOTS).astype(U64)))
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(block.first, block.n), pa.array(np.diff(bounds)), sketch], names=["id", "size", "sketch"])

    return lines.select("id", "line").mapInArrow(frugal(run), "id long, size long, sketch array<long>")


def line_roots(docs: DataFrame, table: DataFrame, key: str, text: str) -> DataFrame:
    """node and root of every line hash that is linked with another line; table: the rows of line_table."""
    places = table.select("key", "number", "id")
    texts: list[DataFrame] = []

    def describe(ids: DataFrame) -> DataFrame:
        """Fetch the candidates' texts once, and give them sketches that tell similarities just below the wanted one."""
        wanted = ids.withColumnRenamed("id", "of")
        # One document for each wanted line is enough to read its text from.
        holders = prefilter(places, "id", wanted.withColumnRenamed("of", "key")).join(wanted, F.col("id") == F.col("of"), "left_semi").groupBy("id").agg(F.min("key").alias("key"))
        holders = settle(holders.select("key").distinct())
        rows = docs.select(F.col(key).alias("key"), F.col(text).alias("text"))
        some = line_texts(prefilter(rows, "key", holders), ids).join(wanted, F.col("id") == F.col("of"), "left_semi")
        texts.append(settle_table(some.groupBy("id").agg(F.first("line").alias("item")), "lines"))
        return line_sketches(texts[0].withColumnRenamed("item", "line"))

    items = table.where("bands is not null").select("id", "bands")
    return components(items, lambda ids: texts[0], line_sets, SLOTS * SAMPLE_BITS // 64, SAMPLE_BITS, SKETCH_LIMIT, PERCENT, describe)


def lost_lines(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and the list of (number, id) of the lines that each document loses."""
    table = settle_table(line_table(docs, key, text), "lines-signed", ("id", "bands"))
    roots = line_roots(docs, table, key, text)
    places = table.select("key", "number", "id")
    first = places.groupBy("id").agg(F.min(F.struct("key", "number")).alias("first"), F.count(F.lit(1)).alias("n"))
    named = first.join(roots, F.col("id") == F.col("node"), "left").select("id", "first", "n", F.coalesce("root", "id").alias("root"), F.col("root").isNotNull().alias("linked"))
    named = settle_table(named.where("n > 1 or linked"), "line-counts")
    keeper = named.groupBy("root").agg(F.min("first").alias("keeper"))
    known = settle_table(named.join(keeper, "root").select(F.col("id").alias("of"), "keeper"), "line-keepers")
    lost = prefilter(places, "id", known.select(F.col("of").alias("key"))).join(known, F.col("id") == F.col("of"))
    lost = lost.where(~F.struct("key", "number").eqNullSafe(F.col("keeper")))
    return lost.groupBy("key").agg(F.collect_set(F.struct("number", "id")).alias("lost"))


def strip_lines(texts: pa.Array, lost: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Texts without the lines (number, id) listed for them, how many each lost, and their lengths in characters."""
    cells = lost.flatten()
    sizes = np.diff(lost.offsets.to_numpy())
    owner = np.repeat(np.arange(len(texts)), sizes).astype(U64)
    salt = U64(0x9E3779B97F4A7C15)
    marks = mix(mix(owner * salt ^ cells.field("number").to_numpy().astype(U64)) ^ cells.field("id").to_numpy().view(U64))
    parts, counts, lengths = [], [], []
    for block in blocks(texts, LINE_BLOCK):
        lo, hi, row, number, ids = line_spans(block)
        gone = np.isin(mix(mix((row + block.first).astype(U64) * salt ^ number.astype(U64)) ^ ids), marks)
        lo, hi, row = lo[gone], hi[gone], row[gone]
        end = block.bounds[1:]
        edge = np.bincount(lo, minlength=len(block.data) + 2) - np.bincount(np.minimum(hi + 1, end[row]), minlength=len(block.data) + 2)
        keep = np.cumsum(edge)[: len(block.data)] == 0
        # Where the last line goes, so does the newline before it, unless nothing is left.
        tail = np.unique(row[hi == end[row]])
        kept = np.concatenate([[0], np.cumsum(keep)])
        for i in tail[kept[end[tail]] > kept[block.bounds[tail]]].tolist():
            last = block.bounds[i] + np.flatnonzero(keep[block.bounds[i] : end[i]])[-1]
            keep[last] = False
        kept = np.concatenate([[0], np.cumsum(keep)])[block.bounds]
        left = block.data[keep]
        heads = np.concatenate([[0], np.cumsum((left & 0xC0) != 0x80)])[kept]
        parts.append(pa.LargeBinaryArray.from_buffers(pa.large_binary(), block.n, [None, pa.py_buffer(kept.astype(np.int64).tobytes()), pa.py_buffer(left.tobytes())]))
        counts.append(np.bincount(row, minlength=block.n))
        lengths.append(np.diff(heads))
    return pa.concat_arrays(parts).cast(pa.large_string()), np.concatenate(counts), np.concatenate(lengths)


def dedup_lines(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with one line of each component left in all texts, and the column ``lines_lost`` (long) of their numbers."""
    lost = settle_table(lost_lines(docs, key, text), "lost-lines")
    wide = docs.drop("lines_lost")
    packed = wide.select(F.struct(*[F.col(f"`{c}`") for c in wide.columns]).alias("row"))
    maybe, whole = split(packed, F.col("row")[key], lost)
    hit = maybe.join(lost, F.col("row")[key].eqNullSafe(lost["key"]), "left").select("row", "lost")
    joined = hit.select(*[F.col("row")[c].alias(c) for c in wide.columns], F.col("lost").alias("lines_lost"))
    names, chars = wide.columns, "n_chars" in wide.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts, out = np.zeros(batch.num_rows, dtype=np.int64), batch.select(names)
            hit = np.flatnonzero(batch.column("lines_lost").is_valid().to_numpy(zero_copy_only=False))
            if len(hit):
                at = out.schema.get_field_index(text)
                fresh, lost, sizes = strip_lines(out.column(at).take(pa.array(hit)), batch.column("lines_lost").take(pa.array(hit)))
                counts[hit] = lost
                # The changed rows are put in place of the old ones by a take from both.
                place = np.arange(batch.num_rows)
                place[hit] = batch.num_rows + np.arange(len(hit))
                both = pa.concat_arrays([out.column(at), fresh.cast(out.column(at).type)])
                out = out.set_column(at, out.schema.field(at), both.take(pa.array(place)))
                if chars:
                    at = out.schema.get_field_index("n_chars")
                    changed = pa.array(np.where(lost > 0, sizes, 0), mask=lost == 0, type=out.schema.field(at).type)
                    old = out.column(at).take(pa.array(hit))
                    both = pa.concat_arrays([out.column(at), pc.coalesce(changed, old)])
                    out = out.set_column(at, out.schema.field(at), both.take(pa.array(place)))
            yield out.append_column("lines_lost", pa.array(counts))

    spec = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in wide.schema.fields) + ", lines_lost long"
    untouched = whole.select(*[F.col("row")[c].alias(c) for c in names], F.lit(0).cast("bigint").alias("lines_lost"))
    return joined.mapInArrow(frugal(run), spec).union(untouched)
