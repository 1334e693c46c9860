"""MinHash near-dedup of documents with SuperMinHash signatures.

A document's set holds its distinct runs of WIDTH words (ASCII lower case); one of fewer
words has the whole sequence as its only member. For a signature of SLOTS registers every
member draws, from its hash, a random permutation of the registers step by step and offers
``step + random`` to the register at each step. Offers of later steps can't win once all
registers hold an earlier step, so the walk ends there: after one or two steps for most
texts. The permutations are correlated across registers, which lowers the variance of the
similarity estimate. Bands of ROWS registers make candidates, sketches of four bits a
register thin them, and full sets confirm every link: 100 * common >= PERCENT * union.

Documents with equal sets are one item from the start, and a group of near copies is linked
by stars (see near), so that a group costs its size.

Defined results: null and empty texts and texts of white space alone have an empty set and
link with nothing; rows without a key link with nothing and keep a null component; repeated
rows share their component; the smallest key of a component is the one that stays; an empty
table gives an empty result; extra columns aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bloom import prefilter, split
from .cluster import settle, settle_table
from .kernels import Block, blocks, frugal, mix, pack_rows, set_prints, sorted_sets, windows
from .near import components

U64 = np.uint64
PERCENT = 80
SLOTS, ROWS, BANDS = 256, 4, 18
SAMPLE_BITS = 4
#: Differing samples of 256 that a pair may have: at the threshold 48 are expected, with a deviation of 4.6 for small sets and up to the binomial one of 6.2 for large sets; five of the latter are allowed.
SKETCH_LIMIT = 79


def shingle_sets(block: Block, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text and their bounds."""
    starts, ends, firsts = block.spans()
    return sorted_sets(*windows(block.span_hashes(starts, ends, lower=True), firsts, width, whole_if_short=True))


def superminhash(values: np.ndarray, bounds: np.ndarray, slots: int = SLOTS) -> np.ndarray:
    """Registers (texts x slots): the step in the high byte, the random part below; all ones for empty sets."""
    n = len(bounds) - 1
    best = np.full(n * slots, ~U64(0))
    owner = np.repeat(np.arange(n), np.diff(bounds))
    state, drawn = values, []
    for step in range(slots):
        if not len(owner):
            break
        state = mix(state)
        pick = step + ((state >> U64(32)) * U64(slots - step) >> U64(32)).astype(np.int64)
        place = pick
        for earlier in range(step - 1, -1, -1):  # where the swaps of earlier steps have put this place
            place = np.where(drawn[earlier] == place, earlier, place)
        np.minimum.at(best, owner * slots + place, U64(step) << U64(56) | mix(state ^ U64(0xA5A5A5A5)) >> U64(8))
        drawn.append(pick)
        there = np.unique(owner)
        done = np.zeros(n, dtype=bool)
        done[there] = (best.reshape(n, slots)[there] >> U64(56)).max(axis=1) <= step
        go = ~done[owner]
        if not go.all():
            owner, state, drawn = owner[go], state[go], [x[go] for x in drawn]
    return best.reshape(n, slots)


def band_hashes(registers: np.ndarray, rows: int, bands: int) -> np.ndarray:
    grouped = registers[:, : rows * bands].reshape(len(registers), bands, rows)
    total = np.tile(np.arange(1, bands + 1, dtype=U64), (len(registers), 1))
    for r in range(rows):
        total = mix(total ^ grouped[:, :, r])
    return total


def sketch_longs(registers: np.ndarray) -> np.ndarray:
    """SAMPLE_BITS hashed bits of each register, whose number is a multiple of 16."""
    each = 64 // SAMPLE_BITS
    samples = (mix(registers) & U64((1 << SAMPLE_BITS) - 1)).reshape(len(registers), -1, each)
    return np.bitwise_or.reduce(samples << (np.arange(each, dtype=U64) * U64(SAMPLE_BITS)), axis=2)


def list_array(rows: np.ndarray) -> pa.Array:
    n, width = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * width + 1, width, dtype=np.int32)), pa.array(np.ascontiguousarray(rows).reshape(-1).view(np.int64)))


def signatures(docs: DataFrame, key: str, text: str, width: int) -> DataFrame:
    """key, size, set print (two longs), sketch and bands (packed longs) of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("text")):
                sets, bounds = shingle_sets(block, width)
                sizes, prints, registers = np.diff(bounds), set_prints(sets, bounds), superminhash(sets, bounds)
                bands = pack_rows(band_hashes(registers, ROWS, BANDS))
                columns = [batch.column("key").slice(block.first, block.n), pa.array(sizes), pa.array(prints[:, 0].view(np.int64)), pa.array(np.ascontiguousarray(prints[:, 1]).view(np.int64)), list_array(sketch_longs(registers)), bands]
                yield pa.RecordBatch.from_arrays(columns, names=["key", "size", "print1", "print2", "sketch", "bands"])

    named = docs.select(F.col(key).cast("bigint").alias("key"), F.col(text).alias("text"))
    return named.mapInArrow(frugal(run), "key long, size long, print1 long, print2 long, sketch array<long>, bands binary")


def near_components(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 5) -> DataFrame:
    """key, n_shingles, component_id and kept of every row of docs."""
    signed = settle_table(signatures(docs, key, text, width), "signatures", ("print1", "print2", "bands"))
    usable = signed.where("key is not null and size > 0")
    items = usable.groupBy("print1", "print2").agg(F.min("key").alias("id"), F.first("size").alias("size"), F.first("sketch").alias("sketch"), F.first("bands").alias("bands"))
    items = settle_table(items, "items", ("print1", "print2", "bands"))
    texts = docs.select(F.col(key).cast("bigint").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("item")).where("id is not null")

    def texts_of(ids: DataFrame) -> DataFrame:
        wanted = settle(ids.select(F.col("id").alias("key")))
        return prefilter(texts, "id", wanted).join(wanted, F.col("id") == F.col("key"), "left_semi")

    roots = components(items.select("id", "size", "sketch", "bands"), texts_of, lambda block: shingle_sets(block, width), SLOTS * SAMPLE_BITS // 64, SAMPLE_BITS, SKETCH_LIMIT, PERCENT)
    grouped = items.join(roots, F.col("id") == F.col("node"), "left").select("print1", "print2", F.coalesce("root", "id").alias("component"))
    found = signed.join(grouped, ["print1", "print2"], "left")
    component = F.when(F.col("key").isNotNull(), F.when(F.col("size") > 0, F.col("component")).otherwise(F.col("key")))
    out = found.select(F.col("key").alias(key), F.col("size").alias("n_shingles"), component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col(key) == F.col("component_id"), F.lit(True)))


def drop_near_copies(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 5) -> DataFrame:
    """docs without those whose component has a smaller key; rows without a key stay.

    Only the keys of dropped documents travel: rows that a filter on them lets through go to the anti-join, the others stay where they are.
    """
    lost = settle(near_components(docs, key, text, width).where("not kept").select(F.col(key).alias("key")).distinct())
    maybe, stay = split(docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")), F.col("row")[key].cast("bigint"), lost)
    left = maybe.join(lost, F.col("row")[key].cast("bigint") == lost["key"], "left_anti").union(stay)
    return left.select(*[F.col("row")[c].alias(c) for c in docs.columns])
