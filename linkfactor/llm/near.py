"""Links between near copies, from banded signatures to components, as DataFrame plans.

Items are distinct things (exact copies are one item): ``id`` (long), ``size`` of its set,
``sketch`` (longs of 2- or 4-bit signature samples) and ``bands`` (packed longs; items that
share one are candidates). No step lists the pairs of a group as such:

1. Each bucket links its members to its smallest and its largest member only, where the
   sketches allow the wanted similarity; these pairs are verified on full sets.
2. Their components are found by alternating star contractions.
3. What remains are pairs of one bucket in different components. Members outside the
   bucket's commonest component (outsiders) are compared with all others in cells of bounded
   size: an outsider goes to every piece of the bucket, the other members to the few pieces of
   the outsiders, so a bucket of a million copies and one outsider costs a million rows. A
   cell first thins by sizes and sketches; only members with a likely mate fetch their texts,
   and the cell's pairs are then verified on full sets, save those that are connected by then.

So no link found by the bands is lost, no pair becomes a row unless it is a link of step 1 or
3, and a group of near copies costs its size, not its square.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .cluster import settle
from .kernels import Block, Overlap, blocks, distinct, frugal, mix, shared_by_pair, similar, unpack_rows

U64 = np.uint64
#: Bits (as a power of two) of the filters that travel to every task: 2 MB, whatever the input.
FILTER_POWER = 24
#: Packed bands that a worker holds back before it sends them, and the ranges of bands that a partition decides on one after the other.
HELD, RANGES = 500_000, 16
#: Members of a bucket, and shingles of their sets, that are compared in one piece.
CELL, CELL_SHINGLES = 1500, 1 << 21
#: Pairs whose sketches are compared at a time, bytes of text whose sets are held at a time, and sets that one is compared with at a time.
PAIRS, SET_BYTES, MATES = 1 << 16, 4 << 20, 256

#: The lowest bit of each sample, by the bits of a sample.
_LOW_BITS = {2: 0x5555555555555555, 4: 0x1111111111111111}

Sets = Callable[[Block], tuple[np.ndarray, np.ndarray]]


def mismatches(a: Column, b: Column, longs: int, bits: int) -> Column:
    """How many samples of so many bits differ between two sketches."""
    total = F.lit(0)
    for i in range(longs):
        x = F.get(a, i).bitwiseXOR(F.get(b, i))
        for step in (1, 2)[: bits // 2]:
            x = x.bitwiseOR(F.shiftrightunsigned(x, step))
        total = total + F.bit_count(x.bitwiseAND(F.lit(_LOW_BITS[bits])))
    return total


@dataclass(frozen=True)
class FixedFilter:
    """A Bloom filter of two hashes and fixed size, broadcast; past some million values it passes more, and an exact join follows it."""

    words: Broadcast

    def passes(self, values: np.ndarray) -> np.ndarray:
        held, hit = self.words.value, np.ones(len(values), dtype=bool)
        for spot in _spots(values):
            hit &= (held[spot >> 6] >> (spot & 63).astype(U64)) & U64(1) == 1
        return hit


def _spots(values: np.ndarray) -> list[np.ndarray]:
    return [(mix(values.view(U64) ^ U64(salt)) >> U64(64 - FILTER_POWER)).astype(np.int64) for salt in (11, 12)]


def fixed_filter(frame: DataFrame, column: str) -> FixedFilter:
    """The filter of a column of longs; the driver sees its words only, whose number is bounded."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spot = np.unique(np.concatenate(_spots(batch.column(column).to_numpy())))
            word, first = np.unique(spot >> 6, return_index=True)
            bits = np.bitwise_or.reduceat(U64(1) << (spot & 63).astype(U64), first) if len(first) else np.zeros(0, dtype=U64)
            yield pa.RecordBatch.from_arrays([pa.array(word), pa.array(bits.view(np.int64))], names=["word", "bits"])

    marks = frame.select(column).mapInArrow(frugal(mark), "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()
    words = np.zeros(1 << (FILTER_POWER - 6), dtype=U64)
    words[marks.column("word").to_numpy()] = marks.column("bits").to_numpy().view(U64)
    return FixedFilter(frame.sparkSession.sparkContext.broadcast(words))


def _ends(entries: np.ndarray) -> np.ndarray:
    """Of ascending distinct entries the first and the last of each band."""
    band = entries >> U64(16)
    first = np.ones(len(band), dtype=bool)
    first[1:] = band[1:] != band[:-1]
    return entries[first | np.append(first[1:], True)]


def shared_bands(items: DataFrame) -> DataFrame:
    """Bands (column ``band``, the upper 48 bits) that two different ids have.

    An entry is one long: the band's upper 48 bits, and 16 bits of a hash of id and band that
    tell ids apart (two ids agree there in one band of 65,000, for each band anew). A task
    sends at most two entries of a band at a time, packed by the range of bands that decides
    on them, so a band that many items share costs each task two numbers.
    """
    parts = max(1, int(items.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranges = parts * RANGES

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            flat, row = unpack_rows(batch.column("bands"))
            tag = mix(batch.column("id").to_numpy().view(U64)[row] ^ flat) & U64(0xFFFF)
            held.append(flat & ~U64(0xFFFF) | tag)
            n += len(flat)
            if n > HELD:  # what a worker holds back stays small
                yield pack(held)
                held, n = [], 0
        if n:
            yield pack(held)

    def pack(held: list[np.ndarray]) -> pa.RecordBatch:
        entries = _ends(distinct(np.concatenate(held)))
        cuts = np.searchsorted(((entries >> U64(32)) * U64(ranges) >> U64(32)).astype(np.int64), np.arange(ranges + 1))
        full = np.flatnonzero(np.diff(cuts))
        ends = np.append(cuts[full], len(entries)).astype(np.int32) * 8
        packed = pa.Array.from_buffers(pa.binary(), len(full), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(entries.tobytes())])
        return pa.RecordBatch.from_arrays([pa.array(full.astype(np.int32)), packed], names=["part", "packed"])

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held = None, []
        for batch in batches:
            for number, packed in zip(batch.column("part").to_pylist(), batch.column("packed"), strict=True):
                if number != part and held:
                    yield shared(held)
                    held = []
                part = number
                held.append(np.frombuffer(packed.as_buffer(), dtype=U64))
        if held:
            yield shared(held)

    def shared(held: list[np.ndarray]) -> pa.RecordBatch:
        band = distinct(np.concatenate(held)) >> U64(16)
        return pa.RecordBatch.from_arrays([pa.array(distinct(band[1:][band[1:] == band[:-1]]).view(np.int64))], names=["band"])

    sent = items.select("id", "bands").mapInArrow(frugal(send), "part int, packed binary")
    return sent.repartition(parts, "part").sortWithinPartitions("part").mapInArrow(frugal(decide), "band long")


def band_members(items: DataFrame, shared: DataFrame) -> DataFrame:
    """band and id of all items in shared bands: a filter of fixed size first, then the exact join."""
    likely = fixed_filter(shared, "band")

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, row = unpack_rows(batch.column("bands"))
            band = flat >> U64(16)
            hit = np.flatnonzero(likely.passes(band))
            band, item = band[hit], batch.column("id").to_numpy()[row[hit]]
            _, one = np.unique(mix(band) ^ item.view(U64), return_index=True)
            yield pa.RecordBatch.from_arrays([pa.array(band[one].view(np.int64)), pa.array(item[one])], names=["band", "id"])

    some = items.select("id", "bands").mapInArrow(frugal(explode), "band long, id long")
    # An item may come from many tasks.
    return some.join(shared.withColumnRenamed("band", "key"), F.col("band") == F.col("key"), "left_semi").distinct()


def connected(edges: DataFrame) -> DataFrame:
    """node and root (the smallest node of its component) of every node on an edge (a, b)."""
    now = settle(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct())
    while _unsettled(now):
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy(F.col("u").alias("k")).agg(F.min("v").alias("m"))
        large = both.where("v > u").join(low, F.col("u") == F.col("k")).select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        large = settle(large)
        low = large.groupBy(F.col("u").alias("k")).agg(F.min("v").alias("m"))
        small = large.join(low, F.col("u") == F.col("k"))
        small = small.select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u != v")
        now = settle(small.distinct())
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def _unsettled(edges: DataFrame) -> bool:
    """Whether a node still points to two others, or to one that points further."""
    ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("out"), F.lit(0).alias("held")).union(edges.select("v", F.lit(0), F.lit(1)))
    seen = ends.groupBy("node").agg(F.sum("out").alias("out"), F.max("held").alias("held"))
    return seen.where("out > 1 or (out = 1 and held = 1)").limit(1).count() > 0


def _text_sets(texts: pa.Array, sets: Sets) -> list[np.ndarray]:
    out = []
    for block in blocks(texts):
        values, bounds = sets(block)
        out += [values[i:j] for i, j in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
    return out


def _similar(sets: Sets, percent: int):
    """Of pairs (a, b, item_a, item_b) those whose sets are similar; pairs are taken while their texts are within SET_BYTES."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = (batch.column(name).dictionary_encode() for name in ("item_a", "item_b"))  # a hub's text comes many times
            sizes = [pc.binary_length(side.dictionary).to_numpy()[side.indices.to_numpy()] for side in (one, two)]
            load, at = np.cumsum(sizes[0].astype(np.int64) + sizes[1]), 0
            while at < batch.num_rows:
                until = min(at + 8192, max(at + 1, int(np.searchsorted(load, (load[at - 1] if at else 0) + SET_BYTES, "right"))))
                sides = []
                for side in (one, two):
                    used, place = np.unique(side.indices.to_numpy()[at:until], return_inverse=True)
                    found = _text_sets(side.dictionary.take(pa.array(used)), sets)
                    sides.append([found[i] for i in place.tolist()])
                union = np.array([len(x) for x in sides[0]]) + np.array([len(x) for x in sides[1]])
                shared = shared_by_pair(*sides)
                keep = 100 * shared >= percent * (union - shared)
                yield batch.select(["a", "b"]).slice(at, until - at).filter(pa.array(keep))
                at = until

    return run


def _cells(here: DataFrame) -> DataFrame:
    """Rows of mixed buckets by cell: a cell is a piece of the outsiders (rows with asks) and a piece of all members."""
    asks = F.col("root") != F.col("main")

    def pieces(n: str, size: str) -> Column:
        return F.greatest(F.ceil(F.col(n) / F.lit(float(CELL))), F.ceil(F.col(size) / F.lit(float(CELL_SHINGLES)))).cast("bigint")

    cut = here.withColumn("askers", pieces("n_out", "size_out")).withColumn("pieces", pieces("n", "size_all"))
    mine, own = F.pmod(F.xxhash64("id"), F.col("pieces")), F.pmod(F.xxhash64(F.lit(1), "id"), F.col("askers"))
    held = F.transform(F.sequence(F.lit(0).cast("bigint"), F.col("askers") - 1), lambda k: F.struct(F.lit(False).alias("asks"), (k * F.col("pieces") + mine).alias("at")))
    asked = F.transform(F.sequence(F.lit(0).cast("bigint"), F.col("pieces") - 1), lambda k: F.struct(F.lit(True).alias("asks"), (own * F.col("pieces") + k).alias("at")))
    rows = cut.withColumn("place", F.explode(F.when(asks, F.concat(held, asked)).otherwise(held)))
    return rows.select(F.xxhash64("band", "place.at").alias("cell"), "band", F.col("place.at").alias("at"), F.col("place.asks").alias("asks"), "id", "root", "main", "info", "bands")


_PLACES = ("cell", "band", "at", "asks", "id", "root", "main")


def _by_cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Whole cells, as many at a time as a batch ends; rows come sorted by cell."""
    rest: list[pa.Table] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([batch])
        cell = table.column("cell").to_numpy()
        cut = int(np.searchsorted(cell, cell[-1]))
        if cut or (rest and rest[0].column("cell")[0].as_py() != cell[0]):
            yield pa.concat_tables([*rest, table.slice(0, cut)]).combine_chunks()
            rest = []
        rest.append(table.slice(cut))
    if rest:
        yield pa.concat_tables(rest).combine_chunks()


def _likely_pairs(table: pa.Table, bits: int, limit: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of rows (an asker and another member of its cell) in different components that sizes and sketches allow, each at the least band that the two share."""
    cell, band, at, asks, ids, root, main, size = (table.column(k).to_numpy() for k in (*_PLACES, "size"))
    n = len(ids)
    fresh = np.ones(n, dtype=bool)
    fresh[1:] = (cell[1:] != cell[:-1]) | (band[1:] != band[:-1]) | (at[1:] != at[:-1])
    starts = np.flatnonzero(fresh)
    first = starts[np.cumsum(fresh) - 1]
    # Members come before askers in each cell.
    members = np.add.reduceat((~asks).astype(np.int64), starts)[np.cumsum(fresh) - 1] if n else np.zeros(0, dtype=np.int64)
    askers = np.flatnonzero(asks)
    sketch = table.column("sketch").combine_chunks().flatten().to_numpy().view(U64).reshape(n, -1) if n else np.zeros((0, 1), dtype=U64)
    bands = table.column("bands")
    found: list[tuple[np.ndarray, np.ndarray]] = []
    load, k = np.cumsum(members[askers]), 0
    while k < len(askers):
        until = max(k + 1, int(np.searchsorted(load, (load[k - 1] if k else 0) + PAIRS, "right")))
        some = askers[k:until]
        counts = members[some]
        i = np.repeat(some, counts)
        j = np.arange(len(i)) - np.repeat(np.cumsum(counts) - counts, counts) + first[i]
        k = until
        ok = (root[i] != root[j]) & ((root[j] == main[j]) | (ids[i] < ids[j])) & (100 * np.minimum(size[i], size[j]) >= percent * np.maximum(size[i], size[j]))
        i, j = i[ok], j[ok]
        differ = np.zeros(len(i), dtype=np.int64)
        for word in range(sketch.shape[1]):
            x = sketch[i, word] ^ sketch[j, word]
            for step in (1, 2)[: bits // 2]:
                x |= x >> U64(step)
            differ += np.bitwise_count(x & U64(_LOW_BITS[bits]))
        ok = np.flatnonzero(differ <= limit)
        i, j = i[ok], j[ok]
        if len(i):
            rows = np.unique(np.concatenate([i, j]))
            own = dict(zip(rows.tolist(), map(frozenset, bands.take(pa.array(rows)).to_pylist()), strict=True))
            least = np.array([min(own[x] & own[y]) for x, y in zip(i.tolist(), j.tolist(), strict=True)])
            ok = least == band[i]
            found.append((i[ok], j[ok]))
    none = np.zeros(0, dtype=np.int64)
    return tuple(np.concatenate([f[x] for f in found]) if found else none for x in range(2))


def compare_cells(cells: DataFrame, texts_of: Callable[[DataFrame], DataFrame], sets: Sets, bits: int, limit: int, percent: int) -> DataFrame:
    """Links (a, b) in the cells of mixed buckets."""
    shape = "cell long, band long, at long, asks boolean, id long, root long, main long, size long, sketch array<long>, bands array<long>"
    names = [f.split()[0] for f in shape.split(", ")]
    order = ("cell", "band", "at", "asks")
    flat = cells.select(*_PLACES, F.col("info.size").alias("size"), F.col("info.sketch").alias("sketch"), "bands")

    def thin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _by_cell(batches):
            i, j = _likely_pairs(table, bits, limit, percent)
            if len(i):
                yield from table.take(pa.array(np.unique(np.concatenate([i, j])))).combine_chunks().select(names).to_batches()

    some = settle(flat.repartition("cell").sortWithinPartitions(*order).mapInArrow(frugal(thin), shape))

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        overlap = Overlap()
        for table in _by_cell(batches):
            i, j = _likely_pairs(table, bits, limit, percent)
            ids, roots, cell = (table.column(k).to_numpy() for k in ("id", "root", "cell"))
            items = table.column("item").combine_chunks()
            above: dict[int, int] = {}

            def find(x: int) -> int:
                while (y := above.get(x, x)) != x:
                    above[x] = above.get(y, y)
                    x = y
                return x

            out: list[tuple[int, int]] = []
            order = np.lexsort((j, i, cell[i]))
            for rows in np.split(order, np.flatnonzero(np.diff(cell[i[order]])) + 1) if len(i) else ():
                members = np.unique(np.concatenate([i[rows], j[rows]]))
                held = dict(zip(members.tolist(), _text_sets(items.take(pa.array(members)), sets), strict=True))
                for part in np.split(rows, np.flatnonzero(np.diff(i[rows])) + 1):
                    x = int(i[part[0]])
                    mine = find(int(roots[x]))
                    mates = [y for y in j[part].tolist() if find(int(roots[y])) != mine]
                    for at in range(0, len(mates), MATES):
                        some_mates = mates[at : at + MATES]
                        for y, ok in zip(some_mates, similar(overlap, held[x], [held[y] for y in some_mates], percent).tolist(), strict=True):
                            if ok and (a := find(int(roots[x]))) != (b := find(int(roots[y]))):
                                above[a] = b
                                out.append((min(int(ids[x]), int(ids[y])), max(int(ids[x]), int(ids[y]))))
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], type=pa.int64()) for k in (0, 1)], names=["a", "b"])

    texts = texts_of(some.select("id").distinct())
    full = some.join(texts.select(F.col("id").alias("text_id"), "item"), F.col("id") == F.col("text_id")).select(*names, "item")
    return full.repartition("cell").sortWithinPartitions(*order).mapInArrow(frugal(links), "a long, b long")


def components(items: DataFrame, texts_of: Callable[[DataFrame], DataFrame], sets: Sets, sketch_longs: int, sketch_bits: int, sketch_limit: int, percent: int = 80, describe: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """node and root of all items that are linked with another one.

    items: id and bands, and also size and sketch where ``describe`` doesn't give them.
    texts_of: takes ids (column id, distinct) and returns at least these with their texts (id, item), one row each.
    sets: the sorted sets of a block of texts; two items are linked if 100 * common >= percent * union.
    describe: takes the ids (column id) of the members of shared bands and returns id, size and sketch of each.
    """

    def may_link(x: str, y: str) -> Column:
        sizes = F.least(F.col(f"{x}.size"), F.col(f"{y}.size")) * 100 >= F.lit(percent) * F.greatest(F.col(f"{x}.size"), F.col(f"{y}.size"))
        return sizes & (mismatches(F.col(f"{x}.sketch"), F.col(f"{y}.sketch"), sketch_longs, sketch_bits) <= sketch_limit)

    shared = settle(shared_bands(items))
    members = settle(band_members(items, shared))
    # Of buckets with the same members (by ends, number and a hash of all) one is enough.
    sized = members.groupBy("band").agg(F.min("id").alias("lo"), F.max("id").alias("hi"), F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("id")).alias("print"))
    kept = sized.where("lo < hi").groupBy("lo", "hi", "n", "print").agg(F.min("band").alias("at")).select("at", "lo", "hi")
    members = settle(members.join(kept, F.col("band") == F.col("at")).select("band", "id", "lo", "hi"))
    ids = settle(members.select("id").distinct())
    known = describe(ids) if describe else items.select("id", "size", "sketch").join(ids, "id", "left_semi")
    known = settle(known.select(F.col("id").alias("of"), F.struct("id", "size", "sketch").alias("info")))

    star = members.select(F.explode(F.array(F.struct(F.col("lo").alias("a"), F.col("id").alias("b")), F.struct(F.col("id").alias("a"), F.col("hi").alias("b")))).alias("e")).select("e.a", "e.b").where("a < b").distinct()
    star = star.join(known.select(F.col("of").alias("p_of"), F.col("info").alias("p")), F.col("a") == F.col("p_of")).join(known.select(F.col("of").alias("q_of"), F.col("info").alias("q")), F.col("b") == F.col("q_of"))
    pairs = settle(star.where(may_link("p", "q")).select("a", "b"))
    texts = texts_of(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct())
    one = pairs.join(texts.select(F.col("id").alias("one"), F.col("item").alias("item_a")), F.col("a") == F.col("one"))
    two = one.join(texts.select(F.col("id").alias("two"), F.col("item").alias("item_b")), F.col("b") == F.col("two")).select("a", "b", "item_a", "item_b")
    links = settle(two.mapInArrow(frugal(_similar(sets, percent)), "a long, b long"))
    roots = connected(links)

    placed = settle(members.join(roots, F.col("id") == F.col("node"), "left").select("band", "id", F.coalesce("root", "id").alias("root")))
    shares = placed.join(known.select("of", F.col("info.size").alias("size")), F.col("id") == F.col("of")).groupBy("band", "root").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("size"))
    main = shares.groupBy(F.col("band").alias("of_band")).agg(F.max_by(F.struct("root", "n", "size"), F.struct("n", "root")).alias("main"), F.count(F.lit(1)).alias("roots"), F.sum("n").alias("n"), F.sum("size").alias("size_all"))
    mixed = main.where("roots > 1").select("of_band", F.col("main.root").alias("main"), "n", (F.col("n") - F.col("main.n")).alias("n_out"), "size_all", (F.col("size_all") - F.col("main.size")).alias("size_out"))
    here = settle(placed.join(mixed, F.col("band") == F.col("of_band")).drop("of_band"))
    own = here.groupBy(F.col("id").alias("owner")).agg(F.collect_set("band").alias("bands"))  # an item has few bands
    full = here.join(known, F.col("id") == F.col("of")).join(own, F.col("id") == F.col("owner")).drop("of", "owner")
    more = settle(compare_cells(_cells(full), texts_of, sets, sketch_bits, sketch_limit, percent))
    return connected(links.union(more)) if more.limit(1).count() else roots
