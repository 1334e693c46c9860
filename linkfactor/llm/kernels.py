"""Array kernels over the bytes of whole texts.

Texts come as Arrow columns and are cut into blocks of about a megabyte, so that the
temporary arrays (eight bytes a character) stay small; one text longer than that makes a
block of its own. Words are maximal runs outside ``[\\x20\\x09-\\x0D]``.
"""

from __future__ import annotations

import ctypes
import sys
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession

_libc = ctypes.CDLL(None) if sys.platform == "linux" else None
if hasattr(_libc, "mallopt"):
    # Arrays of a few megabytes are made and freed all the time: let glibc keep up to 32 MB instead of asking the kernel for each (M_TRIM_THRESHOLD, M_MMAP_THRESHOLD).
    _libc.mallopt(-1, 32 << 20)
    _libc.mallopt(-3, 16 << 20)

U64 = np.uint64
BLOCK_BYTES = 1 << 20
_STEP = U64(0x9E3779B97F4A7C15)
_BASE = 0xD6E8FEB86659FD93
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)

IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective finalizer of 64-bit integers (public splitmix constants)."""
    x = x + _STEP
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


_BYTE_CODES = mix(np.arange(1, 257, dtype=U64) * U64(0xA24BAED4963EE407))
_LOWER_CODES = _BYTE_CODES[LOWER]


class _Powers:
    """Powers of an odd number and of its inverse modulo 2**64, extended on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, dtype=U64)

    def upto(self, n: int) -> _Powers:
        if len(self.up) < n:
            size = 1 << int(n - 1).bit_length()
            for name, base in (("up", _BASE), ("down", _BASE_INVERSE)):
                factors = np.full(size, base, dtype=U64)
                factors[0] = 1
                setattr(self, name, np.cumprod(factors))
        return self


_POWERS = _Powers()


def release() -> None:
    """Give free memory back to the system."""
    pa.default_memory_pool().release_unused()
    if hasattr(_libc, "malloc_trim"):
        _libc.malloc_trim(0)


#: Bytes of a batch that Spark hands to a worker at a time, where the session has its default of 64 MB: long texts would make large batches, in the worker and in the executor beside it.
BATCH_BYTES, DEFAULT_BYTES = 6 << 20, "67108864b"
_BATCH_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def frugal(run: Callable) -> Callable:
    """The function of a mapInArrow, which at its end gives the worker's free memory back to the system (workers outlive their tasks). Batches of the session are kept small, as this setting can change at any time."""
    session = SparkSession.getActiveSession()
    if session is not None and session.conf.get(_BATCH_SETTING) == DEFAULT_BYTES:
        session.conf.set(_BATCH_SETTING, f"{BATCH_BYTES}b")

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped


class Block:
    """Consecutive texts as bytes; ``bounds`` has one entry more than there are texts."""

    def __init__(self, first: int, data: np.ndarray, bounds: np.ndarray) -> None:
        self.first, self.data, self.bounds, self.n = first, data, bounds, len(bounds) - 1
        self.sums: dict[bool, np.ndarray] = {}

    def spans(self, outside: np.ndarray = IS_SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, ends and the first word of each text (n + 1 entries) of runs not in ``outside``."""
        inside = ~outside[self.data]
        lo, hi = self.bounds[:-1], self.bounds[1:]
        filled = hi > lo
        lo, hi = lo[filled], hi[filled]
        begin, finish = inside.copy(), inside.copy()
        begin[1:] &= ~inside[:-1]
        finish[:-1] &= ~inside[1:]
        begin[lo] = inside[lo]
        finish[hi - 1] = inside[hi - 1]
        starts = np.flatnonzero(begin)
        return starts, np.flatnonzero(finish) + 1, np.searchsorted(starts, self.bounds)

    def prefix_sums(self, lower: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """Hash sums before each byte, and the factors that move a span's difference to the front."""
        powers = _POWERS.upto(len(self.data) + 1)
        if lower not in self.sums:
            self.sums[lower] = np.zeros(len(self.data) + 1, dtype=U64)
            terms = (_LOWER_CODES if lower else _BYTE_CODES)[self.data]
            terms *= powers.up[: len(self.data)]
            np.cumsum(terms, out=self.sums[lower][1:])
        return self.sums[lower], powers.down

    def span_hashes(self, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
        """One 64-bit hash for the bytes of each span, the same wherever the span stands."""
        sums, down = self.prefix_sums(lower)
        return mix((sums[ends] - sums[starts]) * down[starts] ^ (ends - starts).astype(U64))


def blocks(column: pa.Array | pa.ChunkedArray, limit: int = BLOCK_BYTES) -> Iterator[Block]:
    """Cut an Arrow string or binary column into blocks; a null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    column = column.cast(pa.large_binary())
    n = len(column)
    if not n:
        return
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + n + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, dtype=np.uint8)
    at = 0
    while at < n:
        until = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield Block(at, data[offsets[at] : offsets[until]], offsets[at : until + 1] - offsets[at])
        at = until


def windows(hashes: np.ndarray, firsts: np.ndarray, width: int, whole_if_short: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of every run of ``width`` words inside each text, and the bounds of each text's runs.

    With whole_if_short a text of fewer (but some) words has one run, the whole of it.
    """
    counts = np.diff(firsts)
    n = len(hashes)
    combined = np.zeros(max(0, n - width + 1), dtype=U64)
    for k in range(width):
        combined = (combined + hashes[k : n - width + 1 + k]) * U64(_BASE) if len(combined) else combined
    runs = np.maximum(counts - width + 1, 0)
    owner = np.repeat(np.arange(len(counts)), runs)
    bounds = np.concatenate([[0], np.cumsum(runs)])
    place = firsts[owner] + np.arange(len(owner)) - bounds[owner]
    out = mix(combined[place]) if len(place) else np.zeros(0, dtype=U64)
    if whole_if_short and (short := np.flatnonzero((counts > 0) & (counts < width))).size:
        extra = np.zeros(len(short), dtype=U64)
        for k in range(width - 1):
            has = counts[short] > k
            extra[has] = (extra[has] + hashes[firsts[short[has]] + k]) * U64(_BASE)
        extra = mix(extra ^ U64(0x5851F42D4C957F2D))
        runs[short] = 1
        merged = np.concatenate([[0], np.cumsum(runs)])
        full = np.empty(int(merged[-1]), dtype=U64)
        spot = np.ones(len(full), dtype=bool)
        spot[merged[short]] = False
        full[spot], full[merged[short]] = out, extra
        return full, merged
    return out, bounds


def distinct(values: np.ndarray) -> np.ndarray:
    """The distinct values in ascending order, by one sort."""
    values = np.sort(values)
    keep = np.ones(len(values), dtype=bool)
    keep[1:] = values[1:] != values[:-1]
    return values[keep]


def one_permutation(values: np.ndarray, bounds: np.ndarray, bins: int) -> np.ndarray:
    """One-permutation minima (texts x bins, 32 bits): every value offers its low half to the bin that its high half names.

    An empty bin takes over the first filled one in an order of its own (optimal
    densification), so two sets agree in each bin with a chance of their Jaccard similarity,
    whatever their sizes. Repeats don't change a minimum. Rows without a value hold the largest number.
    """
    none = np.uint32((1 << 32) - 1)
    n = len(bounds) - 1
    place = np.repeat(np.arange(0, n * bins, bins), np.diff(bounds))
    halves = np.ascontiguousarray(values).view(np.uint32)
    place += halves[1::2].astype(np.int64) * bins >> 32
    best = np.full(n * bins, none, dtype=np.uint32)
    np.minimum.at(best, place, halves[::2])
    best = best.reshape(n, bins)
    row, col = np.nonzero(best == none)
    some = np.diff(bounds)[row] > 0
    row, col = row[some], col[some]
    if len(row):
        turn = np.argsort(mix(np.arange(bins * bins, dtype=U64)).reshape(bins, bins), axis=1)
        out = best.copy()
        for step in range(bins):
            got = best[row, turn[col, step]]
            out[row, col] = got
            left = got == none
            if not left.any():
                break
            row, col = row[left], col[left]
        best = out
    return best


def pack_rows(rows: np.ndarray) -> pa.Array:
    """Each row of a matrix as one binary value."""
    n, width = len(rows), rows.shape[1] * rows.itemsize
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(0, n * width + 1, max(width, 1), dtype=np.int32)[: n + 1].tobytes()), pa.py_buffer(np.ascontiguousarray(rows).tobytes())])


def unpack_rows(column: pa.Array, kind: type = np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of all rows of a binary column, and the row of each."""
    ends = np.frombuffer(column.buffers()[1], dtype=np.int32)[column.offset : column.offset + len(column) + 1]
    flat = np.frombuffer(column.buffers()[2], dtype=np.uint8)[ends[0] : ends[-1]].view(kind) if len(column) and ends[-1] > ends[0] else np.zeros(0, dtype=kind)
    return flat, np.repeat(np.arange(len(column)), np.diff(ends) // np.dtype(kind).itemsize)


class Overlap:
    """Sizes of a set's intersections with many others, by a direct-mapped table of its values.

    A slot holds one value of the set or one that belongs to another slot; values that lost
    their slot to another are looked up by themselves. Sets hold distinct values.
    """

    def __init__(self) -> None:
        self._room(16)

    def _room(self, bits: int) -> None:
        self.bits, self.mask = bits, U64((1 << bits) - 1)
        self.empty = np.arange(1 << bits, dtype=U64) ^ U64(1)
        self.table = self.empty.copy()

    def counts(self, x: np.ndarray, others: list[np.ndarray]) -> np.ndarray:
        if not len(x):
            return np.zeros(len(others), dtype=np.int64)
        if (bits := len(x).bit_length() + 2) > self.bits:
            self._room(bits)
        slot = (x & self.mask).astype(np.int64)
        self.table[slot] = x
        lost = x[self.table[slot] != x]
        every = np.concatenate([*others, x[:1]])  # the end keeps all bounds inside
        hit = self.table[(every & self.mask).astype(np.int64)] == every
        if len(lost):
            hit |= np.isin(every, lost)
        self.table[slot] = self.empty[slot]
        sums = np.concatenate([[0], np.cumsum(hit)])
        bounds = np.concatenate([[0], np.cumsum([len(y) for y in others])])
        return sums[bounds[1:]] - sums[bounds[:-1]]


def shared_by_pair(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of left[p] and right[p], by one sort of all values behind the pair's number.

    Values are compared by as many of their bits as the numbers leave (51 with 8,192 pairs).
    """
    bits = max(1, (len(left) - 1).bit_length())
    both = []
    for side in (left, right):
        pair = np.repeat(np.arange(len(side), dtype=U64) << U64(64 - bits), [len(x) for x in side])
        both.append(np.concatenate([*side, np.zeros(0, dtype=U64)]) >> U64(bits) | pair)
    every = np.sort(np.concatenate(both))
    return np.bincount((every[1:][every[1:] == every[:-1]] >> U64(64 - bits)).astype(np.int64), minlength=len(left))


def similar(overlap: Overlap, x: np.ndarray, others: list[np.ndarray], percent: int) -> np.ndarray:
    """Which of the others share percent of the union with x."""
    n = overlap.counts(x, others)
    return 100 * n >= percent * (len(x) + np.array([len(y) for y in others], dtype=np.int64) - n)


def sorted_sets(values: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of each text in ascending order, and the new bounds."""
    values = values.copy()
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b - a > 1:
            values[a:b].sort()
    keep = np.ones(len(values), dtype=bool)
    keep[1:] = values[1:] != values[:-1]
    starts = bounds[:-1][np.diff(bounds) > 0]
    keep[starts] = True
    before = np.concatenate([[0], np.cumsum(keep)])
    return values[keep], before[bounds]


def set_prints(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """A 128-bit fingerprint (two columns) of each set, whatever the order of its values."""
    sums = np.zeros((len(bounds) - 1, 2), dtype=U64)
    for k, salt in enumerate((U64(0x2545F4914F6CDD1D), U64(0x9FB21C651E98DF25))):
        total = np.concatenate([np.zeros(1, dtype=U64), np.cumsum(mix(values ^ salt), dtype=U64)])
        sums[:, k] = mix(total[bounds[1:]] - total[bounds[:-1]] ^ np.diff(bounds).astype(U64))
    return sums


def spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The numbers from each start on, as many as its size, one run after the other."""
    return np.arange(int(sizes.sum())) + np.repeat(starts - (np.cumsum(sizes) - sizes), sizes)


class PoolTable:
    """Runs of numbers by 64-bit hashes: open addressing over one pool. ``leads`` is a second number kept with each run."""

    def __init__(self, room: int, kind: np.dtype) -> None:
        self.mask = (1 << int(2 * room - 1).bit_length()) - 1
        self.keys, self.starts, self.sizes = np.zeros(self.mask + 1, dtype=U64), np.zeros(self.mask + 1, dtype=np.int32), np.full(self.mask + 1, -1, dtype=np.int32)
        self.leads = np.zeros(self.mask + 1, dtype=np.int32)
        self.pool, self.used, self.count = np.zeros(1 << 16, dtype=kind), 0, 0

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The slot of each hash, -1 where it isn't there."""
        at, todo, out = (hashes >> U64(20)).astype(np.int64) & self.mask, np.arange(len(hashes)), np.full(len(hashes), -1, dtype=np.int64)
        while len(todo):
            spot = at[todo]
            filled = self.sizes[spot] >= 0
            hit = filled & (self.keys[spot] == hashes[todo])
            out[todo[hit]] = spot[hit]
            todo = todo[filled & ~hit]
            at[todo] = at[todo] + 1 & self.mask
        return out

    def put(self, hashes: np.ndarray, sizes: np.ndarray, numbers: np.ndarray, leads: np.ndarray | None = None) -> None:
        """Distinct hashes that aren't there, how many numbers each has, and all numbers."""
        while self.used + len(numbers) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.used : self.used + len(numbers)] = numbers
        starts = self.used + np.cumsum(sizes) - sizes
        self.used, self.count = self.used + len(numbers), self.count + len(hashes)
        at, todo = (hashes >> U64(20)).astype(np.int64) & self.mask, np.arange(len(hashes))
        while len(todo):
            free = todo[self.sizes[at[todo]] < 0]
            # Of several for one slot the last one written gets it.
            self.keys[at[free]] = hashes[free]
            won = free[self.keys[at[free]] == hashes[free]]
            self.starts[at[won]], self.sizes[at[won]] = starts[won], sizes[won]
            if leads is not None:
                self.leads[at[won]] = leads[won]
            left = np.ones(len(hashes), dtype=bool)
            left[won] = False
            todo = todo[left[todo]]
            at[todo] = at[todo] + 1 & self.mask


class Generations:
    """Two tables: once the young one is full it becomes the old one, and what is asked for again moves to the young, so what is frequent stays."""

    def __init__(self, room: int, kind: np.dtype) -> None:
        self.room, self.kind = room, kind
        self.young, self.old = PoolTable(room, kind), PoolTable(1, kind)

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """Slots of the young table, -1 for hashes that neither holds."""
        slot = self.young.find(hashes)
        left = np.flatnonzero(slot < 0)
        if len(left) and self.old.count:
            there = self.old.find(hashes[left])
            left, there = left[there >= 0], there[there >= 0]
            _, one = np.unique(hashes[left], return_index=True)
            spot = there[one]
            if self.young.count + len(spot) <= self.young.mask // 2:
                sizes = self.old.sizes[spot].astype(np.int64)
                self.young.put(hashes[left[one]], sizes, self.old.pool[spread(self.old.starts[spot].astype(np.int64), sizes)], self.old.leads[spot])
                slot[left] = self.young.find(hashes[left])
        return slot

    def complete(self, hashes: np.ndarray, make) -> np.ndarray:
        """Slots of all hashes in the young table. make(rows) gives, for rows with the distinct new hashes, an order of them and in this order their sizes, numbers and leads."""
        slot = self.find(hashes)
        left = np.flatnonzero(slot < 0)
        if not len(left):
            return slot
        fresh, one = np.unique(hashes[left], return_index=True)
        if self.young.count + len(fresh) > self.room:
            self.young, self.old = PoolTable(max(self.room, len(hashes)), self.kind), self.young
            self.find(hashes)
            left = np.flatnonzero(self.young.find(hashes) < 0)
            fresh, one = np.unique(hashes[left], return_index=True)
        if len(fresh):
            order, sizes, numbers, leads = make(left[one])
            self.young.put(fresh[order], sizes, numbers, None if leads is None else leads)
        return self.young.find(hashes)
