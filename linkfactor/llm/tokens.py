"""Token-ID shards with a minimal perfect hash index.

Layout of a shard, all little-endian: ``<n>.ids`` holds the token ids of its documents, one
after the other (16-bit if the vocabulary fits, else 32-bit, unless a width is given). ``<n>.mph`` maps a document
key to its slot: the header (magic, count, id width, levels, words), each level's bit count
and bits, the running popcounts, then for each slot a 32-bit fingerprint, a 64-bit start and
a 32-bit length, and last the keys in payload order. A key goes to the first level where it
is alone at its place; the rank of that bit is its slot, so a lookup reads a few words
whatever the count, and the fingerprint turns away keys that aren't stored.

Documents are range-partitioned by key, so shards and the ids in them ascend. Writing goes
to a temporary name first and is then moved, so a task that runs again does no harm. Paths
are opened with pyarrow.fs, for any store that it knows. Special tokens in a text are
recognized, as the library does by default.

Defined results: a null key counts as the smallest long, which is no key of its own;
documents with equal keys stand by a hash of their texts, may fill several shards, and are
told apart by their rank among them in a shard; null and empty texts have only the end id;
an empty table makes no shard. Columns other than key and text aren't read.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import Block, Generations, blocks, frugal, mix, spread

U64 = np.uint64
MAGIC = 0x31485052
END_ID = 2
#: Pieces in each of the two generations of ids that a worker keeps (some 35 bytes each).
CACHE_PIECES = 1_000_000
NULL_KEY = -(1 << 63)
#: Bytes of text that are encoded at a time (a longer text stands alone).
SLICE_BYTES = 2 << 20

#: Any white space but single blanks and newlines between words.
UNEVEN = r"[\t\x0b-\r\x1c-\x1f\x{85}\x{a0}\x{1680}\x{180e}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]|[ \n][ \n]|\A[ \n]|[ \n]\z"
#: Pieces of Latin letters, which every version of Unicode takes for letters.
WORD = r"\A[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{24f}]+\z"
#: Stops that are a pre-token of their own behind letters.
STOPS = b".,;:!?"

_GAP = np.zeros(256, dtype=bool)
_GAP[[10, 32]] = True
_NOT_LETTER = np.ones(256, dtype=np.uint8)
_NOT_LETTER[[*range(65, 91), *range(97, 123)]] = 0
_STOP = np.zeros(256, dtype=bool)
_STOP[list(STOPS)] = True
#: Told apart from the same bytes behind a space.
_FRONT = U64(0x9E3779B97F4A7C15)


def byte_letters() -> dict[int, str]:
    """The character that stands for each byte in a byte-level vocabulary: printable ones for themselves, the others from 256 on; blanks are left out."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    odd = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(odd) if b != 32}


class PieceEncoder:
    """The tokenizer's ids by pieces between safe cuts; pieces that a worker knows aren't encoded again.

    A byte-level BPE never merges across its pre-tokens. A single space between two
    characters that aren't white space begins one, and a single newline there is one, so
    texts of single blanks and newlines may be cut before such spaces and around such
    newlines, and the pieces' ids joined; a special token holds no white space and stays
    whole. A stop behind ASCII letters alone is a pre-token too and counts as a piece.
    Texts with any other white space go through the tokenizer in parts between single spaces.

    Cutting, looking up and joining are array operations over the bytes of many texts; pieces
    are told by 64-bit hashes. New pieces of letters are one pre-token, so they go to the
    tokenizer's model without the pre-tokenizer, and all others through the whole tokenizer.
    Ids are kept in two generations: once the young one is full it becomes the old one, and
    what is asked for again moves to the young, so frequent pieces stay.
    """

    def __init__(self, vocabulary: str, width: int | None = None, end_id: int = END_ID) -> None:
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(vocabulary)
        self.words = Tokenizer(self.tokenizer.model)
        self.words.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        size = self.tokenizer.get_vocab_size()
        self.width = width or (2 if max(size, end_id + 1) <= 1 << 16 else 4)
        self.kind, self.end_id = np.dtype(f"<u{self.width}"), end_id
        # In a byte-level vocabulary each character of a token stands for one byte.
        self.sizes = np.array([len(self.tokenizer.id_to_token(i) or "") for i in range(size)])
        self.letters = byte_letters()
        self.cut = re.compile(r"(?<=\S) (?=\S)")
        (self.newline,) = self._single(["\n"])
        self.stops = np.zeros(256, dtype=self.kind)
        self.stops[list(STOPS)] = [x[0] for x in self._single([chr(c) for c in STOPS])]
        self.known = Generations(CACHE_PIECES, self.kind)

    def _single(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, dtype=self.kind) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _letters(self, words: list[str], lead: str) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of ids, and ids, of words of letters by the model, many in one text, cut by the tokens' byte lengths; ``lead`` stands before each."""
        counts, out = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=self.kind)]
        for at in range(0, len(words), 2000):
            raw = " ".join(words[at : at + 2000]).encode()
            text = lead + raw.decode("latin-1").translate(self.letters).replace(" ", " " + lead)
            ids = np.array(self.words.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype=np.int64)
            blanks = np.flatnonzero(np.frombuffer(raw, dtype=np.uint8) == 32)
            lengths = np.diff(np.concatenate([[-1], blanks, [len(raw)]])) - 1 + len(lead)
            stops = np.searchsorted(np.cumsum(self.sizes[ids]), np.cumsum(lengths)) + 1
            counts.append(np.diff(np.concatenate([[0], stops])))
            out.append(ids.astype(self.kind))
        return np.concatenate(counts), np.concatenate(out)

    def _fresh(self, pieces: list[str], front: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """An order of the pieces, and in this order their numbers of ids and their ids; those not in front follow a space."""
        plain = pc.match_substring_regex(pa.array(pieces, type=pa.string()), WORD).to_numpy(zero_copy_only=False) if pieces else np.zeros(0, dtype=bool)
        order, counts, ids = [], [], []
        for lead, part in (("", np.flatnonzero(plain & front)), ("\u0120", np.flatnonzero(plain & ~front))):
            n, x = self._letters([pieces[i] for i in part.tolist()], lead)
            order.append(part)
            counts.append(n)
            ids.append(x)
        odd = np.flatnonzero(~plain)
        rest = self._single([pieces[i] if first else " " + pieces[i] for i, first in zip(odd.tolist(), front[odd].tolist(), strict=True)])
        order.append(odd)
        counts.append(np.array([len(x) for x in rest], dtype=np.int64))
        return np.concatenate(order), np.concatenate(counts), np.concatenate([*ids, *rest]) if rest else np.concatenate(ids)

    def _even(self, block: Block) -> tuple[np.ndarray, np.ndarray]:
        """Ids of a block of texts of single blanks and newlines, each followed by the end id, and their number for each text."""
        data, bounds = block.data, block.bounds
        lo, hi, firsts = block.spans(_GAP)
        first = np.zeros(len(lo), dtype=bool)
        first[firsts[:-1][np.diff(firsts) > 0]] = True
        newline = ~first & (data[np.maximum(lo, 1) - 1] == 10) if len(data) else first
        front = first | newline
        odd = np.concatenate([[0], np.cumsum(_NOT_LETTER[data], dtype=np.int32)])
        stopped = (hi - lo > 1) & (odd[hi] - odd[lo] == 1) & _STOP[data[hi - 1]] if len(data) else first
        cut = hi - stopped
        hashes = block.span_hashes(lo, cut) ^ front * _FRONT
        raw = data.tobytes()

        def make(rows: np.ndarray) -> tuple:
            return *self._fresh([raw[a:b].decode() for a, b in zip(lo[rows].tolist(), cut[rows].tolist(), strict=True)], front[rows]), None

        slot = self.known.complete(hashes, make)
        table = self.known.young
        sizes, starts = table.sizes[slot].astype(np.int64), table.starts[slot].astype(np.int64)
        # Each piece with a newline's id before and a stop's behind, where it has them; an end id behind each text.
        whole = sizes + newline + stopped
        owner = np.repeat(np.arange(block.n), np.diff(firsts))
        at = np.cumsum(whole) - whole + owner
        out = np.empty(int(whole.sum()) + block.n, dtype=self.kind)
        out[spread(at + newline, sizes)] = table.pool[spread(starts, sizes)]
        out[at[newline]] = self.newline[0]
        out[(at + whole - 1)[stopped]] = self.stops[data[hi[stopped] - 1]]
        total = np.concatenate([[0], np.cumsum(whole)])[firsts]
        ends = total[1:] + np.arange(block.n)
        out[ends] = self.end_id
        return out, np.diff(np.concatenate([[-1], ends]))

    def _uneven(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of texts with other white space, in parts between single spaces, each with its end id."""
        parts = [self.cut.split(t) for t in texts]
        ids = self._single([" " * (i > 0) + x for p in parts for i, x in enumerate(p)])
        out, at = [], 0
        for p in parts:
            out.append(np.concatenate([*ids[at : at + len(p)], np.array([self.end_id], dtype=self.kind)]))
            at += len(p)
        return out

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids (each text's followed by the end id), and the number of ids of each text; texts: strings without nulls."""
        slow = pc.match_substring_regex(texts, UNEVEN).to_numpy(zero_copy_only=False)
        fast = texts if not slow.any() else texts.filter(pa.array(~slow))
        found = [self._even(block) for block in blocks(fast, SLICE_BYTES)]
        ids, sizes = (np.concatenate([f[k] for f in found]) if found else np.zeros(0, dtype=(self.kind, np.int64)[k]) for k in (0, 1))
        if not slow.any():
            return ids, sizes
        rest = self._uneven(texts.filter(pa.array(slow)).to_pylist())
        every, starts = np.empty(len(texts), dtype=np.int64), np.empty(len(texts), dtype=np.int64)
        every[~slow], every[slow] = sizes, [len(x) for x in rest]
        pool = np.concatenate([ids, *rest])
        starts[~slow] = np.cumsum(sizes) - sizes
        starts[slow] = len(ids) + np.cumsum(every[slow]) - every[slow]
        return pool[spread(starts, every)], every


@cache
def _encoder(vocabulary: str, width: int | None, end_id: int) -> PieceEncoder:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    return PieceEncoder(vocabulary, width, end_id)


def _slices(column: pa.Array) -> Iterator[pa.Array]:
    """A column of strings in pieces of about SLICE_BYTES."""
    column = column.cast(pa.large_string())
    ends = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    at = 0
    while at < len(column):
        until = max(at + 1, int(np.searchsorted(ends, ends[at] + SLICE_BYTES, "right")) - 1)
        part = column.slice(at, until - at)
        yield part.cast(pa.string()) if ends[until] - ends[at] < 1 << 30 else part
        at = until


def key_hashes(keys: np.ndarray, ranks: np.ndarray) -> np.ndarray:
    return mix(mix(keys.astype(np.int64).view(U64)) ^ ranks.astype(U64) * U64(0x9E3779B97F4A7C15))


def _place(hashes: np.ndarray, level: int, bits: int) -> np.ndarray:
    return mix(hashes ^ mix(np.array([level + 1], dtype=U64))) % U64(bits)


class PerfectIndex:
    """Levels of bits; ``slots`` gives each stored key its own number below the count."""

    def __init__(self, sizes: list[int], words: np.ndarray) -> None:
        self.sizes, self.words = sizes, words
        ones = np.bitwise_count(words).astype(np.int64)
        self.before = np.concatenate([[0], np.cumsum(ones)])

    @classmethod
    def build(cls, hashes: np.ndarray, room: float = 1.5) -> PerfectIndex:
        sizes, parts, left = [], [], hashes
        while len(left):
            bits = 64 * max(1, int(np.ceil(len(left) * room / 64)))
            place = _place(left, len(sizes), bits)
            alone = np.bincount(place.astype(np.int64), minlength=bits) == 1
            parts.append(np.packbits(alone, bitorder="little").view("<u8"))
            sizes.append(bits)
            left = left[~alone[place.astype(np.int64)]]
            if len(sizes) > 200:
                raise ValueError("keys are not distinct")
        return cls(sizes, np.concatenate(parts) if parts else np.zeros(0, "<u8"))

    def slots(self, hashes: np.ndarray) -> np.ndarray:
        """-1 for keys that fall through all levels."""
        out, todo, base = np.full(len(hashes), -1, dtype=np.int64), np.arange(len(hashes)), 0
        for level, bits in enumerate(self.sizes):
            place = _place(hashes[todo], level, bits).astype(np.int64)
            word, bit = base + (place >> 6), (place & 63).astype(U64)
            hit = (self.words[word] >> bit) & U64(1) == 1
            below = np.bitwise_count(self.words[word[hit]] & ((U64(1) << bit[hit]) - U64(1))).astype(np.int64)
            out[todo[hit]] = self.before[word[hit]] + below
            todo, base = todo[~hit], base + bits // 64
        return out


class Shard:
    def __init__(self, index: PerfectIndex, prints: np.ndarray, starts: np.ndarray, lengths: np.ndarray, keys: np.ndarray, ranks: np.ndarray, width: int) -> None:
        self.index, self.prints, self.starts, self.lengths, self.keys, self.ranks, self.width = index, prints, starts, lengths, keys, ranks, width

    @classmethod
    def build(cls, keys: np.ndarray, ranks: np.ndarray, lengths: np.ndarray, width: int) -> Shard:
        hashes = key_hashes(keys, ranks)
        index = PerfectIndex.build(hashes)
        slots = index.slots(hashes)
        starts = np.cumsum(lengths) - lengths
        put = lambda values, kind: np.zeros(len(keys), dtype=kind) if not len(keys) else _scatter(values, slots, kind)
        return cls(index, put(hashes >> U64(32), "<u4"), put(starts, "<u8"), put(lengths, "<u4"), keys, ranks, width)

    def to_bytes(self) -> bytes:
        head = np.array([MAGIC, len(self.keys), self.width, len(self.index.sizes), len(self.index.words)], dtype="<u8")
        parts = (head, np.array(self.index.sizes, dtype="<u8"), self.index.words.astype("<u8"), self.prints, self.starts, self.lengths, self.keys.astype("<i8"), self.ranks.astype("<u4"))
        return b"".join(x.tobytes() for x in parts)

    @classmethod
    def from_bytes(cls, raw: bytes) -> Shard:
        magic, n, width, levels, words = np.frombuffer(raw, "<u8", 5).tolist()
        if magic != MAGIC:
            raise ValueError("not an index")
        at, out = 40, []
        for kind, count in (("<u8", levels), ("<u8", words), ("<u4", n), ("<u8", n), ("<u4", n), ("<i8", n), ("<u4", n)):
            out.append(np.frombuffer(raw, kind, count, at))
            at += out[-1].nbytes
        return cls(PerfectIndex(out[0].tolist(), out[1]), *out[2:7], int(width))

    def find(self, keys: np.ndarray, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Which keys are stored, and their starts and lengths (in ids)."""
        hashes = key_hashes(keys, ranks)
        slots = self.index.slots(hashes)
        known = slots >= 0
        known[known] = self.prints[slots[known]] == (hashes[known] >> U64(32))
        safe = np.where(known, slots, 0)
        return known, (self.starts[safe] if len(self.starts) else safe).astype(np.int64), (self.lengths[safe] if len(self.lengths) else safe).astype(np.int64)

    def holds(self, key: int, rank: int) -> bool:
        """Whether the key is really stored (a fingerprint passes one strange key in four thousand million); the stored keys ascend."""
        at = int(np.searchsorted(self.keys, key, "left")) + rank
        return at < len(self.keys) and int(self.keys[at]) == key


def _scatter(values: np.ndarray, slots: np.ndarray, kind: str) -> np.ndarray:
    out = np.empty(len(values), dtype=kind)
    out[slots] = values
    return out


def _store(uri: str) -> tuple[pafs.FileSystem, str]:
    """pyarrow's file system for a path; Hadoop's names for S3 are the one that pyarrow knows."""
    uri = re.sub(r"\As3[an]://", "s3://", uri)
    return pafs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def write_shards(docs: DataFrame, folder: str, vocabulary: str, key: str = "doc_id", text: str = "text", end_id: int = END_ID, width: int | None = None) -> DataFrame:
    """Encode and write the shards; returns their manifest (shard, n_docs, n_ids, low, high), a row for each."""
    named = docs.select(F.coalesce(F.col(key).cast("bigint"), F.lit(NULL_KEY)).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(vocabulary, width, end_id)
        shard = TaskContext.get().partitionId()
        attempt = TaskContext.get().taskAttemptId()
        keys, lengths = [], []
        store = path = sink = None
        for batch in batches:
            if not batch.num_rows:
                continue
            if sink is None:
                store, path = _store(folder)
                store.create_dir(path, recursive=True)
                sink = store.open_output_stream(f"{path}/{shard}.ids.{attempt}")
            for part in _slices(batch.column("text")):
                payload, sizes = encoder.encode(part)
                sink.write(payload.tobytes())
                lengths.append(sizes)
            keys.append(batch.column("key").to_numpy(zero_copy_only=False))
        if sink is None:
            return
        sink.close()
        store.move(f"{path}/{shard}.ids.{attempt}", f"{path}/{shard}.ids")
        every, counts = np.concatenate(keys), np.concatenate(lengths)
        fresh = np.concatenate([[True], every[1:] != every[:-1]])
        ranks = np.arange(len(every)) - np.maximum.accumulate(np.where(fresh, np.arange(len(every)), 0))
        index = Shard.build(every, ranks, counts, encoder.width)
        with store.open_output_stream(f"{path}/{shard}.mph.{attempt}") as out:
            out.write(index.to_bytes())
        store.move(f"{path}/{shard}.mph.{attempt}", f"{path}/{shard}.mph")
        yield pa.RecordBatch.from_pydict({"shard": [shard], "n_docs": [len(every)], "n_ids": [int(counts.sum())], "low": [int(every[0])], "high": [int(every[-1])]})

    # Documents without a key, or with the same one, may fill several shards.
    dealt = named.withColumn("tie", F.xxhash64("text"))
    ordered = dealt.repartitionByRange(F.col("key"), F.col("tie")).sortWithinPartitions("key", "tie").select("key", "text")
    return ordered.mapInArrow(frugal(run), "shard long, n_docs long, n_ids long, low long, high long")


def read_shards(manifest: DataFrame, folder: str) -> DataFrame:
    """Every stored document by keyed lookup: key, start over all shards, n_tokens, ids_crc32.

    manifest: materialized rows of write_shards. It has a row a shard, and so is small.
    """
    spark = manifest.sparkSession
    rows = sorted(manifest.collect(), key=lambda r: r["shard"])
    bases = np.cumsum([0, *[r["n_ids"] for r in rows]]).tolist()
    tasks = spark.createDataFrame([(r["shard"], b) for r, b in zip(rows, bases, strict=False)], "shard long, base long")
    dealt = tasks.repartition(max(1, len(rows)), "shard") if rows else tasks

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, base in zip(batch.column("shard").to_pylist(), batch.column("base").to_pylist(), strict=True):
                store, path = _store(folder)
                with store.open_input_stream(f"{path}/{shard}.mph") as source:
                    index = Shard.from_bytes(source.read())
                known, starts, lengths = index.find(index.keys, index.ranks)
                if not known.all():
                    raise ValueError(f"shard {shard} lost {int((~known).sum())} keys")
                sums = np.empty(len(known), dtype=np.int64)
                with store.open_input_file(f"{path}/{shard}.ids") as payload:
                    for i, (a, n) in enumerate(zip(starts.tolist(), lengths.tolist(), strict=True)):
                        ids = np.frombuffer(payload.read_at(n * index.width, a * index.width), dtype=f"<u{index.width}")
                        sums[i] = zlib.crc32(ids.astype("<u4").tobytes())
                keys = pa.array(index.keys, mask=index.keys == NULL_KEY)
                yield pa.RecordBatch.from_arrays([keys, pa.array(starts + base), pa.array(lengths), pa.array(sums)], names=["key", "start", "n_tokens", "ids_crc32"])

    return dealt.mapInArrow(frugal(run), "key long, start long, n_tokens long, ids_crc32 long")


def lookup(keys: DataFrame, manifest: DataFrame, folder: str, key: str = "doc_id") -> DataFrame:
    """Ids by keyed access: key, copy and ids, a row for every stored document of each key asked for (copy counts them from 0), and one of nulls beside a key that isn't stored.

    A key goes to the shards whose range holds it (several only if one key fills several); a
    task reads the index of its shards and of the payload only the bytes asked for.
    """
    rows = sorted(manifest.collect(), key=lambda r: r["shard"])
    lows, highs, names = (np.array([r[k] for r in rows], dtype=np.int64) for k in ("low", "high", "shard"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opened: dict = {}
        for batch in batches:
            asked = batch.column("key").to_numpy(zero_copy_only=False)
            first, last = np.searchsorted(highs, asked, "left"), np.searchsorted(lows, asked, "right")
            out: dict[str, list] = {"key": [], "copy": [], "ids": []}
            for k, a, b in zip(asked.tolist(), first.tolist(), last.tolist(), strict=True):
                copies = 0
                for i in range(a, b):
                    if i not in opened:
                        if len(opened) > 1:
                            opened.clear()
                        store, path = _store(folder)
                        with store.open_input_stream(f"{path}/{names[i]}.mph") as source:
                            opened[i] = Shard.from_bytes(source.read()), store.open_input_file(f"{path}/{names[i]}.ids")
                    index, payload = opened[i]
                    rank = 0
                    while (found := index.find(np.array([k]), np.array([rank])))[0][0] and index.holds(k, rank):
                        start, n = int(found[1][0]) * index.width, int(found[2][0]) * index.width
                        out["key"].append(None if k == NULL_KEY else k)
                        out["copy"].append(copies)
                        out["ids"].append(np.frombuffer(payload.read_at(n, start), dtype=f"<u{index.width}").astype(np.int64).tolist())
                        rank, copies = rank + 1, copies + 1
                if not copies:
                    out["key"].append(None if k == NULL_KEY else k)
                    out["copy"].append(None)
                    out["ids"].append(None)
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([("key", pa.int64()), ("copy", pa.int32()), ("ids", pa.list_(pa.int64()))]))

    named = keys.select(F.coalesce(F.col(key).cast("bigint"), F.lit(NULL_KEY)).alias("key")).repartitionByRange("key").sortWithinPartitions("key")
    return named.mapInArrow(frugal(run), "key long, copy int, ids array<long>")
