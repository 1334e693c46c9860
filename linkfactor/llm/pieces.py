"""SentencePiece BPE encoding with seeded merge-dropout, and lossless decoding.

Encoding follows an agenda: of all adjacent pairs whose union is a piece, the best-scored
(leftmost of equals) is merged, until none is left. With dropout a candidate is skipped for
good if a hash of (seed, document key, place of the part in the text, left piece, right
piece, place in the part) falls below the rate: every occurrence draws for itself, and
draws the same again on any machine.

No piece holds a space after another character, so texts are cut before runs of spaces and
the parts' ids joined. A worker keeps, for a part and a set of skipped candidates, the ids
and the merges made. An occurrence looks its part up without skips and draws for the merges
that were made there; where one is skipped it goes on with that set, until no merge made is
a skipped one, which is the agenda's own result. New entries are made by array rounds over
many parts, each round making the best merge of every part; very long parts go through a heap.
Spaces are written as the model's space mark behind a leading one; a literal mark and
characters without a piece become byte pieces, so decoding is lossless.

Defined results: null and empty texts have no ids and decode to the empty text; repeated
rows get equal ids; null keys draw alike; an empty table gives an empty result; extra
columns aren't read. Decoding writes U+FFFD for ids that aren't in the vocabulary and for
bytes that are no UTF-8 (as in a list cut inside a character).
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import Block, Generations, blocks, frugal, mix, spread

U64 = np.uint64
RATE, SEED = 0.1, 20_240_601
#: Parts of so many bytes go through the heap.
LONG = 64
#: Entries in each of the two generations that a worker keeps, and bytes of text that are encoded at a time.
CACHE_PARTS, SLICE_BYTES = 260_000, 1 << 20
MARK = "▁"
_SPACES = re.compile(r" *[^ ]+| +")
UNEVEN = r"  |\A | \z"
_SPACE = np.zeros(256, dtype=bool)
_SPACE[32] = True
_PLACE, _OFFSET, _SKIP = U64(0xD6E8FEB86659FD93), U64(0x9E3779B97F4A7C15), U64(0xA24BAED4963EE407)
_MASK = (1 << 64) - 1
_NONE = np.int64(1) << 60


def _mix_int(x: int) -> int:
    x = (x + 0x9E3779B97F4A7C15) & _MASK
    x = (x ^ x >> 30) * 0xBF58476D1CE4E5B9 & _MASK
    x = (x ^ x >> 27) * 0x94D049BB133111EB & _MASK
    return x ^ x >> 31


class PairTable:
    """Open addressing from (left, right) to the merged symbol."""

    def __init__(self, left: np.ndarray, right: np.ndarray, merged: np.ndarray) -> None:
        size = 1 << int(4 * max(16, len(left)) - 1).bit_length()
        self.mask, self.keys, self.values = size - 1, np.full(size, -1, dtype=np.int64), np.full(size, -1, dtype=np.int64)
        keys = left.astype(np.int64) << 32 | right.astype(np.int64)
        at, todo, self.probes = self._home(keys), np.arange(len(keys)), 0
        while len(todo):
            self.probes += 1
            free = todo[self.keys[at[todo]] == -1]
            _, one = np.unique(at[free], return_index=True)
            won = free[one]
            self.keys[at[won]], self.values[at[won]] = keys[won], merged[won]
            todo = np.setdiff1d(todo, won)
            at[todo] = at[todo] + 1 & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (mix(keys.view(U64)) >> U64(20)).astype(np.int64) & self.mask

    def get(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """-1 where the pair makes no piece."""
        keys = left.astype(np.int64) << 32 | right.astype(np.int64)
        at = self._home(keys)
        there = self.keys[at]
        out = np.where(there == keys, self.values[at], -1)
        more = np.flatnonzero((there != keys) & (there != -1))
        while len(more):
            at[more] = at[more] + 1 & self.mask
            there = self.keys[at[more]]
            hit = there == keys[more]
            out[more[hit]] = self.values[at[more[hit]]]
            more = more[~hit & (there != -1)]
        return out


class PieceCoder:
    """One model with one seed and dropout rate."""

    def __init__(self, model_file: str, seed: int = SEED, rate: float = RATE) -> None:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_file)
        n = model.get_piece_size()
        pieces = [model.id_to_piece(i) for i in range(n)]
        plain = [not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i)) for i in range(n)]
        symbols = {p: i for i, p in enumerate(pieces) if plain[i]}
        if any(MARK in p.lstrip(MARK) for p in symbols):
            raise ValueError("pieces with a space inside can't be encoded part by part")
        order = sorted(symbols.values(), key=lambda i: (-model.get_score(i), i))
        self.byte_ids = np.full(256, -1, dtype=np.int64)
        for i in range(n):
            if model.is_byte(i):
                self.byte_ids[int(pieces[i][3:5], 16)] = i
        if (self.byte_ids < 0).any():
            raise ValueError("the model has no byte pieces, so it can't be lossless")
        # Characters that only occur inside pieces are symbols too, beyond the pieces' ids; they end as bytes.
        extra = {}
        for p in symbols:
            for c in p:
                if c not in symbols and c not in extra:
                    extra[c] = n + len(extra)
        known = symbols | extra
        self.rank = np.full(n + len(extra), _NONE, dtype=np.int64)
        self.rank[order] = np.arange(len(order))
        splits = [(known[p[:k]], known[p[k:]], i) for p, i in symbols.items() if len(p) > 1 for k in range(1, len(p)) if p[:k] in known and p[k:] in known]
        self.pairs = PairTable(*(np.array([s[j] for s in splits], dtype=np.int64) for j in range(3)))
        self.of_char = np.full(0x110000, -1, dtype=np.int64)
        for c, i in known.items():
            if len(c) == 1 and c != MARK:
                self.of_char[ord(c)] = i
        self.of_char[ord(" ")] = known.get(MARK, -1)
        self.last_piece, self.characters = n, {i: c for c, i in extra.items()}
        self.bytes_of = [pieces[i].replace(MARK, " ").encode() if plain[i] else b"" for i in range(n)]
        for b, i in enumerate(self.byte_ids):
            self.bytes_of[i] = bytes([b])
        self.key, self.limit = _mix_int(seed), int(rate * (1 << 64))
        self.kind = np.dtype("<u2" if n <= 1 << 16 else "<u4")
        self.known = Generations(CACHE_PARTS, np.dtype(np.uint64))
        self.piece_bytes = pa.array(self.bytes_of, type=pa.binary())
        self.piece_sizes = np.array([len(x) for x in self.bytes_of])

    def salts(self, doc_salt: np.ndarray, offset: np.ndarray) -> np.ndarray:
        """What each part's draws go by: the seed, its document, and where it begins."""
        return mix(mix(doc_salt.view(U64) ^ U64(self.key)) ^ offset.astype(U64) * _OFFSET)

    @staticmethod
    def codes(left: np.ndarray, right: np.ndarray, place: np.ndarray) -> np.ndarray:
        """A number for each candidate of a part."""
        return mix(left.astype(U64) << U64(32) | right.astype(U64)) ^ place.astype(U64) * _PLACE

    def drawn(self, codes: np.ndarray, salts: np.ndarray) -> np.ndarray:
        """Which candidates are skipped."""
        return mix(codes ^ salts) < U64(min(self.limit, _MASK)) if self.limit else np.zeros(len(codes), dtype=bool)

    def _final(self, symbols: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of parts' last symbols (below 0 or from last_piece on: a character without a piece, which becomes its bytes), and the part of each."""
        odd = np.flatnonzero((symbols < 0) | (symbols >= self.last_piece))
        if not len(odd):
            return symbols, owner
        bytes_of = [list((self.characters[s] if s >= 0 else chr(-s - 2)).encode()) for s in symbols[odd].tolist()]
        sizes = np.ones(len(symbols), dtype=np.int64)
        sizes[odd] = [len(x) for x in bytes_of]
        out = np.repeat(symbols, sizes)
        out[spread((np.cumsum(sizes) - sizes)[odd], sizes[odd])] = self.byte_ids[np.array([b for x in bytes_of for b in x], dtype=np.int64)]
        return out, np.repeat(owner, sizes)

    def _symbols(self, text: str) -> np.ndarray:
        codes = np.frombuffer(text.encode("utf-32-le"), dtype="<u4").astype(np.int64)
        found = self.of_char[codes]
        return np.where(found >= 0, found, -codes - 2)

    def by_heap(self, part: str, salt: int) -> np.ndarray:
        """Ids of one part (with its leading spaces) by a heap of candidates."""
        symbols = self._symbols(part).tolist()
        n = len(symbols)
        after, before, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        agenda: list[tuple[int, int, int, int, int]] = []

        def add(i: int, a: int, b: int, merged: int) -> None:
            if merged < 0:
                return
            code = _mix_int((a & _MASK) << 32 & _MASK | b) ^ i * int(_PLACE) & _MASK
            if not self.limit or _mix_int(code ^ salt) >= self.limit:
                heapq.heappush(agenda, (int(self.rank[merged]), i, a, b, merged))

        def look(i: int, j: int) -> None:
            a, b = symbols[i], symbols[j]
            if a >= 0 and b >= 0:
                add(i, a, b, int(self.pairs.get(np.array([a]), np.array([b]))[0]))

        every = np.array(symbols, dtype=np.int64)
        known = np.flatnonzero((every[:-1] >= 0) & (every[1:] >= 0))
        for i, merged in zip(known.tolist(), self.pairs.get(every[known], every[known + 1]).tolist(), strict=True):
            add(i, symbols[i], symbols[i + 1], merged)
        while agenda:
            _, i, a, b, merged = heapq.heappop(agenda)
            j = after[i]
            if not alive[i] or j >= n or symbols[i] != a or symbols[j] != b:
                continue
            symbols[i], alive[j], after[i] = merged, False, after[j]
            if after[i] < n:
                before[after[i]] = i
                look(i, after[i])
            if before[i] >= 0:
                look(before[i], i)
        last = np.array([s for s, ok in zip(symbols, alive, strict=True) if ok], dtype=np.int64)
        return self._final(last, np.zeros(len(last), dtype=np.int64))[0]

    def by_rounds(self, parts: list[str], skips: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Many short parts at once: a round makes the best merge of each that has one.

        skips(codes, parts) tells the skipped candidates. Returns the ids, their number for each part, the codes of the merges made, and their number for each part.
        """
        sizes = np.array([len(p) for p in parts])
        symbols, own = self._symbols("".join(parts)), np.repeat(np.arange(len(parts)), sizes)
        place = np.arange(len(symbols)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        done_symbols, done_own, made_codes, made_own = [], [], [np.zeros(0, dtype=U64)], [np.zeros(0, dtype=np.int64)]
        merged, code = np.full(len(symbols), -1, dtype=np.int64), np.zeros(len(symbols), dtype=U64)
        fresh = np.arange(len(symbols))
        while len(symbols):
            # Look only the pairs up that the last round made.
            fresh = fresh[fresh < len(symbols) - 1]
            merged[fresh] = -1
            fresh = fresh[(own[fresh] == own[fresh + 1]) & (symbols[fresh] >= 0) & (symbols[fresh + 1] >= 0)]
            made = self.pairs.get(symbols[fresh], symbols[fresh + 1])
            some = made >= 0
            fresh, made = fresh[some], made[some]
            code[fresh] = self.codes(symbols[fresh], symbols[fresh + 1], place[fresh])
            merged[fresh] = np.where(skips(code[fresh], own[fresh]), -1, made)
            merged[-1] = -1
            cost = np.where(merged >= 0, self.rank[merged] << 8 | place, _NONE)
            head = np.concatenate([[True], own[1:] != own[:-1]])
            starts = np.flatnonzero(head)
            best = np.minimum.reduceat(cost, starts)
            going = best < _NONE
            if not going.all():
                stays = np.repeat(going, np.diff(np.append(starts, len(symbols))))
                done_symbols.append(symbols[~stays])
                done_own.append(own[~stays])
                symbols, own, place, merged, code, cost, head = (x[stays] for x in (symbols, own, place, merged, code, cost, head))
                best = best[going]
            if not len(symbols):
                break
            at = np.flatnonzero(cost == best[np.cumsum(head) - 1])
            made_codes.append(code[at])
            made_own.append(own[at])
            symbols[at] = merged[at]
            keep = np.ones(len(symbols), dtype=bool)
            keep[at + 1] = False
            new = np.cumsum(keep) - 1
            spots = new[at]
            fresh = np.concatenate([spots, spots[spots > 0] - 1])
            # The pair that began at the swallowed symbol now begins at the merged one.
            symbols, own, place, merged, code = symbols[keep], own[keep], place[keep], merged[keep], code[keep]
        every, owner = np.concatenate(done_symbols), np.concatenate(done_own)
        order = np.argsort(owner, kind="stable")
        ids, owner = self._final(every[order], owner[order])
        codes, made_by = np.concatenate(made_codes), np.concatenate(made_own)
        order = np.argsort(made_by, kind="stable")
        return ids, np.bincount(owner, minlength=len(parts)), codes[order], np.bincount(made_by, minlength=len(parts))

    def _even(self, block: Block, doc_salt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of texts with single spaces between words only, and their number for each text."""
        lo, hi, firsts = block.spans(_SPACE)
        raw = block.data.tobytes()
        owner = np.repeat(np.arange(block.n), np.diff(firsts))
        salts = self.salts(doc_salt[owner], lo - block.bounds[owner])
        found_of, found_sizes, found_ids = [], [], []
        for i in np.flatnonzero(hi - lo >= LONG).tolist():
            ids = self.by_heap(" " + raw[lo[i] : hi[i]].decode(), int(salts[i]))
            found_of.append(np.array([i]))
            found_sizes.append(np.array([len(ids)]))
            found_ids.append(ids)
        todo = np.flatnonzero(hi - lo < LONG)
        key, skipped = block.span_hashes(lo[todo], hi[todo]), []
        while len(todo):

            def make(rows: np.ndarray) -> tuple:
                words = [" " + raw[a:b].decode() for a, b in zip(lo[todo[rows]].tolist(), hi[todo[rows]].tolist(), strict=True)]
                own_skips = [column[rows] for column in skipped]

                def skips(codes: np.ndarray, parts: np.ndarray) -> np.ndarray:
                    hit = np.zeros(len(codes), dtype=bool)
                    for column in own_skips:
                        hit |= column[parts] == codes
                    return hit

                ids, sizes, codes, leads = self.by_rounds(words, skips)
                # Codes first, then ids, part by part.
                both = np.empty(len(ids) + len(codes), dtype=U64)
                begin = np.cumsum(sizes + leads) - sizes - leads
                both[spread(begin, leads)] = codes
                both[spread(begin + leads, sizes)] = ids.astype(U64)
                return np.arange(len(rows)), sizes + leads, both, leads

            slot = self.known.complete(key, make)
            table = self.known.young
            starts, leads, sizes = (x[slot].astype(np.int64) for x in (table.starts, table.leads, table.sizes))
            of = np.repeat(np.arange(len(todo)), leads)
            codes = table.pool[spread(starts, leads)]
            hit = self.drawn(codes, salts[todo][of])
            codes, of = codes[hit], of[hit]
            more = np.bincount(of, minlength=len(todo))
            done = more == 0
            found_of.append(todo[done])
            found_sizes.append((sizes - leads)[done])
            found_ids.append(table.pool[spread((starts + leads)[done], (sizes - leads)[done])].astype(np.int64))
            rest = np.flatnonzero(~done)
            # The sets of skipped candidates grow, and the keys with them.
            turn = np.arange(len(of)) - np.repeat(np.cumsum(more[rest]) - more[rest], more[rest])
            place = np.cumsum(~done)[of] - 1
            skipped = [column[rest] for column in skipped]
            for k in range(int(more.max(initial=0))):
                column = np.zeros(len(rest), dtype=U64)
                column[place[turn == k]] = codes[turn == k]
                skipped.append(column)
            key = key[rest]
            if len(rest):
                key = key ^ np.bitwise_xor.reduceat(mix(codes ^ _SKIP), np.cumsum(more[rest]) - more[rest])
            todo = todo[rest]
        of, sizes = (np.concatenate([np.zeros(0, dtype=np.int64), *x]) for x in (found_of, found_sizes))
        pool = np.concatenate([np.zeros(0, dtype=np.int64), *found_ids])
        starts, counts = np.empty(len(lo), dtype=np.int64), np.empty(len(lo), dtype=np.int64)
        starts[of], counts[of] = np.cumsum(sizes) - sizes, sizes
        return pool[spread(starts, counts)], np.diff(np.concatenate([[0], np.cumsum(counts)])[firsts])

    def _uneven(self, texts: list[str], doc_salt: np.ndarray) -> list[np.ndarray]:
        """Ids of texts with runs of spaces, part by part: those short enough in rounds, the others by the heap."""
        parts, of, offset = [], [], []
        for i, text in enumerate(texts):
            at = 0
            for part in _SPACES.findall(" " + text):
                parts.append(part)
                of.append(i)
                offset.append(at)
                at += len(part.encode())
        salts = self.salts(doc_salt[of], np.array(offset, dtype=np.int64)) if parts else np.zeros(0, dtype=U64)
        ids: list[np.ndarray] = [np.zeros(0, dtype=np.int64)] * len(parts)
        short = [i for i, p in enumerate(parts) if len(p) < LONG]
        if short:
            own = salts[short]
            flat, sizes, _, _ = self.by_rounds([parts[i] for i in short], lambda codes, which: self.drawn(codes, own[which]))
            for i, x in zip(short, np.split(flat, np.cumsum(sizes)[:-1]), strict=True):
                ids[i] = x
        for i, p in enumerate(parts):
            if len(p) >= LONG:
                ids[i] = self.by_heap(p, int(salts[i]))
        bounds = np.searchsorted(np.array(of, dtype=np.int64), np.arange(len(texts) + 1)).tolist()
        return [np.concatenate([np.zeros(0, dtype=np.int64), *ids[a:b]]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]

    def encode(self, texts: pa.Array, doc_salt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and the number of ids of each text; texts: strings without nulls, doc_salt: a long for each."""
        slow = pc.match_substring_regex(texts, UNEVEN).to_numpy(zero_copy_only=False)
        fast = texts if not slow.any() else texts.filter(pa.array(~slow))
        salt = doc_salt[~slow]
        found = [self._even(block, salt[block.first : block.first + block.n]) for block in blocks(fast, SLICE_BYTES)]
        ids, sizes = (np.concatenate([np.zeros(0, dtype=np.int64), *[f[k] for f in found]]) for k in (0, 1))
        if not slow.any():
            return ids, sizes
        rest = self._uneven(texts.filter(pa.array(slow)).to_pylist(), doc_salt[slow])
        every, starts = np.empty(len(texts), dtype=np.int64), np.empty(len(texts), dtype=np.int64)
        every[~slow], every[slow] = sizes, [len(x) for x in rest]
        starts[~slow] = np.cumsum(sizes) - sizes
        starts[slow] = len(ids) + np.cumsum(every[slow]) - every[slow]
        return np.concatenate([ids, *rest])[spread(starts, every)], every

    def decode(self, ids: np.ndarray) -> str:
        known = [self.bytes_of[i] if 0 <= i < self.last_piece else "\ufffd".encode() for i in ids.tolist()]
        return b"".join(known).decode(errors="replace")[1:]

    def is_text(self, ids: np.ndarray, sizes: np.ndarray, texts: pa.Array) -> np.ndarray:
        """Whether each text's ids decode to it, all bytes of it being compared."""
        lengths = np.concatenate([[0], np.cumsum(self.piece_sizes[ids])])
        bounds = np.concatenate([[0], np.cumsum(sizes)])
        spelled = lengths[bounds]
        raw = [b" " + t if t else b"" for t in texts.cast(pa.large_binary()).to_numpy(zero_copy_only=False).tolist()]
        same = np.diff(spelled) == [len(x) for x in raw]
        if not same.all():
            return np.array([self.decode(ids[a:b]) == t for a, b, t in zip(bounds[:-1], bounds[1:], texts.to_pylist(), strict=True)], dtype=bool)
        data = self.piece_bytes.take(pa.array(ids)).buffers()[2]
        made = np.frombuffer(data, dtype=np.uint8)[: spelled[-1]] if data is not None else np.zeros(0, dtype=np.uint8)
        wrong = np.concatenate([[0], np.cumsum(made != np.frombuffer(b"".join(raw), dtype=np.uint8))])[spelled]
        return np.diff(wrong) == 0


@cache
def _coder(model_file: str, seed: int, rate: float) -> PieceCoder:
    return PieceCoder(model_file, seed, rate)


def encode_pieces(docs: DataFrame, model_file: str, key: str = "doc_id", text: str = "text", seed: int = SEED, rate: float = RATE) -> DataFrame:
    """key, ids, n_tokens and lossless (the ids decode to the text) of every text."""
    salt = F.xxhash64(F.lit("dropout"), F.coalesce(F.col(key).cast("string"), F.lit("")))
    named = docs.select(F.col(key).alias("key"), salt.alias("salt"), F.coalesce(F.col(text), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _coder(model_file, seed, rate)
        for whole in batches:
            sizes = np.cumsum(pc.binary_length(whole.column("text")).to_numpy().astype(np.int64))
            at = 0
            while at < whole.num_rows:
                until = max(at + 1, int(np.searchsorted(sizes, (sizes[at - 1] if at else 0) + SLICE_BYTES, "right")))
                batch = whole.slice(at, until - at)
                texts, at = pa.concat_arrays([batch.column("text")]), until
                ids, counts = coder.encode(texts, batch.column("salt").to_numpy())
                bounds = np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(bounds), pa.array(ids.astype(np.int32)))
                yield pa.RecordBatch.from_arrays([batch.column("key"), lists, pa.array(counts), pa.array(coder.is_text(ids, counts, texts))], names=["key", "ids", "n_tokens", "lossless"])

    kind = docs.schema[key].dataType.simpleString()
    return named.mapInArrow(frugal(run), f"key {kind}, ids array<int>, n_tokens long, lossless boolean").withColumnRenamed("key", key)


def decode_pieces(encoded: DataFrame, model_file: str, ids: str = "ids", text: str = "text") -> DataFrame:
    """encoded with the column ``text`` that its ids stand for; null ids give a null text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _coder(model_file, SEED, 0.0)
        for batch in batches:
            texts = [None if x is None else coder.decode(np.array(x, dtype=np.int64)) for x in batch.column(ids).to_pylist()]
            yield batch.append_column(text, pa.array(texts, type=pa.string()))

    frame = encoded.drop(text)
    spec = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in frame.schema.fields) + f", `{text}` string"
    return frame.mapInArrow(frugal(run), spec)
