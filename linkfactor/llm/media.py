"""Media columns: store payloads as 8-bit PCM, sniff stored bytes, carve what is embedded.

An Aho-Corasick automaton finds the magic bytes of all known formats in one pass over a
cell. A validator then checks the structure at each hit and gives the length it confirms;
only validated hits count. One that starts at byte 0 is the cell's own type, which corrects
the declared type; those within it are carved.

Defined results: a null or empty cell has type None, valid false and nothing carved; bytes
that fit no format keep no type either (``application/octet-stream``); repeated rows give
equal rows; carved pieces come in order of their start, and one inside another carved
piece isn't listed again. Extra columns are carried through.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import frugal

RATE = 8000
UNIT = 192
UNKNOWN = "application/octet-stream"

# The magic bytes of each format.
MAGIC = (
    (b"\x89PNG\r\n\x1a\n", "image/png"),
    (b"GIF87a", "image/gif"),
    (b"GIF89a", "image/gif"),
    (b"\xff\xd8\xff", "image/jpeg"),
    (b"RIFF", "riff"),
    (b"BM", "image/bmp"),
    (b"%PDF-", "application/pdf"),
    (b"PK\x03\x04", "application/zip"),
    (b"\x1f\x8b\x08", "application/gzip"),
    (b"OggS", "audio/ogg"),
    (b"fLaC", "audio/flac"),
)


def wav_bytes(payload: bytes, rate: int = RATE) -> bytes:
    """Mono unsigned 8-bit PCM; an odd payload gets the format's pad byte."""
    n = len(payload)
    body = b"fmt " + struct.pack("<IHHIIHH", 16, 1, 1, rate, rate, 1, 8) + b"data" + struct.pack("<I", n) + payload + b"\0" * (n % 2)
    return b"RIFF" + struct.pack("<I", 4 + len(body)) + b"WAVE" + body


def wav_payload(media: bytes) -> tuple[int, bytes]:
    """Sample rate and samples of the data chunk, found by walking the chunks."""
    at, rate = 12, 0
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"fmt ":
            rate = struct.unpack_from("<I", media, at + 12)[0]
        if name == b"data":
            return rate, media[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    raise ValueError("no data chunk")


def _png(b: bytes, at: int) -> tuple[str, int] | None:
    i, first = at + 8, True
    while i + 12 <= len(b):
        n, kind = struct.unpack_from(">I4s", b, i)
        if i + 12 + n > len(b) or (first and (kind != b"IHDR" or n != 13)) or zlib.crc32(b[i + 4 : i + 8 + n]) != struct.unpack_from(">I", b, i + 8 + n)[0]:
            return None
        i, first = i + 12 + n, False
        if kind == b"IEND":
            return "image/png", i - at
    return None


def _gif(b: bytes, at: int) -> tuple[str, int] | None:
    if at + 13 > len(b):
        return None
    flags = b[at + 10]
    i = at + 13 + (3 << ((flags & 7) + 1) if flags & 0x80 else 0)

    def blocks(i: int) -> int:
        while i < len(b) and b[i]:
            i += b[i] + 1
        return i + 1

    frames = 0
    while i < len(b):
        if b[i] == 0x3B:
            return ("image/gif", i + 1 - at) if frames else None
        if b[i] == 0x21:
            i = blocks(i + 2)
        elif b[i] == 0x2C and i + 10 < len(b):
            local = b[i + 9]
            i = blocks(i + 10 + (3 << ((local & 7) + 1) if local & 0x80 else 0) + 1)
            frames += 1
        else:
            return None
    return None


def _jpeg(b: bytes, at: int) -> tuple[str, int] | None:
    i, scan = at + 2, False
    while i + 1 < len(b):
        if b[i] != 0xFF:
            if not scan:
                return None
            i = b.find(b"\xff", i)
            if i < 0:
                return None
            continue
        mark = b[i + 1]
        if mark == 0xD8:  # another picture begins, so this one has no end
            return None
        if mark == 0xD9:
            return ("image/jpeg", i + 2 - at) if scan else None
        if mark in (0x00, 0x01, 0xFF) or 0xD0 <= mark <= 0xD7:
            i += 1 if mark == 0xFF else 2
            continue
        if i + 4 > len(b) or (n := struct.unpack_from(">H", b, i + 2)[0]) < 2:
            return None
        scan |= mark == 0xDA
        i += 2 + n
    return None


def _riff(b: bytes, at: int) -> tuple[str, int] | None:
    if at + 12 > len(b):
        return None
    size, form = struct.unpack_from("<I4s", b, at + 4)
    end, kinds = at + 8 + size, {b"WAVE": "audio/wav", b"WEBP": "image/webp", b"AVI ": "video/x-msvideo"}
    if form not in kinds or end > len(b) or size < 12:
        return None
    i, names = at + 12, []
    while i + 8 <= end:
        name, n = struct.unpack_from("<4sI", b, i)
        names.append(name)
        i += 8 + n + n % 2
    if i != end or (form == b"WAVE" and not {b"fmt ", b"data"} <= set(names)):
        return None
    return kinds[form], end - at


def _bmp(b: bytes, at: int) -> tuple[str, int] | None:
    if at + 26 > len(b):
        return None
    size, spare, pixels, header = struct.unpack_from("<IIII", b, at + 2)
    return ("image/bmp", size) if spare == 0 and header in (12, 40, 52, 56, 64, 108, 124) and 14 + header <= pixels <= size and at + size <= len(b) else None


def _pdf(b: bytes, at: int, marks: Marks) -> tuple[str, int] | None:
    """Up to the last end mark before the next header, if its startxref points to a cross-reference table or stream."""
    headers = marks.places(b"%PDF-")
    k = bisect_right(headers, at)
    until = headers[k] if k < len(headers) else len(b)
    trailers = marks.trailers()
    k = bisect_left(trailers, (until,)) - 1
    if k < 0 or trailers[k][0] < at:
        return None
    _, end, place = trailers[k]
    table = b[at + place : at + place + 24]
    return ("application/pdf", end - at) if end <= until and (table.startswith(b"xref") or re.match(rb"\d+\s+\d+\s+obj", table)) else None


def _zip(b: bytes, at: int, marks: Marks) -> tuple[str, int] | None:
    """Up to the end record whose directory, by its size and place, belongs to an archive that starts here."""
    end = marks.archives().get(at)
    return ("application/zip", end - at) if end is not None else None


def _gzip(b: bytes, at: int) -> tuple[str, int] | None:
    engine, rest = zlib.decompressobj(31), memoryview(b)[at:]
    try:
        while not engine.eof and len(rest):  # the output goes in pieces, so that memory stays bounded
            engine.decompress(rest, 1 << 20)
            rest = engine.unconsumed_tail
    except zlib.error:
        return None
    return ("application/gzip", len(b) - at - len(engine.unused_data)) if engine.eof else None


def _ogg(b: bytes, at: int, marks: Marks) -> tuple[str, int] | None:
    """Whole pages from one with the start flag up to one with the end flag; where a chain of pages ends is noted for each of them."""
    if at + 5 >= len(b) or not b[at + 5] & 2:
        return None
    path, i, end = [], at, -1
    while i not in marks.chains:
        path.append(i)
        if i + 27 > len(b) or b[i : i + 4] != b"OggS" or b[i + 4] != 0:
            break
        n = b[i + 26]
        after = i + 27 + n + sum(b[i + 27 : i + 27 + n])
        if after > len(b):
            break
        if b[i + 5] & 4:
            end = after
            break
        i = after
    end = marks.chains.get(i, end)
    marks.chains.update(dict.fromkeys(path, end))
    return ("audio/ogg", end - at) if end > 0 else None


def _crc_table(bits: int, polynomial: int) -> list[int]:
    out = []
    for byte in range(256):
        value = byte << (bits - 8)
        for _ in range(8):
            value = (value << 1 ^ polynomial if value >> (bits - 1) & 1 else value << 1) & ((1 << bits) - 1)
        out.append(value)
    return out


_CRC8, _CRC16 = _crc_table(8, 0x07), _crc_table(16, 0x8005)


def _flac_header(b: bytes, i: int) -> int:
    """Length of a valid frame header at i (its check sum included), or 0."""
    if i + 6 > len(b) or b[i] != 0xFF or b[i + 1] & 0xFE != 0xF8 or b[i + 2] >> 4 == 0 or b[i + 2] & 15 == 15 or b[i + 3] >> 4 > 10 or b[i + 3] & 1:
        return 0
    lead = b[i + 4]
    extra = 0 if lead < 0x80 else next((k for k in range(1, 7) if not lead >> (6 - k) & 1), 7)
    size = 5 + extra + {6: 1, 7: 2}.get(b[i + 2] >> 4, 0) + {12: 1, 13: 2, 14: 2}.get(b[i + 2] & 15, 0)
    if extra > 6 or i + size >= len(b):
        return 0
    check = 0
    for byte in b[i : i + size]:
        check = _CRC8[check ^ byte]
    return size + 1 if check == b[i + size] else 0


def _flac(b: bytes, at: int) -> tuple[str, int] | None:
    """Metadata blocks, then frames: each ends where its check sum over all bytes comes out even and the next frame, or none, begins.

    A frame is sought within the largest size that the stream states; streams that state none aren't confirmed.
    """
    i, first, largest = at + 4, True, 0
    while i + 4 <= len(b):
        head, n = b[i], int.from_bytes(b[i + 1 : i + 4], "big")
        if (first and (head & 0x7F or n != 34)) or i + 4 + n > len(b):
            return None
        if first:
            largest = int.from_bytes(b[i + 11 : i + 14], "big")
        i, first = i + 4 + n, False
        if head & 0x80:
            break
    else:
        return None
    frames = 0
    while size := _flac_header(b, i):
        check, end = 0, 0
        for k in range(i, min(len(b), i + largest)):
            check = (check << 8 ^ _CRC16[check >> 8 ^ b[k]]) & 0xFFFF
            if check == 0 and k >= i + size + 1:
                end = k + 1
                if end == len(b) or _flac_header(b, end):
                    break
        if not end:
            return None
        i, frames = end, frames + 1
    return ("audio/flac", i - at) if frames else None


class Marks:
    """What validators look up in a cell, found once for all hits, so that many false hits don't make many scans."""

    def __init__(self, cell: bytes) -> None:
        self.cell, self.found, self.chains = cell, {}, {}

    def places(self, mark: bytes) -> list[int]:
        if mark not in self.found:
            self.found[mark] = [m.start() for m in re.finditer(re.escape(mark), self.cell)]
        return self.found[mark]

    def trailers(self) -> list[tuple[int, int, int]]:
        """(start, end, place of the cross-references) of each PDF trailer's last lines."""
        if "pdf" not in self.found:
            self.found["pdf"] = [(m.start(), m.end(), int(m[1])) for m in re.finditer(rb"startxref\s{1,4}(\d{1,12})\s{1,4}%%EOF", self.cell)]
        return self.found["pdf"]

    def archives(self) -> dict[int, int]:
        """Start and end of each archive by its end record (the last one, if several fit a start)."""
        if "zip" not in self.found:
            out = {}
            for end in self.places(b"PK\x05\x06"):
                if end + 22 <= len(self.cell):
                    size, place, note = struct.unpack_from("<IIH", self.cell, end + 12)
                    if end + 22 + note <= len(self.cell) and end - size - place >= 0:
                        out[end - size - place] = end + 22 + note
            self.found["zip"] = out
        return self.found["zip"]


_VALID = {"image/png": _png, "image/gif": _gif, "image/jpeg": _jpeg, "riff": _riff, "image/bmp": _bmp, "application/pdf": _pdf, "application/zip": _zip, "application/gzip": _gzip, "audio/ogg": _ogg, "audio/flac": _flac}
_MARKED = ("application/pdf", "application/zip", "audio/ogg")


@cache
def _automaton():
    import ahocorasick

    found = ahocorasick.Automaton()
    for magic, kind in MAGIC:
        found.add_word(magic.decode("latin-1"), (len(magic), kind))
    found.make_automaton()
    return found


def sniff(cell: bytes | None) -> list[tuple[int, int, str]]:
    """Validated media in a cell as (start, length, type), outermost first, then by start."""
    if not cell:
        return []
    found: list[tuple[int, int, str]] = []
    covered = 0  # end of the last piece listed below the cell's own
    marks = Marks(cell)
    for last, (n, kind) in _automaton().iter(cell.decode("latin-1")):
        at = last - n + 1
        if at and at < covered:
            continue
        if ok := _VALID[kind](cell, at, marks) if kind in _MARKED else _VALID[kind](cell, at):
            found.append((at, ok[1], ok[0]))
            covered = at + ok[1] if at else 0
    return found


SNIFF_TYPE = "detected string, valid boolean, length long, corrected boolean, carved array<struct<start: long, length: long, type: string>>"


def sniff_media(frame: DataFrame, media: str = "media", declared: str = "declared") -> DataFrame:
    """frame (without columns of these names) with the columns of SNIFF_TYPE for its media column."""
    fresh = pa.schema([("detected", pa.string()), ("valid", pa.bool_()), ("length", pa.int64()), ("corrected", pa.bool_()), ("carved", pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64()), ("type", pa.string())])))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for cell, said in zip(batch.column(media), batch.column(declared).to_pylist(), strict=True):
                found = sniff(cell.as_py())
                own = next((x for x in found if x[0] == 0), None)
                kind = own[2] if own else UNKNOWN if cell.is_valid and len(cell.as_buffer()) else None
                inner = [{"start": a, "length": n, "type": t} for a, n, t in found if a]
                out.append((kind, own is not None, own[1] if own else None, kind is not None and kind != said, inner))
            columns = [pa.array([x[i] for x in out], type=field.type) for i, field in enumerate(fresh)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *columns], names=[*batch.schema.names, *fresh.names])

    frame = frame.drop(*fresh.names)
    spec = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in frame.schema.fields] + [SNIFF_TYPE])
    return frame.mapInArrow(frugal(run), spec)


def store_texts(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs without its text, with ``media`` (its UTF-8 bytes as WAV, spaces up to a positive multiple of UNIT) and ``n_bytes``."""
    bytes_of = F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8")
    n = F.octet_length(bytes_of).cast("bigint")
    wanted = F.greatest(F.ceil(n / UNIT), F.lit(1)) * UNIT
    padded = docs.select(*[c for c in docs.columns if c not in (text, "n_bytes", "media")], n.alias("n_bytes"), F.concat(bytes_of, F.encode(F.repeat(F.lit(" "), (wanted - n).cast("int")), "UTF-8")).alias("media"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index("media")
            yield batch.set_column(at, "media", pa.array([wav_bytes(x.as_py()) for x in batch.column(at)], type=pa.binary()))

    return padded.mapInArrow(frugal(run), padded.schema)


def media_digests(stored: DataFrame, key: str = "doc_id") -> DataFrame:
    """Digests and a feature line of sniffed WAV cells, all from the stored bytes, beside what the sniffing says: the type found, whether it corrects the declared one, and the pieces carved (start:length:type, comma-joined)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for cell, kind, ok in zip(batch.column("media"), batch.column("detected").to_pylist(), batch.column("valid").to_pylist(), strict=True):
                media = cell.as_py()
                rate, payload = wav_payload(media)
                samples = np.frombuffer(payload, dtype=np.uint8)
                changes = int(np.count_nonzero(np.diff(samples)))
                line = f"{kind};valid={int(ok)};rate={rate};samples={len(samples)};mean={samples.mean():.4f};min={samples.min()};max={samples.max()};changes={changes}"
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), line))
            kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
            names = ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")
            columns = [pa.array([x[i] for x in rows], type=t) for i, t in enumerate(kinds)]
            carved = pa.array([",".join(f"{c['start']}:{c['length']}:{c['type']}" for c in found) for found in batch.column("carved").to_pylist()], type=pa.string())
            columns += [batch.column("detected"), batch.column("corrected"), carved]
            yield pa.RecordBatch.from_arrays([batch.column(key), batch.column("n_bytes"), *columns], names=[key, "n_bytes", *names, "detected", "corrected", "carved"])

    kind = stored.schema[key].dataType.simpleString()
    return stored.mapInArrow(frugal(run), f"`{key}` {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, detected string, corrected boolean, carved string")
