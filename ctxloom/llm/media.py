"""Media columns: signature sniffing, validation, type correction and carving.

An Aho-Corasick automaton finds all magic byte strings of a blob in one pass. Every hit is then handed to its format's
validator, which reads the structure (chunk lengths, checksums, end marks) and returns the exact length or refuses. The
blob's type is the valid format at offset 0 that spans it; other valid hits are embedded media, which can be carved out.

Null blobs have type ``null``, empty ones ``empty``; unknown ones ``application/octet-stream``. Media inside media are
listed with their parent, the smallest that holds them. Equal blobs give equal results, so repeated rows do, too. Blobs are
read whole, however long; marks that a format ends with are found in one pass for all hits of a blob. An empty table gives
an empty result. Columns of the input that are named like a result column are replaced by it; others pass.
"""

from __future__ import annotations

import functools
import hashlib
import re
import struct
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.session import load, schema_with

UNKNOWN = "application/octet-stream"
# Magic bytes of each format and the offset of the magic in the file.
MAGIC = {
    "image/png": [(b"\x89PNG\r\n\x1a\n", 0)],
    "image/jpeg": [(b"\xff\xd8\xff", 0)],
    "image/gif": [(b"GIF87a", 0), (b"GIF89a", 0)],
    "image/bmp": [(b"BM", 0)],
    "audio/wav": [(b"RIFF", 0)],
    "audio/flac": [(b"fLaC", 0)],
    "audio/ogg": [(b"OggS", 0)],
    "video/mp4": [(b"ftyp", 4)],
    "application/pdf": [(b"%PDF-", 0)],
    "application/zip": [(b"PK\x03\x04", 0)],
    "application/gzip": [(b"\x1f\x8b\x08", 0)],
    "image/x-portable-graymap": [(b"P5\n", 0)],
}


RIFF_KINDS = {b"WAVE": "audio/wav", b"WEBP": "image/webp", b"AVI ": "video/avi"}


class Found(NamedTuple):
    kind: str
    start: int
    length: int
    parent: int = -1  # place of the smallest medium around it in the list


def _u32(data: bytes, at: int, order: str = "<") -> int:
    return struct.unpack_from(order + "I", data, at)[0] if at + 4 <= len(data) else -1


def _png(d: bytes, at: int) -> tuple[str, int] | None:
    i = at + 8
    first = True
    while i + 12 <= len(d):
        size, kind = _u32(d, i, ">"), d[i + 4 : i + 8]
        if size > len(d) or i + 12 + size > len(d) or first and (kind != b"IHDR" or size != 13):
            return None
        if zlib.crc32(d[i + 4 : i + 8 + size]) != _u32(d, i + 8 + size, ">"):
            return None
        i, first = i + 12 + size, False
        if kind == b"IEND":
            return "image/png", i - at
    return None


# The markers of JPEG frame headers.
_FRAMES = frozenset(range(0xC0, 0xD0)) - {0xC4, 0xC8, 0xCC}


def _jpeg(d: bytes, at: int) -> tuple[str, int] | None:
    """Segments by their lengths to the end mark; there must be a frame header with sides and components, and a scan after it."""
    i, frame, scan = at + 2, False, False
    while i + 2 <= len(d) and d[i] == 0xFF:
        mark = d[i + 1]
        if mark == 0xD9:
            return ("image/jpeg", i + 2 - at) if scan else None
        if mark in (0x01, *range(0xD0, 0xD8)):
            i += 2
            continue
        size = struct.unpack_from(">H", d, i + 2)[0] if i + 4 <= len(d) else 0
        if size < 2 or mark == 0xDA and not frame:
            return None
        if mark in _FRAMES:
            parts = d[i + 9] if i + 9 < len(d) else 0
            frame = size == 8 + 3 * parts and parts > 0 and struct.unpack_from(">H", d, i + 7)[0] > 0
            if not frame:
                return None
        i += 2 + size
        if mark == 0xDA:
            scan = True  # entropy-coded data runs to the next real marker
            while True:
                i = d.find(b"\xff", i)
                if i < 0 or i + 1 >= len(d):
                    return None
                if d[i + 1] == 0 or 0xD0 <= d[i + 1] <= 0xD7:
                    i += 2
                    continue
                break
    return None


def _gif(d: bytes, at: int) -> tuple[str, int] | None:
    if at + 13 > len(d):
        return None
    flags, i = d[at + 10], at + 13
    i += 3 * (2 << (flags & 7)) if flags & 0x80 else 0
    while i < len(d):
        block = d[i]
        if block == 0x3B:
            return "image/gif", i + 1 - at
        if block == 0x21:
            i += 2
        elif block == 0x2C and i + 10 <= len(d):
            i += 10 + (3 * (2 << (d[i + 9] & 7)) if d[i + 9] & 0x80 else 0) + 1
        else:
            return None
        while i < len(d) and d[i]:
            i += d[i] + 1
        i += 1
    return None


def _bmp(d: bytes, at: int) -> tuple[str, int] | None:
    size, reserved, start, header = (_u32(d, at + k) for k in (2, 6, 10, 14))
    if reserved or header not in (12, 40, 52, 56, 64, 108, 124) or not 14 + header <= start <= size <= len(d) - at:
        return None
    return "image/bmp", size


def _riff(d: bytes, at: int) -> tuple[str, int] | None:
    size, kind = _u32(d, at + 4), RIFF_KINDS.get(d[at + 8 : at + 12])
    if not kind or size < 4 or at + 8 + size > len(d):
        return None
    i, end, seen = at + 12, at + 8 + size, []
    while i + 8 <= end:
        seen.append(d[i : i + 4])
        i += 8 + _u32(d, i + 4) + (_u32(d, i + 4) & 1)
    if i != end or kind == "audio/wav" and not (seen and seen[0] == b"fmt " and b"data" in seen):
        return None
    return kind, 8 + size


def _crc_table(bits: int, polynomial: int) -> list[int]:
    top, mask, out = 1 << (bits - 1), (1 << bits) - 1, []
    for x in range(256):
        c = x << (bits - 8)
        for _ in range(8):
            c = (c << 1 ^ polynomial if c & top else c << 1) & mask
        out.append(c)
    return out


_CRC8, _CRC16 = _crc_table(8, 0x07), _crc_table(16, 0x8005)


def _flac_frame(d: bytes, at: int) -> tuple[int, int] | None:
    """Length of a frame header with a right checksum, and the frame's samples."""
    if at + 6 > len(d) or d[at] != 0xFF or d[at + 1] & 0xFE != 0xF8 or d[at + 3] & 1:
        return None
    block, rate, lead = d[at + 2] >> 4, d[at + 2] & 15, d[at + 4]
    ones = 8 - (lead ^ 0xFF).bit_length()
    if not block or rate == 15 or d[at + 3] >> 4 > 10 or ones in (1, 8):
        return None
    i = at + 4 + max(1, ones)
    extra = {6: 1, 7: 2}.get(block, 0)
    size = int.from_bytes(d[i : i + extra], "big") + 1 if extra else 192 if block == 1 else 576 << (block - 2) if block < 6 else 256 << (block - 8)
    i += extra + {12: 1, 13: 2, 14: 2}.get(rate, 0)
    crc = 0
    for x in d[at : i + 1]:
        crc = _CRC8[crc ^ x]
    return (i + 1 - at, size) if i < len(d) and not crc else None


def _flac(d: bytes, at: int) -> tuple[str, int] | None:
    """Frames are walked by header and frame checksums until the samples that the stream names are there.

    A frame ends where its checksum is right and a frame header follows; the last one at the first right checksum.
    """
    i, last = at + 4, False
    while not last:
        if i + 4 > len(d):
            return None
        head, size = d[i], int.from_bytes(d[i + 1 : i + 4], "big")
        if i == at + 4 and (head & 0x7F or size != 34):
            return None
        i, last = i + 4 + size, bool(head & 0x80)
    if i > len(d):
        return None
    least = int.from_bytes(d[at + 12 : at + 15], "big")
    total, seen = int.from_bytes(d[at + 21 : at + 26], "big") & (1 << 36) - 1, 0
    while (not total or seen < total) and (frame := _flac_frame(d, i)):
        head, samples = frame
        crc, first, end = 0, 0, 0
        final = total and seen + samples >= total
        for j in range(i, len(d)):
            crc = (crc << 8 & 0xFFFF) ^ _CRC16[crc >> 8 ^ d[j]]
            if not crc and j + 1 - i >= max(head + 3, least):
                first = first or j + 1
                if final or _flac_frame(d, j + 1):
                    end = j + 1
                    break
        end = end or (first if not total else 0)
        if not end:
            return None
        i, seen = end, seen + samples
    return ("audio/flac", i - at) if seen >= total else None


def _ogg(d: bytes, at: int) -> tuple[str, int] | None:
    i = at
    while i + 27 <= len(d) and d[i : i + 4] == b"OggS" and d[i + 4] == 0:
        flags, segments = d[i + 5], d[i + 26]
        if i == at and not flags & 2:
            return None
        i += 27 + segments + sum(d[i + 27 : i + 27 + segments])
        if flags & 4:
            return ("audio/ogg", i - at) if i <= len(d) else None
    return None


def _mp4(d: bytes, at: int) -> tuple[str, int] | None:
    i, boxes = at, set()
    while i + 8 <= len(d):
        size, kind = _u32(d, i, ">"), d[i + 4 : i + 8]
        if size < 8 or i + size > len(d) or not kind.isalnum():
            break
        boxes.add(kind)
        i += size
    return ("video/mp4", i - at) if {b"ftyp", b"moov"} <= boxes else None


class Marks:
    """What the formats with a table at their end need to know of a blob, found once for all hits."""

    def __init__(self, data: bytes):
        self.data = data

    @functools.cached_property
    def zips(self) -> dict[int, int]:
        """Start -> length of every archive whose end record names a central directory that is where it says."""
        d, out, at = self.data, {}, self.data.find(b"PK\x05\x06")
        while at >= 0:
            if at + 22 <= len(d):
                entries, size, start = struct.unpack_from("<HII", d, at + 10)
                begin, comment = at - size - start, struct.unpack_from("<H", d, at + 20)[0]
                named = entries and d[at - size : at - size + 4] == b"PK\x01\x02"
                if begin >= 0 and named and at + 22 + comment <= len(d):
                    out.setdefault(begin, at + 22 + comment - begin)
            at = d.find(b"PK\x05\x06", at + 1)
        return out

    @functools.cached_property
    def pdfs(self) -> dict[int, int]:
        """Start -> length of every document. A document reaches from its header to the last end mark before the next header
        whose cross-reference offset points at a table or an object of it; updates that were appended belong to it."""
        d, out = self.data, {}
        heads = [m.start() for m in re.finditer(rb"%PDF-", d)]
        ends = [(m.start(1), int(m.group(1)), m.end()) for m in re.finditer(rb"startxref\s+(\d{1,12})\s+%%EOF", d)]
        k = 0
        for head, after in zip(heads, [*heads[1:], len(d)]):
            while k < len(ends) and ends[k][0] < head:
                k += 1
            while k < len(ends) and ends[k][2] <= after:
                place = head + ends[k][1]
                if place < ends[k][0] and re.compile(rb"xref\b|\d+\s+\d+\s+obj\b").match(d, place):
                    out[head] = ends[k][2] - head
                k += 1
        return out


def _pdf(d: bytes, at: int, marks: Marks) -> tuple[str, int] | None:
    return ("application/pdf", marks.pdfs[at]) if at in marks.pdfs else None


def _zip(d: bytes, at: int, marks: Marks) -> tuple[str, int] | None:
    return ("application/zip", marks.zips[at]) if at in marks.zips else None


def _gzip(d: bytes, at: int) -> tuple[str, int] | None:
    unpack = zlib.decompressobj(31)
    try:
        i = at
        while i < len(d) and not unpack.eof:
            unpack.decompress(d[i : i + 65536])
            i += 65536
    except zlib.error:
        return None
    return ("application/gzip", min(i, len(d)) - len(unpack.unused_data) - at) if unpack.eof else None


def _pgm(d: bytes, at: int) -> tuple[str, int] | None:
    fields = d[at : at + 64].split(maxsplit=4)[:4]
    if len(fields) < 4 or not all(x.isdigit() for x in fields[1:4]) or int(fields[3]) != 255:
        return None
    head = len(b"P5\n%d %d\n255\n" % (int(fields[1]), int(fields[2])))
    size = head + int(fields[1]) * int(fields[2])
    return ("image/x-portable-graymap", size) if at + size <= len(d) else None


VALIDATE = {
    "image/png": _png, "image/jpeg": _jpeg, "image/gif": _gif, "image/bmp": _bmp, "audio/wav": _riff, "audio/flac": _flac, "audio/ogg": _ogg,
    "video/mp4": _mp4, "application/gzip": _gzip, "image/x-portable-graymap": _pgm,
}
VALIDATE_WITH_MARKS = {"application/pdf": _pdf, "application/zip": _zip}


@functools.lru_cache(maxsize=1)
def automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for kind, marks in MAGIC.items():
        for magic, offset in marks:
            a.add_word(magic.decode("latin-1"), (kind, len(magic), offset))
    a.make_automaton()
    return a


def sniff(data: bytes | None) -> list[Found]:
    """All valid media in a blob, outermost first, in order of their start."""
    hits = set()
    marks = Marks(data or b"")
    for last, (kind, size, offset) in automaton().iter((data or b"").decode("latin-1")):
        at = last + 1 - size - offset
        if at >= 0 and (good := VALIDATE_WITH_MARKS[kind](data, at, marks) if kind in VALIDATE_WITH_MARKS else VALIDATE[kind](data, at)):
            hits.add((at, -good[1], good[0]))
    found: list[Found] = []
    around: list[int] = []  # media that the place is in, outermost first
    for at, size, kind in sorted(hits):
        while around and found[around[-1]].start + found[around[-1]].length <= at:
            around.pop()
        parent = next((p for p in reversed(around) if at - size <= found[p].start + found[p].length), -1)
        found.append(Found(kind, at, -size, parent))
        around.append(len(found) - 1)
    return found


def true_type(data: bytes | None, found: list[Found]) -> str:
    if not data:
        return "null" if data is None else "empty"
    return found[0].kind if found and found[0].start == 0 else UNKNOWN


ADDED = ("media_type", "corrected", "media")


def inspect(rows: DataFrame, data: str = "data", declared: str = "declared") -> DataFrame:
    """Adds to each blob: media_type (what it is), corrected (differs from the declared type), and media (kind, start, length and parent of all found)."""
    kept = [c for c in rows.columns if c not in ADDED]
    rows = rows.select(*kept, F.col(data).alias("__data"), F.col(declared).alias("__declared"))
    # kinds cross as numbers: a batch without any medium would have an empty column of names, which not all readers take
    names = sorted({*VALIDATE, *VALIDATE_WITH_MARKS, *RIFF_KINDS.values()})
    schema = schema_with(T.StructType(rows.schema.fields[: len(kept)]), "media_type string, corrected boolean, media array<struct<kind:int,start:long,length:long,parent:int>>")
    at, said_at = len(kept), len(kept) + 1

    def kernel(batches):
        for batch in batches:
            blobs, said = batch.column(at), batch.column(said_at).to_pylist()
            hits = [sniff(b.as_py()) for b in blobs]
            kinds = [true_type(b.as_py(), h) for b, h in zip(blobs, hits)]
            media = pa.array([[{**h._asdict(), "kind": names.index(h.kind)} for h in hs] for hs in hits], pa.list_(pa.struct([("kind", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("parent", pa.int32())])))
            yield pa.RecordBatch.from_arrays([*batch.columns[:at], pa.array(kinds, pa.string()), pa.array([k != s for k, s in zip(kinds, said)], pa.bool_()), media], names=schema.names)

    named = F.transform("media", lambda x: F.struct(F.get(F.lit(names), x["kind"]).alias("kind"), x["start"].alias("start"), x["length"].alias("length"), x["parent"].alias("parent")))
    return rows.mapInArrow(kernel, schema).withColumn("media", named)


def carve(rows: DataFrame, key: str, data: str = "data") -> DataFrame:
    """One row per medium found: key, kind, start, bytes. A key that is named like one of the others is called ``key``."""
    kind = rows.schema[key].dataType.simpleString()
    name = "key" if key in ("kind", "start", "bytes") else key

    def kernel(batches):
        for batch in batches:
            out = [(k, h.kind, h.start, b[h.start : h.start + h.length]) for k, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) for h in sniff(b)]
            cols = list(zip(*out)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], batch.schema.field(0).type), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.binary())], names=[name, "kind", "start", "bytes"])

    return rows.select(key, data).mapInArrow(kernel, f"`{name}` {kind}, kind string, start long, bytes binary")


def wav_of(payload: bytes, rate: int = 8000) -> bytes:
    """A mono file of unsigned 8-bit samples that holds the payload, one byte a sample (its length must be even)."""
    head = b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, rate, rate, 1, 8) + b"data" + struct.pack("<I", len(payload))
    return b"RIFF" + struct.pack("<I", len(head) + len(payload)) + head + payload


def samples_of(media: bytes) -> bytes:
    """The data chunk of a WAV file, by walking its chunks."""
    i = 12
    while i + 8 <= len(media):
        size = _u32(media, i + 4)
        if media[i : i + 4] == b"data":
            return media[i + 8 : i + 8 + size]
        i += 8 + size + (size & 1)
    raise ValueError("no data chunk")


def store_and_read(text: str | None) -> tuple:
    """Text to padded payload to stored medium, and everything that is then read back from the stored bytes alone."""
    raw = (text or "").encode()
    stored = wav_of(raw + bytes(-len(raw) % 64 if raw else 64))
    found = sniff(stored)  # the stored bytes are read as a blob that is declared as unknown
    if not found or found[0].kind != "audio/wav":
        raise ValueError("the stored medium is not recognised")
    medium = stored[found[0].start : found[0].start + found[0].length]
    back = samples_of(medium)
    level = np.frombuffer(back, np.uint8)
    swing = np.count_nonzero((level[1:] < 128) != (level[:-1] < 128))
    feature = f"{found[0].kind};samples={len(back)};mean={level.mean():.6f};peak={int(level.max())};crossings={swing}"
    kind = true_type(stored, found)
    carved = [stored[f.start : f.start + f.length] for f in found[1:]]
    return (
        len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(medium), hashlib.sha256(medium).hexdigest(), feature,
        kind, kind != UNKNOWN, ",".join(f.kind for f in found[1:]), hashlib.sha256(b"".join(carved)).hexdigest() if carved else None,
    )


RESULT = """doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string,
  media_type string, corrected boolean, embedded string, embedded_sha256 string"""


def stored_texts(docs: DataFrame) -> DataFrame:
    """Each text as a stored medium: what is read back from it, its type (declared as unknown, corrected by its bytes), and
    the kinds and digest of media that its payload carries and that were carved out. Null texts are empty ones."""
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.bool_(), pa.string(), pa.string()]
    names = [c.split()[0] for c in RESULT.split(",")]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [store_and_read(t.as_py()) for t in batch.column(1)]
            cols = list(zip(*rows)) or [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, k) for c, k in zip(cols, kinds)]], names=names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(kernel, RESULT)


def op4_media_sniffing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stored_texts(load(spark, sf_dir, "documents"))


QUERIES = {"op4_media_sniffing": op4_media_sniffing}
ORACLES: dict[str, str] = {}
