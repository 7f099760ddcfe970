"""Byte-level BPE through a sentencepiece model that is written straight from the rank file.

Each byte is mapped to one printable character, so every vocabulary entry becomes a piece; its score is minus its rank and
its id is its rank. With identity normalisation the library's merge loop (best score first, leftmost on ties) is then the
merge loop of the rank file. Texts are split by the tokenizer's pattern and each match is encoded by itself; ids decode by
the inverse mapping.

Null and empty texts give no ids. Long matches are encoded whole. An empty table gives an empty result; columns of the
input beyond doc_id and text are not read.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import struct
from collections.abc import Iterator

import pyarrow as pa
import regex
import sentencepiece
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.session import load

CACHE = 200_000  # matches kept with their ids; cleared when full
CACHED_LENGTH = 40


def byte_alphabet() -> list[str]:
    """A printable character for each byte: Latin-1's own where it prints, else the next free one from U+0100 on."""
    printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = iter(range(0x100, 0x200))
    return [chr(b) if b in set(printable) else chr(next(rest)) for b in range(256)]


def read_ranks(path: str) -> list[bytes]:
    """Vocabulary entries by rank; ranks must run 0, 1, 2 ..."""
    with open(path, "rb") as f:
        pairs = {int(rank): base64.b64decode(token) for token, rank in map(bytes.split, f)}
    return [pairs[i] for i in range(len(pairs))]


def _varint(n: int) -> bytes:
    out = b""
    while n > 0x7F:
        out, n = out + bytes([n & 0x7F | 0x80]), n >> 7
    return out + bytes([n])


def _field(number: int, value: bytes | int | float | str) -> bytes:
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    if isinstance(value, int):
        return _varint(number << 3) + _varint(value)
    value = value.encode() if isinstance(value, str) else value
    return _varint(number << 3 | 2) + _varint(len(value)) + value


def serialise(vocabulary: list[bytes]) -> bytes:
    """A sentencepiece model file: pieces (1), trainer spec (2) with type BPE, normaliser spec (3) that changes nothing."""
    letters = byte_alphabet()
    unknown = len(vocabulary)
    pieces = [_field(1, _field(1, "".join(letters[b] for b in token)) + _field(2, float(-rank))) for rank, token in enumerate(vocabulary)]
    pieces.append(_field(1, _field(1, "<unk>") + _field(2, 0.0) + _field(3, 2)))
    trainer = _field(3, 2) + _field(4, unknown + 1) + _field(40, unknown)
    normaliser = _field(1, "identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)
    return b"".join(pieces) + _field(2, trainer) + _field(3, normaliser)


class Codec:
    def __init__(self, path: str, pattern: str):
        self.vocabulary = read_ranks(path)
        self.model = sentencepiece.SentencePieceProcessor(model_proto=serialise(self.vocabulary))
        self.split = regex.compile(pattern).findall
        letters = byte_alphabet()
        self.mapped = {i: c for i, c in enumerate(letters)}
        self.whole = {token: rank for rank, token in enumerate(self.vocabulary)}
        self.names = [str(i) for i in range(len(self.vocabulary))]
        self.cache: dict[str, list[int]] = {}

    def _pieces(self, match: str) -> list[int]:
        data = match.encode("utf-8", "surrogatepass")
        rank = self.whole.get(data)  # a match that is an entry is that entry
        if rank is not None:
            return [rank]
        return self.model.encode(data.decode("latin-1").translate(self.mapped))

    def encode(self, text: str) -> list[int]:
        cache, out = self.cache, []
        for match in self.split(text):
            ids = cache.get(match)
            if ids is None:
                ids = self._pieces(match)
                if len(match) <= CACHED_LENGTH:
                    if len(cache) >= CACHE:
                        cache.clear()
                    cache[match] = ids
            out += ids
        return out

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.vocabulary.__getitem__, ids))


@functools.lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> Codec:
    return Codec(path, pattern)


RESULT = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Per document the number of ids, the digest of the ids and the digest of the bytes they decode to. Narrow, no shuffle."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column(0), batch.column(1)):
                ids = c.encode(text.as_py() or "")
                rows.append((doc_id.as_py(), len(ids), hashlib.sha256(" ".join(map(c.names.__getitem__, ids)).encode()).hexdigest(), hashlib.sha256(c.decode(ids)).hexdigest()))
            cols = list(zip(*rows)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays(
                [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.string()), pa.array(cols[3], pa.string())],
                names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(kernel, RESULT)


def encode_ids(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and the ids themselves."""

    def kernel(batches):
        c = codec(path, pattern)
        for batch in batches:
            ids = [c.encode(t.as_py() or "") for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(kernel, "doc_id long, ids array<int>")


def decode_ids(rows: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and the decoded bytes of ``ids``."""

    def kernel(batches):
        c = codec(path, pattern)
        for batch in batches:
            data = [c.decode(ids.as_py() or []) for ids in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(data, pa.binary())], names=["doc_id", "data"])

    return rows.select(F.col("doc_id").cast("long"), "ids").mapInArrow(kernel, "doc_id long, data binary")


def public_vocabulary() -> tuple[str, str]:
    """Path of the rank file and the split pattern. The package is installed on driver and executors alike."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(load(spark, sf_dir, "documents"), *public_vocabulary())


QUERIES = {"op3_byte_bpe": op3_byte_bpe}
ORACLES: dict[str, str] = {}
