"""Symbol streams: rows that carry a sequence, and how to read symbols from a batch of them.

A stream keeps its payload as it is stored (text or array<int>). Kernels turn an Arrow batch into one flat array of codes with
row offsets, so text crosses into Python once, at one byte a character, and contexts, counts and costs are all computed from
it in the same pass. Cutting into reads only changes the offsets.

Null payloads have no symbols. A stream's ids are ordinary columns and may be used for grouping.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.functions import symbols as S
from ctxloom.session import schema_with

SLICE_SYMBOLS = 1 << 20


class Flat(NamedTuple):
    codes: np.ndarray  # int64, sequence after sequence
    starts: np.ndarray  # int64, one more than there are sequences
    row: np.ndarray  # batch row of each sequence
    nth: np.ndarray  # number of the sequence within its row

    @property
    def size(self) -> np.ndarray:
        return np.diff(self.starts)

    def owner(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.starts) - 1), self.size)

    def position(self) -> np.ndarray:
        return np.arange(len(self.codes)) - np.repeat(self.starts[:-1], self.size)


@dataclass(frozen=True)
class Reader:
    kind: str
    m: int
    read_length: int
    tail: str
    group: int

    def __call__(self, payload: pa.Array) -> Flat:
        if self.kind == "array":
            lists = payload.combine_chunks() if isinstance(payload, pa.ChunkedArray) else payload
            codes = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
            size = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)
        elif self.kind == "digits":
            size = pc.fill_null(pc.binary_length(payload), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            codes = np.frombuffer(b"".join(x.as_buffer() for x in payload if x.is_valid), np.uint8).astype(np.int64) - 48
        else:
            texts = pc.fill_null(payload, "").to_pylist()
            points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
            table = S.class_table() if self.kind == "class" else S.text_table(S.TEXT_ALPHABET, len(S.TEXT_ALPHABET))
            codes = table[np.minimum(points, len(table) - 1)].astype(np.int64)
            size = np.array([len(t) for t in texts], np.int64)
        row, nth = np.arange(len(size)), np.zeros(len(size), np.int64)
        if self.read_length:
            codes, size, row, nth = _cut(codes, size, self.read_length, self.tail == "keep")
        if self.group > 1:
            codes, size = _group(codes, size, self.group, round(self.m ** (1 / self.group)))
        return Flat(codes, np.concatenate([[0], np.cumsum(size)]).astype(np.int64), row, nth)


@dataclass(frozen=True)
class Stream:
    df: DataFrame
    payload: str
    m: int
    kind: str = "array"  # or text, class, digits (see frame)
    ids: tuple[str, ...] = ()
    read_length: int = 0
    tail: str = "drop"
    group: int = 1

    def cut(self, length: int, tail: str = "drop") -> Stream:
        """Reads of a fixed length; what is left at the end of a row is dropped or kept as a shorter read."""
        return replace(self, read_length=length, tail=tail)

    def grouped(self, g: int) -> Stream:
        """g neighbouring symbols, without overlap, as one; a short tail is dropped."""
        return replace(self, group=g, m=self.m**g)

    def where(self, condition) -> Stream:
        return replace(self, df=self.df.where(condition))

    def with_df(self, df: DataFrame) -> Stream:
        return replace(self, df=df)

    @property
    def flat(self) -> Reader:
        """What kernels take along to read symbols from a batch's payload."""
        return Reader(self.kind, self.m, self.read_length, self.tail, self.group)

    def select(self, *columns: str) -> DataFrame:
        """Only what a kernel needs: the payload first, then the columns."""
        return self.df.select(self.payload, *[c for c in columns if c != self.payload])

    def frame(self, digits: bool = False) -> DataFrame:
        """One row a sequence: ids, read_no, syms array<int>, or a string of one digit a symbol (a quarter of the bytes; for m up to 10)."""
        keep = [c for c in self.ids if c != self.payload]
        schema = schema_with(T.StructType([self.df.schema[c] for c in keep]), f"read_no int, syms {syms_type(self.m, digits)}")
        flat = self.flat

        def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in pieces(batches):
                f = flat(batch.column(0))
                syms = syms_array(f.codes, f.starts, digits)
                cols = [batch.column(i + 1).take(pa.array(f.row)) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), syms], names=[*keep, "read_no", "syms"])

        return self.select(*keep).mapInArrow(kernel, schema)


def syms_type(m: int, digits: bool) -> str:
    if digits and m > 10:
        raise ValueError("digits stand for ten symbols at most")
    return "string" if digits else "array<int>"


def syms_array(codes: np.ndarray, starts: np.ndarray, digits: bool) -> pa.Array:
    """Sequences, given end to end, as lists or as strings of digits."""
    if digits:
        return pa.StringArray.from_buffers(len(starts) - 1, pa.py_buffer(starts.astype(np.int32)), pa.py_buffer((codes + 48).astype(np.uint8)))
    return pa.ListArray.from_arrays(pa.array(starts, pa.int32()), pa.array(codes, pa.int32()))


def _cut(codes: np.ndarray, size: np.ndarray, length: int, keep_tail: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    whole = size // length
    rest = size - whole * length
    reads = whole + ((rest > 0) & keep_tail)
    row = np.repeat(np.arange(len(size)), reads)
    nth = np.arange(len(row)) - np.repeat(np.cumsum(reads) - reads, reads)
    lengths = np.where(nth < whole[row], length, rest[row])
    if not keep_tail:
        inside = np.arange(len(codes)) - np.repeat(np.cumsum(size) - size, size)
        codes = codes[inside < np.repeat(whole * length, size)]
    return codes, lengths, row, nth


def _group(codes: np.ndarray, size: np.ndarray, g: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    whole = size // g
    inside = np.arange(len(codes)) - np.repeat(np.cumsum(size) - size, size)
    codes = codes[inside < np.repeat(whole * g, size)].reshape(-1, g)
    return codes @ (m ** np.arange(g - 1, -1, -1)), whole


def pieces(batches: Iterator[pa.RecordBatch], most: int = 4 * SLICE_SYMBOLS) -> Iterator[pa.RecordBatch]:
    """Batches cut so that each holds a few MB of payload (column 0), or one row."""
    for batch in batches:
        a, n = 0, batch.num_rows
        if batch.nbytes <= most or n <= 1:
            if n:
                yield batch
            continue
        step = max(1, int(n * most / batch.nbytes))
        while a < n:
            yield batch.slice(a, step)
            a += step


def text_stream(docs: DataFrame, column: str = "text", kind: str = "text", ids: tuple[str, ...] = ("doc_id",)) -> Stream:
    """Characters of a text column: 42 codes (kind ``text``) or 4 classes (kind ``class``)."""
    return Stream(docs, column, 42 if kind == "text" else 4, kind, ids)


def array_stream(df: DataFrame, column: str, m: int, ids: tuple[str, ...] = ()) -> Stream:
    return Stream(df, column, m, "array", ids)


def ordered_arrays(df: DataFrame, key: str, order: list[str], value, m: int) -> Stream:
    """One sequence per key from rows: values in the given order. Aggregates once; sequences must fit in a row."""
    packed = F.array_sort(F.collect_list(F.struct(*order, value.alias("_v"))))
    rows = df.groupBy(key).agg(F.transform(packed, lambda s: s["_v"]).alias("syms"))
    return array_stream(rows, "syms", m, (key,))


Kernel = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]
