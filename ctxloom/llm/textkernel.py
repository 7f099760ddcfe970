"""Vectorised word and n-gram hashing over Arrow string batches.

A word is a maximal run of ASCII letters and digits or of bytes >= 0x80 in the lower-cased UTF-8 text; everything else
separates. Words become 64-bit hashes, so two different words are told apart up to a collision chance near n^2 / 2^65.
Null texts count as empty. Long texts are hashed in pieces of a few MB that end between words: memory stays bounded.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FILTER_BITS = 1 << 24
PIECE = 1 << 21
GOLD = np.uint64(0x9E3779B97F4A7C15)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_WORD = np.zeros(256, bool)
for _a, _b in ((48, 58), (65, 91), (97, 123), (128, 256)):
    _WORD[_a:_b] = True


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit counter generator: a bijection whose output bits look independent."""
    x = x + GOLD
    x ^= x >> np.uint64(30)
    x *= _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


def stride(n: int) -> np.uint64:
    """The n-th step of the counter."""
    return np.uint64(n * int(GOLD) & 0xFFFFFFFFFFFFFFFF)


_BYTE = mix(np.arange(256, dtype=np.uint64) * np.uint64(7919))
_PLACE = mix(np.arange(1 << 16, dtype=np.uint64) + np.uint64(1 << 32)) | np.uint64(1)


class Words(NamedTuple):
    hashes: np.ndarray  # uint64, one per word, document after document
    starts: np.ndarray  # int64, starts[i]:starts[i + 1] are the words of document i


def flat_bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows end to end, and each row's offsets in them."""
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if not len(texts):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
    return data, offsets - offsets[0]


def slices(batches: Iterator[pa.RecordBatch], most: int = 1 << 20, column: int = 1) -> Iterator[pa.RecordBatch]:
    """Batches cut so that each holds about ``most`` bytes of text (in the given column), or one row."""
    for batch in batches:
        sizes = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False) + 64)
        a = 0
        while a < len(sizes):
            b = max(a + 1, int(np.searchsorted(sizes, (sizes[a - 1] if a else 0) + most)))
            yield batch.slice(a, b - a)
            a = b


def release() -> None:
    """Gives freed memory back to the system: Python workers are kept for later stages, and what they hold on to adds up."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def tidy(kernel: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The kernel, with memory given back after every batch and at its end."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch
            del batch
            release()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from kernel(each(batches))
        release()

    return run


def lower(texts: pa.Array) -> pa.Array:
    return pc.utf8_lower(texts.cast(pa.large_string()))


def words(texts: pa.Array) -> Words:
    data, offsets = flat_bytes(lower(texts))
    hashes, first = [], []
    a, n = 0, len(data)
    while a < n:
        b = min(a + PIECE, n)
        if b < n:  # end the piece between words, or at a row's end
            back = np.flatnonzero(~_WORD[data[a:b]])
            row = int(offsets[np.searchsorted(offsets, b, "right") - 1])
            cut = max(a + int(back[-1]) + 1 if len(back) else a, row)
            if cut <= a:
                ahead = np.flatnonzero(~_WORD[data[b:]])
                cut = min(b + int(ahead[0]) if len(ahead) else n, int(offsets[np.searchsorted(offsets, b, "right")]))
            b = cut
        part = data[a:b]
        inside = _WORD[part]
        opens = inside.copy()
        opens[1:] &= ~inside[:-1]
        edges = offsets[np.searchsorted(offsets, a) : np.searchsorted(offsets, b)] - a
        opens[edges] = inside[edges]
        at = np.flatnonzero(opens)
        if len(at):
            where = np.flatnonzero(inside)
            begin = np.searchsorted(where, at)
            length = np.diff(np.append(begin, len(where)))
            place = where - np.repeat(at, length)
            values = _BYTE[part[where]] * _PLACE[place & 0xFFFF]
            hashes.append(mix(np.add.reduceat(values, begin)))
            first.append(at + a)
        a = b
    if not hashes:
        return Words(np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64))
    return Words(np.concatenate(hashes), np.searchsorted(np.concatenate(first), offsets).astype(np.int64))


def owners(starts: np.ndarray) -> np.ndarray:
    """Row number of each element, from the rows' starts."""
    return np.repeat(np.arange(len(starts) - 1), np.diff(starts))


def chunks(offsets: np.ndarray, overlap: int, most: int = 1 << 20):
    """(a, b, row of each element of a:b) over flat rows: pieces of at most ``most`` elements that overlap, whatever the rows' lengths."""
    n = int(offsets[-1])
    for a in range(0, n, most):
        b = min(a + most + overlap, n)
        first = int(np.searchsorted(offsets, a, "right")) - 1
        last = int(np.searchsorted(offsets, b, "left"))
        inside = np.clip(offsets[first : last + 1], a, b)
        yield a, b, np.repeat(np.arange(first, last), np.diff(inside))


def windows(w: Words, k: int) -> Words:
    """Hashes of all k neighbouring words that lie in one document."""
    n = len(w.hashes) - k + 1
    if n <= 0:
        return Words(np.zeros(0, np.uint64), np.zeros(len(w.starts), np.int64))
    h = np.zeros(n, np.uint64)
    for j in range(k):
        h = mix(h * np.uint64(3) + w.hashes[j : j + n])
    size = np.maximum(np.diff(w.starts) - (k - 1), 0)
    keep = np.zeros(len(w.hashes) + 1, np.int64)
    full = size > 0
    np.add.at(keep, w.starts[:-1][full], 1)
    np.add.at(keep, (w.starts[:-1] + size)[full], -1)
    return Words(h[np.cumsum(keep)[:n] > 0], np.concatenate([[0], np.cumsum(size)]))


def counted(doc: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (document, key) with their counts, ordered by document and key."""
    if not len(key):
        return doc[:0], key[:0], np.zeros(0, np.int64)
    order = np.lexsort((key, doc))
    doc, key = doc[order], key[order]
    new = np.ones(len(key), bool)
    new[1:] = (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])
    at = np.flatnonzero(new)
    return doc[at], key[at], np.diff(np.append(at, len(key)))


def marked(rows: DataFrame, keys: list, wanted: DataFrame, wanted_keys: list) -> DataFrame:
    """Adds __mark: false only for rows whose keys are not in ``wanted``. The wanted keys' hashes are a bitmap of at most
    FILTER_BITS / 64 rows, whatever the data."""
    place = lambda columns: F.pmod(F.xxhash64(*columns), F.lit(FILTER_BITS))
    words_ = wanted.select(place(wanted_keys).alias("p")).groupBy(F.expr("p div 64").alias("__word")).agg(F.expr("bit_or(shiftleft(1L, cast(p % 64 as int)))").alias("__bits"))
    met = rows.withColumn("__place", place(keys)).withColumn("__word", F.expr("__place div 64")).join(F.broadcast(words_), "__word", "left")
    return met.withColumn("__mark", F.expr("coalesce((shiftright(__bits, cast(__place % 64 as int)) & 1) = 1, false)")).drop("__place", "__word", "__bits")


def may_match(rows: DataFrame, keys: list[str], wanted: DataFrame) -> DataFrame:
    """Rows whose keys may be in ``wanted``, by the bitmap, so that few others are shuffled for the exact join that follows; a
    semi-join here would be moved below the bitmap by the optimiser."""
    return marked(rows, keys, wanted, keys).where("__mark").select(*rows.columns)


def without(docs: DataFrame, keys: list, gone: DataFrame) -> DataFrame:
    """The documents whose keys (expressions) are not in ``gone`` (a column for each key, in order); null is a value.

    Most documents stay, so texts are not shuffled to find out: the bitmap lets all but a few pass where they are, and only
    those it marks are compared with ``gone`` by an exact join."""
    names = gone.columns
    met = marked(docs.select("*", *[k.alias(f"__key{i}") for i, k in enumerate(keys)]), [F.col(f"__key{i}") for i in range(len(keys))], gone, names)
    passed = met.where("not __mark").select(*docs.columns)
    suspects, named = met.where("__mark"), gone.select(*[F.col(n).alias(f"__gone{i}") for i, n in enumerate(names)])
    same = F.lit(True)
    for i in range(len(keys)):
        same = same & F.col(f"__key{i}").eqNullSafe(F.col(f"__gone{i}"))
    return passed.unionByName(suspects.join(named, same, "left_anti").select(*docs.columns))
