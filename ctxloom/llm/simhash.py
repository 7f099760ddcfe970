"""Document fingerprints by signed votes of weighted term hashes, and search within a Hamming radius.

Terms are pairs of neighbouring words; texts under SHORT words add their character 3-grams, so short texts have terms too.
A term's weight is its number of occurrences; that of 3-grams falls in proportion to 0 as the text nears SHORT words. Each bit of a 128-bit fingerprint is the sign of the summed votes.

Search: with radius r the fingerprint is cut into r + EXTRA blocks; two fingerprints within r bits agree in at least EXTRA
blocks, so one table per choice of EXTRA blocks, keyed by those blocks (the permuted table's prefix), meets every pair.

Null and empty texts have no terms: fingerprint 0. Equal texts have equal fingerprints. An empty table gives an empty
result; other input columns are not read. Likeness of two fingerprints is the share of equal bits. Rows of one doc_id follow
each other in the order of their texts; rows without a doc_id come first.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.llm import textkernel as K
from ctxloom.llm.textkernel import may_match
from ctxloom.session import load, materialise

BITS = 128
SHORT = 32
EXTRA = 2
_RUN = 255  # one byte counts the votes of so many terms at most
_ONES = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).copy().view(np.uint64).ravel()


def _votes(first: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Sum of +1 / -1 votes per row and bit. Eight bits are counted in the eight bytes of one integer at a time."""
    rows = len(starts) - 1
    total = np.zeros((rows, BITS), np.int64)
    size = np.diff(starts)
    runs = -(-size // _RUN)
    if not len(first):
        return total
    run_row = np.repeat(np.arange(rows), runs)
    nth = np.arange(len(run_row)) - np.repeat(np.cumsum(runs) - runs, runs)
    cut = starts[run_row] + nth * _RUN
    second = K.mix(first ^ np.uint64(0xA5A5A5A5A5A5A5A5))
    ones = np.empty((len(cut), BITS // 8), np.uint64)
    for half, h in enumerate((first, second)):
        octets = np.ascontiguousarray(h).view(np.uint8).reshape(-1, 8)
        for i in range(8):
            ones[:, half * 8 + i] = np.add.reduceat(_ONES[octets[:, i]], cut)
    counts = ones.view(np.uint8).reshape(len(cut), BITS).astype(np.int64)
    np.add.at(total, run_row, counts)
    return 2 * total - size[:, None]


def _three_grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all character 3-grams, text after text, and the texts' starts. A text of one or two characters is one 3-gram
    with zeros at its end."""
    size = np.array([len(t) for t in texts], np.int64)
    points = np.frombuffer("".join(t + "\0\0" for t in texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    begins = np.concatenate([[0], np.cumsum(size + 2)])
    count = np.where(size > 0, np.maximum(size - 2, 1), 0)
    starts = np.concatenate([[0], np.cumsum(count)])
    at = np.arange(starts[-1]) + np.repeat(begins[:-1] - starts[:-1], count)
    return K.mix(points[at] | points[at + 1] << np.uint64(21) | points[at + 2] << np.uint64(42)), starts


def fingerprints(texts: list[str]) -> np.ndarray:
    """One row of 16 bytes per text."""
    w = K.words(pa.array(texts, pa.string()))
    pairs = K.windows(w, 2)
    votes = _votes(pairs.hashes, pairs.starts)
    size = np.diff(w.starts)
    short = np.flatnonzero(size < SHORT)
    if len(short):
        grams, starts = _three_grams([texts[i].lower() for i in short])
        votes[short] = SHORT * votes[short] + (SHORT - size[short])[:, None] * _votes(grams, starts)
    return np.packbits(votes > 0, axis=1)


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return 1 - np.bitwise_count(a ^ b).sum(axis=1) / BITS


def _compare(ids: list, texts: list[str], following: list[str]) -> dict[str, list]:
    """Rows of the result for texts with their followers (one more text than ids if the follower is the next text)."""
    edited = []
    for t, nxt in zip(texts, following):
        q = len(t) // 4
        edited.append(t[: len(t) - q] + nxt[:q])
    prints = fingerprints([*texts, *edited])
    own, other = prints[: len(texts)], prints[len(texts) :]
    after = np.concatenate([own[1:], fingerprints([following[-1]])]) if texts else own
    return {
        "doc_id": ids,
        "n_chars": [len(t) for t in texts],
        "edited_sha256": [hashlib.sha256(t.encode()).hexdigest() for t in edited],
        "fingerprint": [x.tobytes().hex() for x in own],
        "edited_fingerprint": [x.tobytes().hex() for x in other],
        "near_edited": likeness(own, other),
        "near_next": likeness(own, after),
    }


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
_SCAN = RESULT + ", part int, edge int, text string"
_ARROW = pa.schema(
    [("doc_id", pa.int64()), ("n_chars", pa.int64())]
    + [(c, pa.string()) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")]
    + [("near_edited", pa.float64()), ("near_next", pa.float64())]
)
_EDGED = pa.schema([*_ARROW, pa.field("part", pa.int32()), pa.field("edge", pa.int32()), pa.field("text", pa.string())])


def _pieces(batches: Iterator[pa.RecordBatch], most: int = 4 << 20) -> Iterator[tuple[list, list[str]]]:
    ids, texts, size = [], [], 0
    for batch in batches:
        for i, t in zip(batch.column(0).to_pylist(), batch.column(1)):
            t = t.as_py() or ""
            ids.append(i)
            texts.append(t)
            size += len(t) + 64
            if size >= most:
                yield ids, texts
                ids, texts, size = [], [], 0
    if ids:
        yield ids, texts


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Ordered rows of one partition: each row meets its follower; the partition's first and last row are also passed on."""
    part = TaskContext.get().partitionId()
    held_id, held = None, None

    def edge(kind: int, i, t: str) -> pa.RecordBatch:
        return pa.RecordBatch.from_pylist([{"doc_id": i, "part": part, "edge": kind, "text": t}], schema=_EDGED)

    for ids, texts in _pieces(batches):
        if held is None:
            yield edge(0, ids[0], texts[0])
        else:
            ids, texts = [held_id, *ids], [held, *texts]
        held_id, held = ids[-1], texts[-1]
        if len(ids) > 1:
            out = _compare(ids[:-1], texts[:-1], texts[1:])
            out |= {"part": [part] * (len(ids) - 1), "edge": [-1] * (len(ids) - 1), "text": [None] * (len(ids) - 1)}
            yield pa.RecordBatch.from_pydict(out, schema=_EDGED)
    if held is not None:
        yield edge(1, held_id, held)


def _close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The partitions' first and last rows in order: each last row meets the next partition's first, the very last the very first."""
    opening, last = None, None
    for batch in batches:
        for row in batch.to_pylist():
            if row["edge"] == 0:
                opening = row if opening is None else opening
                if last is not None:
                    yield pa.RecordBatch.from_pydict(_compare([last["doc_id"]], [last["text"]], [row["text"]]), schema=_ARROW)
            else:
                last = row
    if last is not None:
        yield pa.RecordBatch.from_pydict(_compare([last["doc_id"]], [last["text"]], [opening["text"]]), schema=_ARROW)


def with_edited(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text, of its edited text, and its likeness to both that and the next document.

    One range shuffle brings documents into doc_id order (ties by text); rows stream through each partition, and only the
    first and last row of every partition are joined up afterwards (two rows a partition, streamed in one task).
    """
    ordered = docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    found = materialise(ordered.mapInArrow(_scan, _SCAN), "simhash")
    done = found.where("edge = -1").drop("part", "edge", "text")
    ends = found.where("edge >= 0").select("doc_id", "part", "edge", "text").repartition(1).sortWithinPartitions("part", "edge")
    return done.unionByName(ends.mapInArrow(_close, RESULT))


def fingerprint_table(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (hex) for any documents; narrow, no shuffle."""

    def kernel(batches):
        for ids, texts in _pieces(batches):
            yield pa.RecordBatch.from_pydict({"doc_id": ids, "fingerprint": [x.tobytes().hex() for x in fingerprints(texts)]})

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(kernel, "doc_id long, fingerprint string")


def block_bounds(radius: int, extra: int = EXTRA) -> list[tuple[int, int]]:
    """Hex-digit bounds (start, end) of the radius + extra blocks of a fingerprint."""
    cuts = np.linspace(0, BITS // 4, radius + extra + 1).round().astype(int)
    return list(zip(cuts[:-1].tolist(), cuts[1:].tolist()))


def near_fingerprints(prints: DataFrame, queries: DataFrame, radius: int = 3) -> DataFrame:
    """All (query_id, fingerprint, distance) within ``radius`` bits of the stated queries' fingerprints.

    Both sides are taken by distinct fingerprint, so a group of copies counts once in every table; join the result with
    ``prints`` on fingerprint for the members. Each pair is found in several tables and returned once.
    """
    bounds = block_bounds(radius)

    def keyed(df: DataFrame) -> DataFrame:
        tables = [
            F.struct(F.lit(n).alias("table"), F.concat_ws("-", *[F.substring("fingerprint", a + 1, b - a) for a, b in chosen]).alias("key"))
            for n, chosen in enumerate(combinations(bounds, EXTRA))
        ]
        return df.withColumn("t", F.explode(F.array(*tables))).select("*", "t.table", "t.key").drop("t")

    asked = materialise(keyed(queries.select(F.col("fingerprint").alias("asked")).distinct().withColumn("fingerprint", F.col("asked"))), "asked")
    # only keys that may be asked for are shuffled: a bitmap of the asked keys goes to the tables' side first
    classes = may_match(keyed(prints.select("fingerprint")), ["table", "key"], asked).distinct()
    halves = [(1, 16), (17, 16)]

    def differing(a: str, b: str):
        return sum(
            (F.bit_count(F.conv(F.substring(a, s, n // 2), 16, 10).cast("long").bitwiseXOR(F.conv(F.substring(b, s, n // 2), 16, 10).cast("long")))
             + F.bit_count(F.conv(F.substring(a, s + 8, n // 2), 16, 10).cast("long").bitwiseXOR(F.conv(F.substring(b, s + 8, n // 2), 16, 10).cast("long"))))
            for s, n in halves
        )

    met = (
        asked.drop("fingerprint").join(classes, ["table", "key"]).withColumn("distance", differing("asked", "fingerprint"))
        .where(F.col("distance") <= radius).select("asked", "fingerprint", "distance").distinct()
    )
    return queries.select(F.col("doc_id").alias("query_id"), F.col("fingerprint").alias("asked")).join(met, "asked").drop("asked")


def with_near_rows(rows: DataFrame, radius: int = 3, every: int = 100) -> DataFrame:
    """Adds near_rows: for documents whose id is divisible by ``every``, how many other rows' fingerprints lie within ``radius``
    bits (null for other documents). The block tables find them; copies are counted by fingerprint, not paired."""
    asked = materialise(rows.where(F.col("doc_id") % every == 0).select("doc_id", "fingerprint").distinct(), "queries")
    found = materialise(near_fingerprints(rows, asked, radius), "near")
    prints = found.select("fingerprint").distinct()
    counts = rows.join(prints, "fingerprint").groupBy("fingerprint").agg(F.count("*").alias("rows"))
    near = materialise(found.join(counts, "fingerprint").groupBy("query_id").agg((F.sum("rows") - 1).alias("near_rows")), "near")
    # one row a query comes back; the planner sends it out if it is small
    return rows.join(near, rows["doc_id"] == near["query_id"], "left").drop("query_id")


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_near_rows(materialise(with_edited(load(spark, sf_dir, "documents")), "prints"))


QUERIES = {"op2_simhash": op2_simhash}
ORACLES: dict[str, str] = {}
