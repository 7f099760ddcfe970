"""Labelled rows for the classifiers: folds, and bounded samples of hashed features."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ctxloom.llm.textkernel import slices, tidy, without
from ctxloom.session import materialise

#: Most features of a training sample that reach the driver; rows beyond it, in order of a hash of doc_id, are left out of the sample.
SAMPLE_FEATURES = 12_000_000


def fold(doc_id: Column, folds: int) -> Column:
    """Remainder of the CRC-32 of doc_id as text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(folds)).cast("int")


def thinned(rows: DataFrame, most: dict, by: Column) -> DataFrame:
    """About ``most[v]`` rows of each value v of ``by``, chosen by a hash of doc_id; all rows where there are fewer."""
    counts = {r.v: r.n for r in rows.groupBy(by.alias("v")).agg(F.count("*").alias("n")).collect()}
    share = F.when(F.lit(False), F.lit(0.0))  # one flat CASE, however many values
    for value, n in counts.items():
        share = share.when(by.eqNullSafe(F.lit(value)), F.lit(min(1.0, most.get(value, 0) / n)))
    share = share.otherwise(F.lit(0.0))
    return rows.where(F.pmod(F.xxhash64(F.col("doc_id"), F.lit(11)), F.lit(1 << 30)) < share * float(1 << 30))


def one_label(labels: DataFrame, column: str, pick: Callable[[str], Column]) -> DataFrame:
    """doc_id, mark: a label a document. Rows without a doc_id or a label do not count; ``pick`` settles several labels of one id."""
    return labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(pick(column).cast("int").alias("mark"))


def sampled_texts(docs: DataFrame, chosen: DataFrame) -> DataFrame:
    """doc_id, text, mark of the chosen ids (doc_id, mark). An id with several texts counts once, with its least one.

    The chosen ids are written first: the planner then knows how small they are and sends them to the texts, or, if they
    should be many, sorts and merges."""
    chosen = materialise(chosen, "chosen")
    met = docs.select("doc_id", "text").join(chosen, "doc_id")
    return met.groupBy("doc_id", "mark").agg(F.min(F.coalesce("text", F.lit(""))).alias("text")).select("doc_id", "text", "mark")


Featuriser = Callable[[pa.Array], tuple[np.ndarray, np.ndarray, int]]


def collect_features(rows: DataFrame, features: Featuriser, mark: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """marks, feature indices and row starts of a bounded sample (doc_id, text, mark): indices are made on the executors."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            row, index, n = features(batch.column(1))
            ends = np.searchsorted(row, np.arange(n + 1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([index[a:b].astype(np.uint32).tobytes() for a, b in zip(ends[:-1], ends[1:])], pa.binary())], names=["id", "mark", "f"])

    made = rows.select(F.col("doc_id").cast("long"), "text", F.col(mark).cast("int").alias("mark")).mapInArrow(tidy(kernel), "id long, mark int, f binary")
    made = materialise(made, "features")
    sizes = made.select("id", (F.length("f") / 4).cast("long").alias("n"), F.xxhash64("id", F.lit(13)).alias("h")).toArrow()
    order = np.lexsort((sizes.column("id").to_numpy(), sizes.column("h").to_numpy()))
    within = np.cumsum(sizes.column("n").to_numpy()[order]) <= SAMPLE_FEATURES
    if not within.all():
        last = int(sizes.column("h").to_numpy()[order][within.sum() - 1]) if within.any() else -(1 << 63)
        made = made.where(F.xxhash64("id", F.lit(13)) <= last)
    got = made.orderBy("id").toArrow()
    lists = [np.frombuffer(x.as_py(), np.uint32).astype(np.int64) for x in got.column("f")]
    marks = got.column("mark").to_numpy()
    return marks, np.concatenate(lists) if lists else np.zeros(0, np.int64), np.concatenate([[0], np.cumsum([len(x) for x in lists], dtype=np.int64)]).astype(np.int64)


def row_sums(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values)])
    return total[starts[1:]] - total[starts[:-1]]


def keep_rows(docs: DataFrame, accept: Callable[[pa.Array], np.ndarray]) -> DataFrame:
    """The documents whose text is accepted, each decided by its own text, with all their columns.

    Texts go to the kernel and do not come back: it names the rows that go, by doc_id and a hash of the text, and all others
    pass where they are (:func:`ctxloom.llm.textkernel.without`)."""
    digest = F.xxhash64("text").alias("h")
    kind = docs.schema["doc_id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            gone = pa.array(~accept(batch.column(1)), pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(gone), batch.column(2).filter(gone)], names=["doc_id", "h"])

    gone = docs.select("doc_id", "text", digest).mapInArrow(tidy(kernel), f"doc_id {kind}, h long").distinct()
    return without(docs, [F.col("doc_id"), F.xxhash64("text")], materialise(gone, "gone"))


SCORED = "doc_id long, held_out boolean, score double, predicted int"


def score_with(docs: DataFrame, features: Featuriser, score: Callable[[np.ndarray, np.ndarray, int], np.ndarray], threshold: float, folds: int, out: int) -> DataFrame:
    """Scores every whole text in one narrow pass; ``score`` turns (row, index, rows) into scores from 0 to 1."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            s = score(*features(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text", (fold(F.col("doc_id"), folds) == out).alias("held_out")).mapInArrow(tidy(kernel), SCORED)
