"""Joint counts of (context, next symbol) and conditional models built on them.

Counting reads the data once: a kernel counts inside each partition and only distinct (context, symbol) pairs go to the
shuffle. Everything after that works on count tables, whose size depends on alphabet and contexts and not on the data.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.operators.contexts import Context
from ctxloom.operators.stream import Stream, pieces
from ctxloom.session import schema_with

DENSE_CELLS = 1 << 22
#: Largest count table that is brought to the driver.
MATRIX_CELLS = 1 << 24
#: Largest model that is sent to all executors.
BROADCAST_CELLS = 1 << 26


def _counted_pairs(group: np.ndarray, key: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (group, key below ``span``) with their counts: as one packed number where that fits."""
    if (int(group.max(initial=0)) + 1) * span < 1 << 62:
        packed, n = np.unique(group * span + key, return_counts=True)
        return packed // span, packed % span, n
    order = np.lexsort((key, group))
    group, key = group[order], key[order]
    new = np.ones(len(key), bool)
    new[1:] = (group[1:] != group[:-1]) | (key[1:] != key[:-1])
    at = np.flatnonzero(new)
    return group[at], key[at], np.diff(np.append(at, len(key)))


def count_windows(stream: Stream, spec: Context, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., ctx, sym, n) over all windows of the stream; ``by`` are columns of its rows."""
    m, flat = stream.m, stream.flat
    by = tuple(c for c in by if c != stream.payload)
    groups = [stream.df.schema[c] for c in by]
    if spec.size(m) * m >= 1 << 62:
        raise ValueError("context codes would not fit 64 bits; bin the contexts or lower the order")
    dense = spec.size(m) * m <= DENSE_CELLS and not by
    schema = schema_with(T.StructType(groups), "ctx long, sym int, n long")

    def batch_of(key: np.ndarray, n: np.ndarray, values: list[pa.Array]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*values, pa.array(key // m), pa.array((key % m).astype(np.int32)), pa.array(n.astype(np.int64))], names=[*by, "ctx", "sym", "n"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(spec.size(m) * m if dense else 0, np.int64)
        for batch in pieces(batches):
            f = flat(batch.column(0))
            ctx, valid = spec.codes(f, m)
            key = (ctx * m + f.codes)[valid]
            if dense:
                total += np.bincount(key, minlength=len(total))
            elif not by:
                yield batch_of(*np.unique(key, return_counts=True), [])
            else:
                frame = batch.select(list(by)).to_pandas()
                number = frame.groupby(list(by), dropna=False, sort=False).ngroup().to_numpy()
                first = pd.Series(np.arange(len(number))).groupby(number).first()
                group, key, n = _counted_pairs(number[f.row][f.owner()][valid], key, spec.size(m) * m)
                yield batch_of(key, n, [batch.column(c).take(pa.array(first.loc[group].to_numpy())) for c in by])
        if dense and total.any():
            key = np.flatnonzero(total)
            yield batch_of(key, total[key], [])

    partial = stream.select(*by).mapInArrow(kernel, schema)
    return partial.groupBy(*by, "ctx", "sym").agg(F.sum("n").alias("n"))


def count_many(stream: Stream, specs: list[Context]) -> DataFrame:
    """(spec, ctx, sym, n) of several contexts from one scan; ``spec`` is the place in the list."""
    m, flat = stream.m, stream.flat
    if max(x.size(m) for x in specs) * m >= 1 << 62:
        raise ValueError("context codes would not fit 64 bits; bin the contexts or lower the order")

    def batch_of(spec: int, key: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(key), spec, np.int32)), pa.array(key // m), pa.array((key % m).astype(np.int32)), pa.array(n.astype(np.int64))], names=["spec", "ctx", "sym", "n"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals = {i: np.zeros(x.size(m) * m, np.int64) for i, x in enumerate(specs) if x.size(m) * m <= DENSE_CELLS}
        for batch in pieces(batches):
            f = flat(batch.column(0))
            for i, x in enumerate(specs):
                ctx, valid = x.codes(f, m)
                key = (ctx * m + f.codes)[valid]
                if i in totals:
                    totals[i] += np.bincount(key, minlength=len(totals[i]))
                else:
                    yield batch_of(i, *np.unique(key, return_counts=True))
        for i, total in totals.items():
            key = np.flatnonzero(total)
            yield batch_of(i, key, total[key])

    return stream.select().mapInArrow(kernel, "spec int, ctx long, sym int, n long").groupBy("spec", "ctx", "sym").agg(F.sum("n").alias("n"))


def smooth(counts: DataFrame, eps: float, contexts: int, m: int, observed: bool = False) -> DataFrame:
    """Adds ``eps`` to every cell of the joint table: of all contexts, or of the observed ones. n becomes a double."""
    spark = counts.sparkSession
    ctx = counts.select("ctx").distinct() if observed else spark.range(contexts).withColumnRenamed("id", "ctx")
    cells = ctx.withColumn("sym", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    return cells.join(counts, ["ctx", "sym"], "left").select("ctx", "sym", (F.coalesce("n", F.lit(0)) + F.lit(eps)).alias("n"))


def conditional(counts: DataFrame) -> DataFrame:
    """ctx, sym, n, n_ctx, p, bits = lg(1/p)."""
    total = F.sum("n").over(Window.partitionBy("ctx"))
    rows = counts.withColumn("n_ctx", total).withColumn("p", F.col("n") / F.col("n_ctx"))
    return rows.withColumn("bits", F.log2(F.col("n_ctx") / F.col("n")))


def add_counts(*tables: DataFrame) -> DataFrame:
    first, *rest = tables
    for t in rest:
        first = first.unionByName(t)
    return first.groupBy("ctx", "sym").agg(F.sum("n").alias("n"))


def subtract_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """a minus b; cells that come to nothing are left out."""
    return add_counts(a, b.withColumn("n", -F.col("n"))).where("n <> 0")


def scale_counts(table: DataFrame, weight: float) -> DataFrame:
    return table.withColumn("n", F.col("n") * F.lit(weight))


def marginal(counts: DataFrame, keep: int) -> DataFrame:
    """Counts of the contexts' low digits (the nearest values): lower orders from the same windows, without a scan."""
    return counts.groupBy((F.col("ctx") % F.lit(keep)).alias("ctx"), "sym").agg(F.sum("n").alias("n"))


def matrix(counts: DataFrame, m: int, most: int = MATRIX_CELLS) -> tuple[np.ndarray, np.ndarray]:
    """Context codes (sorted) and their rows of counts. At most ``most`` cells come to the driver; larger tables are refused
    before they are collected in full."""
    got = counts.select("ctx", "sym", "n").limit(most + 1).toArrow()
    if got.num_rows > most:
        raise ValueError(f"more than {most} cells: bin the contexts in stages or per group first")
    ctx, sym, n = (got.column(c).to_numpy() for c in ("ctx", "sym", "n"))
    codes, at = np.unique(ctx, return_inverse=True)
    out = np.zeros((len(codes), m), n.dtype if n.dtype.kind == "f" else np.int64)
    np.add.at(out, (at, sym), n)
    return codes, out


def frame_of(spark: SparkSession, codes: np.ndarray, table: np.ndarray) -> DataFrame:
    """A count table from a matrix."""
    at, sym = np.nonzero(table)
    kind = pa.float64() if table.dtype.kind == "f" else pa.int64()
    return spark.createDataFrame(pa.table({"ctx": pa.array(codes[at], pa.int64()), "sym": pa.array(sym.astype(np.int32)), "n": pa.array(table[at, sym], kind)}))


@dataclass(frozen=True)
class Model:
    """Bits of every (context, symbol) in a dense table; contexts without counts have what smoothing gives them."""

    spec: object
    m: int
    bits: np.ndarray

    @staticmethod
    def from_matrix(spec: Context, m: int, codes: np.ndarray, table: np.ndarray, alpha: float = 1.0) -> Model:
        size = spec.size(m)
        if size * m > BROADCAST_CELLS:
            raise ValueError(f"a dense model of {size} x {m} cells is too large to send out; bin the contexts first")
        full = np.full((size, m), float(alpha))
        full[codes] += table
        with np.errstate(divide="ignore", invalid="ignore"):
            bits = np.log2(full.sum(axis=1, keepdims=True)) - np.log2(full)
        return Model(spec, m, np.nan_to_num(bits, nan=np.log2(m), posinf=np.inf))

    @staticmethod
    def fit(stream: Stream, spec: Context, alpha: float = 1.0) -> Model:
        return Model.from_matrix(spec, stream.m, *matrix(count_windows(stream, spec), stream.m), alpha)

    def size(self) -> int:
        """Cells of the table."""
        return self.bits.size

    def cost(self, stream: Stream) -> DataFrame:
        """ids, read_no, bits, n: what this model needs for each sequence."""
        from ctxloom.operators.cluster import read_costs

        return read_costs(stream, self.spec, self.bits[None]).select(*stream.ids, "read_no", F.col("bits")[0].alias("bits"), "n")

    def table(self, spark: SparkSession) -> DataFrame:
        at, sym = np.nonzero(np.isfinite(self.bits))
        return spark.createDataFrame(pa.table({"ctx": pa.array(at, pa.int64()), "sym": pa.array(sym.astype(np.int32)), "p": 2.0 ** -self.bits[at, sym], "bits": self.bits[at, sym]}))

    def save(self, spark: SparkSession, path: str) -> None:
        self.table(spark).withColumn("m", F.lit(self.m)).withColumn("contexts", F.lit(len(self.bits))).write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str, spec: Context) -> Model:
        got = spark.read.parquet(path).toArrow().to_pandas()
        bits = np.full((int(got.contexts.iloc[0]), int(got.m.iloc[0])), np.inf)
        bits[got.ctx, got.sym] = got.bits
        return Model(spec, bits.shape[1], bits)
