"""What the methods are compared with: plain, complete and truncated contexts, run lengths, block sorting, other binnings."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.operators import counts as C
from ctxloom.operators import merge as M
from ctxloom.operators import rates as R
from ctxloom.operators.contexts import From, LowBits, Previous
from ctxloom.operators.stream import Stream, pieces
from ctxloom.session import schema_with


def order_rate(stream: Stream, order: int, start: int | None = None) -> DataFrame:
    """n, contexts, bpv with no context (order 0) or the complete one, over windows from place ``start`` (default: the order)."""
    return R.rate(C.count_windows(stream, From(Previous(order), order if start is None else start)))


def order_rates(stream: Stream, orders: list[int]) -> DataFrame:
    """ord, n, contexts, bpv of stationary models of several orders, each over its own windows, from one scan.

    The scan counts the highest order with shorter heads as contexts of their own; lower orders are sums of those counts.
    """
    top, m = max(orders), stream.m
    counted = C.count_windows(stream, Previous(top, "backoff"))
    offset, bounds = m**top, []
    for k in range(top - 1, -1, -1):
        bounds.append((k, offset, offset + m**k))
        offset += m**k
    length = F.lit(top)
    code = F.col("ctx")
    for k, a, b in bounds:
        inside = (F.col("ctx") >= a) & (F.col("ctx") < b)
        length = F.when(inside, k).otherwise(length)
        code = F.when(inside, F.col("ctx") - a).otherwise(code)
    rows = counted.select(length.alias("known"), code.alias("code"), "sym", "n")
    per = rows.withColumn("ord", F.explode(F.lit(list(orders)))).where("ord <= known")
    power = F.lit([m**k for k in range(top + 1)])
    cells = per.groupBy("ord", (F.col("code") % F.get(power, F.col("ord"))).alias("ctx"), "sym").agg(F.sum("n").alias("n"))
    return R.rate(cells, "ord")


def low_bits_curve(stream: Stream, order: int, drops: list[int]) -> DataFrame:
    """drop, n, contexts, bpv when the previous values lose their low bits; one scan."""
    rated = R.rate(C.count_many(stream, [LowBits(order, d) for d in drops]), "spec")
    return rated.select(F.get(F.lit(list(drops)), F.col("spec")).alias("drop"), "n", "contexts", "bpv")


def range_bins(contexts: int, bins: int) -> np.ndarray:
    """Equal ranges of codes."""
    return np.arange(contexts) * bins // max(contexts, 1)


def random_bins(contexts: int, bins: int, seed: int = 0) -> np.ndarray:
    """Contexts dealt into bins in the order of a digest."""
    order = sorted(range(contexts), key=lambda i: (hashlib.md5(f"{i}|{seed}".encode()).hexdigest(), i))
    out = np.empty(contexts, np.int64)
    out[order] = np.arange(contexts) % bins
    return out


def best_partition(table: np.ndarray, bins: int) -> float:
    """Least rate over all partitions of the contexts (rows) into at most ``bins`` sets; for up to 8 contexts."""
    n = len(table)
    if n > 8:
        raise ValueError("too many contexts for an exhaustive search")
    best = np.inf

    def place(i: int, label: list[int], used: int) -> None:
        nonlocal best
        if i == n:
            rows = np.zeros((used, table.shape[1]))
            np.add.at(rows, label, table)
            best = min(best, float(M.excess(rows).sum() / table.sum()))
            return
        for x in range(min(used + 1, bins)):
            place(i + 1, [*label, x], max(used, x + 1))

    place(0, [], 0)
    return best


def runs(rows: DataFrame, key: str, order: list[str], sym: Column) -> DataFrame:
    """key, run, sym, length: maximal runs of equal symbols in order (rows form)."""
    w = Window.partitionBy(key).orderBy(*order)
    marked = rows.select(key, *order, sym.alias("sym")).withColumn("new", (~F.coalesce(F.lag("sym").over(w) == F.col("sym"), F.lit(False))).cast("int"))
    numbered = marked.withColumn("run", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(key, "run").agg(F.first("sym").alias("sym"), F.count("*").alias("length"))


def run_lengths(stream: Stream) -> DataFrame:
    """sym, length, n: how many runs of each kind the stream has, counted inside partitions first."""
    m, flat = stream.m, stream.flat

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            if not len(f.codes):
                continue
            new = np.ones(len(f.codes), bool)
            new[1:] = f.codes[1:] != f.codes[:-1]
            new[f.starts[:-1][f.size > 0]] = True
            at = np.flatnonzero(new)
            pair, n = np.unique(np.diff(np.append(at, len(f.codes))) * m + f.codes[at], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(pair % m, pa.int32()), pa.array(pair // m), pa.array(n)], names=["sym", "length", "n"])

    return stream.select().mapInArrow(kernel, "sym int, length long, n long").groupBy("sym", "length").agg(F.sum("n").alias("n"))


def run_length_rate(lengths: DataFrame) -> DataFrame:
    """runs, n, bpv: entropy of the (symbol, length) pairs over the symbols they stand for."""
    total = F.sum("n")
    bits = R.xlog2x(total) - F.sum(R.xlog2x(F.col("n")))
    symbols = F.sum(F.col("n") * F.col("length"))
    return lengths.agg(total.alias("runs"), symbols.alias("n"), F.round(bits / symbols + 0.0, 6).alias("bpv"))


def block_sort(codes: np.ndarray, m: int) -> tuple[np.ndarray, int]:
    """Block-sorting transform: last column of the sorted rotations, and the row of the original. By prefix doubling."""
    n = len(codes)
    if not n:
        return codes, 0
    rank, step = codes.copy(), 1
    while True:
        key = rank * (rank.max() + 1) + np.roll(rank, -step)
        _, rank = np.unique(key, return_inverse=True)
        step *= 2
        if step >= n or rank.max() == n - 1:
            break
    order = np.argsort(rank, kind="stable")
    return codes[order - 1], int(np.flatnonzero(order == 0)[0])


def block_unsort(last: np.ndarray, row: int) -> np.ndarray:
    order = np.argsort(last, kind="stable")
    out, at = np.empty_like(last), row
    for i in range(len(last)):
        at = order[at]
        out[i] = last[at]
    return out


def block_sorted(stream: Stream) -> DataFrame:
    """ids, read_no, syms (transformed), row: each sequence by itself."""
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    schema = schema_with(T.StructType([stream.df.schema[c] for c in ids]), "read_no int, syms array<int>, row int")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            got = [block_sort(f.codes[a:b], m) for a, b in zip(f.starts[:-1], f.starts[1:])]
            cols = [batch.column(c).take(pa.array(f.row)) for c in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), pa.array([g[0].tolist() for g in got], pa.list_(pa.int32())), pa.array([g[1] for g in got], pa.int32())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)
