"""Cost and accuracy measures, all on count tables or per-read rows."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ctxloom.operators import counts as C
from ctxloom.operators.contexts import Context
from ctxloom.operators.stream import Stream


def xlog2x(n: Column) -> Column:
    return F.when(n > 0, n * F.log2(n)).otherwise(F.lit(0.0))


def rate(counts: DataFrame, *by: str) -> DataFrame:
    """One row (per group): n windows, contexts, bpv = sum over contexts of p_c H(P_c)."""
    per = counts.groupBy(*by, "ctx").agg(F.sum("n").alias("n"), F.sum(xlog2x(F.col("n"))).alias("g"))
    bits = F.sum(xlog2x(F.col("n")) - F.col("g"))
    return per.groupBy(*by).agg(F.sum("n").cast("long").alias("n"), F.count("*").alias("contexts"), F.round(bits / F.sum("n") + 0.0, 6).alias("bpv"))


def rate_value(counts: DataFrame) -> float:
    return rate(counts).first()["bpv"]


def entropy(weights: DataFrame, column: str = "n") -> DataFrame:
    """Shannon entropy of one distribution given as a column of weights."""
    total = F.sum(column)
    return weights.agg(F.round((xlog2x(total) - F.sum(xlog2x(F.col(column)))) / total + 0.0, 6).alias("entropy"))


def bpv(counts: DataFrame, model: DataFrame, missing_bits: float | None = None) -> DataFrame:
    """Cross-entropy of counted data under a conditional model (ctx, sym, bits). The model is joined by key, whatever its size."""
    joined = counts.join(model.select("ctx", "sym", "bits"), ["ctx", "sym"], "left")
    bits = F.col("bits") if missing_bits is None else F.coalesce("bits", F.lit(missing_bits))
    return joined.agg(F.sum("n").cast("long").alias("n"), F.round(F.sum(F.col("n") * bits) / F.sum("n"), 6).alias("bpv"))


def held_out(counts: DataFrame, contexts: int, m: int, alpha: float = 1.0, fold: str = "fold") -> DataFrame:
    """Two-fold held-out bits per value beside the training ones: each fold is scored by the other's counts plus ``alpha``.

    ``counts`` has a column ``fold`` (0 or 1). Unseen contexts cost lg m, unseen symbols what alpha gives them.
    """
    wide = counts.groupBy("ctx", "sym").agg(*[F.coalesce(F.sum(F.when(F.col(fold) == k, F.col("n"))), F.lit(0)).alias(f"n{k}") for k in (0, 1)])
    per = Window.partitionBy("ctx")
    rows = wide.select("*", *[F.sum(f"n{k}").over(per).alias(f"t{k}") for k in (0, 1)])
    cost = sum(F.col(f"n{k}") * F.log2((F.col(f"t{1 - k}") + alpha * m) / (F.col(f"n{1 - k}") + alpha)) for k in (0, 1))
    both = F.col("n0") + F.col("n1")
    train = both * F.log2((F.col("t0") + F.col("t1")) / both)
    n = F.sum(both)
    return rows.agg(n.cast("long").alias("n"), F.round(F.sum(train) / n + 0.0, 6).alias("training"), F.round(F.sum(cost) / n, 6).alias("held_out"))


def overfit(stream: Stream, spec: Context, fold: Column, alpha: float = 1.0) -> DataFrame:
    """n, training, held_out for a context over a stream; ``fold`` (0 / 1) is computed on the stream's rows."""
    split = stream.with_df(stream.df.withColumn("fold", fold.cast("int")))
    return held_out(C.count_windows(split, spec, ("fold",)), spec.size(stream.m), stream.m, alpha)


def model_size(contexts: int, m: int, bytes_per_cell: int = 2) -> dict[str, int]:
    return {"contexts": contexts, "cells": contexts * m, "bytes": contexts * m * bytes_per_cell}


def header_bits(shares: DataFrame, k: int) -> DataFrame:
    """Bits a read for naming its model: lg k flat, or the entropy of the clusters' shares. ``shares`` has cluster, n."""
    return entropy(shares).select(F.round(F.lit(math.log2(k)), 6).alias("flat"), F.col("entropy").alias("entropy"))


def header_bpv(assignment: DataFrame, k: int) -> DataFrame:
    """Header cost per value: ``assignment`` has cluster and n (the read's length)."""
    shares = assignment.groupBy("cluster").agg(F.count("*").alias("reads"), F.sum("n").alias("values"))
    reads, values = F.sum("reads"), F.sum("values")
    entropy_bits = xlog2x(reads) - F.sum(xlog2x(F.col("reads")))
    return shares.agg(
        F.round(reads * math.log2(k) / values, 6).alias("flat_bpv"),
        F.round(entropy_bits / values + 0.0, 6).alias("entropy_bpv"),
    )


def total_bpv(assignment: DataFrame, k: int, storage_bits: float = 0.0) -> DataFrame:
    """Model bits, header bits and (optionally) stored models, per value. ``assignment``: cluster, bits, n."""
    n = F.sum("n")
    return assignment.agg(F.round(F.sum("bits") / n, 6).alias("model_bpv"), F.round((F.sum("bits") + F.count("*") * math.log2(k) + storage_bits) / n, 6).alias("total_bpv"))


def ratio(coded_bits: Column, n: Column, m: int) -> Column:
    """Raw bits (lg m a symbol, rounded up) over coded bits."""
    return n * math.ceil(math.log2(m)) / coded_bits


def order_bits(n: int) -> float:
    """Bits that a free order of n reads is worth: lg(n!)."""
    return math.lgamma(n + 1) / math.log(2)


def purity(assignment: DataFrame, label: str) -> DataFrame:
    """Share of reads that carry their cluster's most frequent label."""
    per = assignment.groupBy("cluster", label).agg(F.count("*").alias("n"))
    top = per.groupBy("cluster").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    return top.agg(F.round(F.sum("top") / F.sum("n"), 6).alias("purity"))


def draw(keys: list[str], seed: int = 0) -> Column:
    """A number from 0 to 1 by a digest of the key columns: the same in every run and in other engines."""
    text = F.concat_ws("|", *[F.coalesce(F.col(k).cast("string"), F.lit("")) for k in keys], F.lit(str(seed)))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("double") / F.lit(float(1 << 48))


def shuffled(assignment: DataFrame, label: str, keys: list[str], seed: int = 0) -> DataFrame:
    """The assignment with every label drawn anew from the labels' shares, by a digest of the row's keys: what is left of a
    label's agreement with the clusters if it says nothing. One row a label is joined, no order of all rows is needed."""
    order = Window.orderBy(F.col("_l").asc_nulls_first())
    per = assignment.groupBy(F.col(label).alias("_l")).agg(F.count("*").alias("_n"))
    ranges = per.select("_l", (F.sum("_n").over(order) - F.col("_n")).alias("_a"), F.sum("_n").over(order).alias("_b"), F.sum("_n").over(Window.partitionBy()).alias("_t"))
    steps = ranges.agg(F.array_sort(F.collect_list(F.struct("_b", "_l"))).alias("_steps"), F.max("_t").alias("_t"))
    place = F.floor(draw(keys, seed) * F.col("_t"))
    drawn = F.filter("_steps", lambda x: x["_b"] > place)[0]["_l"]
    return assignment.crossJoin(steps).withColumn(label, drawn).drop("_steps", "_t")


def chance(assignment: DataFrame, label: str, keys: list[str], seed: int = 0) -> DataFrame:
    """Purity of the same clusters under labels that were drawn anew."""
    return purity(shuffled(assignment, label, keys, seed), label).withColumnRenamed("purity", "chance")


def contingency(assignment: DataFrame, label: str) -> DataFrame:
    return assignment.groupBy("cluster", F.col(label).alias("label")).agg(F.count("*").alias("reads"))
