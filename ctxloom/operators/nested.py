"""Nested binning: high orders from small tables.

A ladder of trees: pairs of previous values are binned first, then pairs of pair-states, and so on. The state of an earlier
place is already known, so each level costs one lookup a symbol.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ctxloom.operators import counts as C
from ctxloom.operators import merge as M
from ctxloom.operators import rates as R
from ctxloom.operators.contexts import Binned, DelayedBin, From, Previous, Product
from ctxloom.operators.stream import Flat, Stream


@dataclass(frozen=True)
class Nesting:
    """A context with the number of states it ends in and of lookups a symbol."""

    spec: object
    states: int
    lookups: int
    kind: str


def bin_context(stream: Stream, spec, bins: int | None = None, rule=None, queue: str = "nearest") -> tuple[Binned, M.MergeTree, np.ndarray]:
    """Counts a context, grows its tree, cuts it, and returns the binned context."""
    codes, table = C.matrix(C.count_windows(stream, spec), stream.m)
    tree = M.tree_of(codes, table, queue)
    cut = M.cut(tree, rule or M.MaxBins(bins))
    n = int(cut.max()) + 1 if len(cut) else 1
    return Binned(spec, M.dense_table(codes, cut, spec.size(stream.m)), n), tree, cut


def pair_binning(stream: Stream, bins: int) -> Nesting:
    """The two previous values as one lookup of their packed pair."""
    spec, _, _ = bin_context(stream, Previous(2), bins)
    return Nesting(spec, spec.bins, 1, "pair")


def nest_symmetric(stream: Stream, levels: list[int]) -> Nesting:
    """The same table at every distance: level i covers 2^i previous values with i lookups."""
    inner, _, _ = bin_context(stream, Previous(2), levels[0])
    for i, bins in enumerate(levels[1:], 1):
        inner, _, _ = bin_context(stream, Product((inner, DelayedBin(inner, 2**i))), bins)
    return Nesting(inner, inner.bins, len(levels), "symmetric")


def nest_asymmetric(stream: Stream, near_bins: int, far_bins: int) -> Nesting:
    """A separate, stronger reduction for the pair further away: chosen by how that pair predicts the symbol."""
    near, _, _ = bin_context(stream, Previous(2), near_bins)
    far, _, _ = bin_context(stream, DelayedBin(Previous(2), 2), far_bins)
    return Nesting(Product((near, far)), near.bins * far.bins, 2, "asymmetric")


def far_from_near(stream: Stream, near_bins: int, shift: int) -> Nesting:
    """One table: the far bin is the near one without its low ``shift`` bits. Bins of the near pair are merged by how the far
    pair predicts, and numbered so that the shift gives those groups."""
    near, _, _ = bin_context(stream, Previous(2), near_bins)
    codes, table = C.matrix(C.count_windows(stream, DelayedBin(near, 2)), stream.m)
    full = np.zeros((near.bins, stream.m))
    full[codes] = table
    number, _ = M.two_level(np.arange(near.bins), full, near.bins, shift)
    size = int(number.max()) + 1
    renumbered = Binned(near.inner, tuple(int(number[b]) for b in near.table), size)
    groups = (size - 1 >> shift) + 1
    coarse = Binned(renumbered, tuple(i >> shift for i in range(size)), groups)
    return Nesting(Product((renumbered, DelayedBin(coarse, 2))), near.bins * groups, 1, "far_from_near")


@dataclass(frozen=True)
class PerBin:
    """Far values binned by a table that depends on the near bin."""

    near: object
    far: object
    table: tuple  # near bin -> bin of each far code, already offset
    states: int

    def size(self, m: int) -> int:
        return self.states

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        a, va = self.near.codes(f, m)
        b, vb = self.far.codes(f, m)
        return np.asarray(self.table, np.int64)[a, b], va & vb


def nest_hierarchical(stream: Stream, near_bins: int, far_bins: int | None = None, max_loss: float | None = None, depth: int = 1) -> Nesting:
    """A tree of contexts: inside every near bin the far pair has a tree of its own. Counts come from one scan a level with
    the near bin as grouping key; the trees grow on the executors, one task a near bin."""
    near, _, _ = bin_context(stream, Previous(2), near_bins)
    spec: object = near
    states, lag = near.bins, 2
    for _ in range(depth):
        far = DelayedBin(Previous(2), lag) if lag == 2 else DelayedBin(near, lag)
        far_size = far.size(stream.m)
        counted = C.count_windows(stream, Product((spec, far)))
        per = counted.select((F.col("ctx") % states).alias("near"), F.expr(f"ctx div {states}").alias("ctx"), "sym", "n")
        rows = M.build_trees(per, "near", stream.m, max_bins=far_bins, max_loss=max_loss).toPandas()
        table, offset = np.zeros((states, far_size), np.int64), 0
        for b in range(states):
            own = rows[rows.near == b]
            table[b] = offset
            if len(own):
                table[b, own["ctx"].to_numpy()] = offset + own["bin"].to_numpy()
                offset += int(own["bin"].max())
            offset += 1
        spec = PerBin(spec, far, tuple(map(tuple, table.tolist())), offset)
        states, lag = offset, lag + 2
    return Nesting(spec, states, 1 + depth, "hierarchical")


def nest_with(stream: Stream, a, b, bins: int) -> Nesting:
    """Two contexts (say previous values and position) binned together."""
    spec, _, _ = bin_context(stream, Product((a, b)), bins)
    return Nesting(spec, spec.bins, 1, "with")


def compare_nestings(stream: Stream, nestings: list[Nesting], start: int, fold: Column | None = None) -> DataFrame:
    """kind, states, lookups, n, bpv of each nesting over the same windows (those from place ``start`` on), in one scan. With a
    ``fold`` (0 or 1, of the stream's rows) also held_out, where each fold is scored by the other's counts; a scan a nesting."""
    spark = stream.df.sparkSession
    names = spark.createDataFrame([(i, x.kind, x.states, x.lookups) for i, x in enumerate(nestings)], "spec int, kind string, states int, lookups int")
    if fold is None:
        rated = R.rate(C.count_many(stream, [From(x.spec, start) for x in nestings]), "spec")
        return names.join(rated, "spec").select("kind", "states", "lookups", "n", "bpv")
    out = None
    for i, x in enumerate(nestings):
        row = R.overfit(stream, From(x.spec, start), fold).select(F.lit(i).alias("spec"), "n", F.col("training").alias("bpv"), "held_out")
        out = row if out is None else out.unionByName(row)
    return names.join(out, "spec").select("kind", "states", "lookups", "n", "bpv", "held_out")
