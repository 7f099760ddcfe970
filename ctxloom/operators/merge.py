"""Context binning: greedy agglomeration of contexts, cuts of the merge tree, and bin tables.

A node is the summed counts of its contexts. Merging s and r costs (E(s + r) - E(s) - E(r)) / N bits per value, where
E(s) = g(n_s) - sum over symbols of g(n_sx) and g(n) = n lg n. Counts come from one aggregation; trees are grown on the
driver up to MAX_CONTEXTS, per group on executors, or in distributed rounds for more.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxloom.operators import counts as C

MAX_CONTEXTS = 8192


def g(n: np.ndarray) -> np.ndarray:
    return n * np.log2(n + (n == 0))


def excess(rows: np.ndarray) -> np.ndarray:
    """Bits that the rows' distributions need for their own counts."""
    return g(rows.sum(axis=-1)) - g(rows).sum(axis=-1)


def merge_cost(a: Column, b: Column, total: Column) -> Column:
    """The same cost for two array<long> columns of counts, in bits per value of ``total`` values."""

    def gs(x: Column) -> Column:
        x = x.cast("double")
        return F.when(x > 0, x * F.log2(x)).otherwise(F.lit(0.0))

    def own(x: Column) -> Column:
        return gs(F.aggregate(x, F.lit(0).cast("long"), lambda s, v: s + v)) - F.aggregate(x, F.lit(0.0), lambda s, v: s + gs(v))

    return (own(F.zip_with(a, b, lambda x, y: x + y)) - own(a) - own(b)) / total


def count_arrays(counts: DataFrame, m: int) -> DataFrame:
    """ctx, row array<long> of its counts by symbol."""
    cell = lambda s: F.coalesce(F.sum(F.when(F.col("sym") == s, F.col("n"))), F.lit(0)).cast("long")
    return counts.groupBy("ctx").agg(F.array(*[cell(s) for s in range(m)]).alias("row"))


def all_pair_costs(counts: DataFrame, m: int) -> DataFrame:
    """ctx_a < ctx_b, delta for all pairs of contexts: a table for small context sets (its size is their number squared); more than
    MAX_CONTEXTS are refused."""
    if counts.select("ctx").distinct().limit(MAX_CONTEXTS + 1).count() > MAX_CONTEXTS:
        raise ValueError(f"more than {MAX_CONTEXTS} contexts: their pairs are not listed")
    rows = count_arrays(counts, m)
    n = counts.agg(F.sum("n")).first()[0] or 1
    a, b = rows.select(F.col("ctx").alias("ctx_a"), F.col("row").alias("ra")), rows.select(F.col("ctx").alias("ctx_b"), F.col("row").alias("rb"))
    return a.join(b, F.col("ctx_a") < F.col("ctx_b")).select("ctx_a", "ctx_b", F.round(merge_cost(F.col("ra"), F.col("rb"), F.lit(float(n))) + 0.0, 6).alias("delta"))


@dataclass
class MergeTree:
    """Leaves 0 .. C-1 are the contexts in order of their codes; merge i makes node C + i."""

    codes: np.ndarray
    table: np.ndarray
    left: list[int] = field(default_factory=list)
    right: list[int] = field(default_factory=list)
    delta: list[float] = field(default_factory=list)

    @property
    def leaves(self) -> int:
        return len(self.codes)

    @property
    def total(self) -> float:
        return float(self.table.sum())

    def full_rate(self) -> float:
        return float(excess(self.table).sum() / max(self.total, 1))

    def frame(self, spark: SparkSession) -> DataFrame:
        """step, node, left, right, delta, and loss: the running sum of deltas."""
        n = len(self.left)
        rows = {"step": list(range(1, n + 1)), "node": [self.leaves + i for i in range(n)], "left": self.left, "right": self.right, "delta": self.delta, "loss": list(np.cumsum(self.delta))}
        kinds = [pa.int32()] * 4 + [pa.float64()] * 2
        return spark.createDataFrame(pa.table({k: pa.array(v, t) for (k, v), t in zip(rows.items(), kinds)}))

    def inversions(self) -> int:
        """Steps that cost less than the step before."""
        return int((np.diff(self.delta) < -1e-12).sum())


def _pair_costs(row: np.ndarray, own: float, rows: np.ndarray, owns: np.ndarray, total: float) -> np.ndarray:
    return np.maximum((excess(rows + row) - owns - own) / total, 0.0)


def _grow_heap(tree: MergeTree, stop: int) -> None:
    rows = [*tree.table.astype(float)]
    owns = [*excess(tree.table.astype(float))]
    total = max(tree.total, 1)
    alive = list(range(len(rows)))
    heap: list[tuple[float, int, int]] = []
    stack, own = np.array(rows), np.array(owns)
    for i in range(len(rows) - 1):
        heap += [(d, i, j) for j, d in enumerate(_pair_costs(rows[i], owns[i], stack[i + 1 :], own[i + 1 :], total).tolist(), i + 1)]
    heapq.heapify(heap)
    gone = [False] * len(rows)
    while len(alive) > stop:
        d, a, b = heapq.heappop(heap)
        while gone[a] or gone[b]:  # candidates of merged nodes are stale
            d, a, b = heapq.heappop(heap)
        gone[a] = gone[b] = True
        new = len(rows)
        rows.append(rows[a] + rows[b])
        owns.append(float(excess(rows[new])))
        gone.append(False)
        alive = [x for x in alive if not gone[x]]
        if alive:
            for x, c in zip(alive, _pair_costs(rows[new], owns[new], np.array([rows[x] for x in alive]), np.array([owns[x] for x in alive]), total).tolist()):
                heapq.heappush(heap, (c, x, new))
        alive.append(new)
        tree.left.append(a), tree.right.append(b), tree.delta.append(d)


def _grow_nearest(tree: MergeTree, stop: int, capacity: int = 0) -> None:
    """Keeps one best partner a node: memory grows with the contexts, not with their pairs. ``capacity`` bounds the leaves of a node."""
    n, total = tree.leaves, max(tree.total, 1)
    rows, name, live = tree.table.astype(float).copy(), np.arange(n), np.ones(n, bool)
    own, load = excess(rows), np.ones(n, int)
    best, cost = np.full(n, -1), np.full(n, np.inf)

    def partner(i: int) -> None:
        others = live.copy()
        others[i] = False
        if capacity:
            others &= load + load[i] <= capacity
        at = np.flatnonzero(others)
        if not len(at):
            best[i], cost[i] = -1, np.inf
            return
        d = _pair_costs(rows[i], own[i], rows[at], own[at], total)
        low = at[d == d.min()]
        best[i], cost[i] = low[np.argmin(name[low])], d.min()

    for i in range(n):
        partner(i)
    # A node whose partner was merged keeps its old cost: a lower bound, as all other old nodes cost at least that and the
    # new node is valued at once. It is searched again only when it comes first.
    stale = np.zeros(n, bool)
    nodes = n
    while live.sum() > stop:
        while True:
            d = np.where(live, cost, np.inf).min()
            again = np.flatnonzero(live & stale & (cost == d)) if np.isfinite(d) else ()
            if not len(again):
                break
            for i in again:
                partner(int(i))
                stale[i] = False
        if not np.isfinite(d):
            break
        tied = np.flatnonzero(live & (cost == d))
        a = min(tied, key=lambda i: (min(name[i], name[best[i]]), max(name[i], name[best[i]])))
        b = int(best[a])
        a, b = (a, b) if name[a] < name[b] else (b, a)
        tree.left.append(int(name[a])), tree.right.append(int(name[b])), tree.delta.append(float(d))
        live[b] = False
        rows[a] += rows[b]
        own[a], load[a], name[a] = excess(rows[a]), load[a] + load[b], nodes
        nodes += 1
        others = np.flatnonzero(live)
        others = others[others != a]
        if not len(others):
            break
        lost = (best[others] == a) | (best[others] == b)
        stale[others[lost]] = True
        stale[a] = False
        costs = _pair_costs(rows[a], own[a], rows[others], own[others], total)
        if capacity:
            costs[load[others] + load[a] > capacity] = np.inf
        nearer = (costs < cost[others]) | (lost & (costs == cost[others]) & np.isfinite(costs))
        best[others[nearer]], cost[others[nearer]] = a, costs[nearer]
        stale[others[nearer]] = False
        low = others[costs == costs.min()]
        best[a], cost[a] = (low[np.argmin(name[low])], costs.min()) if np.isfinite(costs.min()) else (-1, np.inf)


def tree_of(codes: np.ndarray, table: np.ndarray, queue: str = "nearest", stop_at: int = 1) -> MergeTree:
    if len(codes) > MAX_CONTEXTS:
        raise ValueError(f"{len(codes)} contexts: bin in stages, per group, or with backend='rounds'")
    tree = MergeTree(codes, table)
    if len(codes) > stop_at:
        (_grow_heap if queue == "heap" else _grow_nearest)(tree, stop_at)
    return tree


def build_tree(counts: DataFrame, m: int, queue: str = "nearest", stop_at: int = 1, backend: str = "driver") -> MergeTree:
    codes, table = C.matrix(counts, m)
    if backend == "rounds":
        return _rounds(counts.sparkSession, codes, table, stop_at)
    return tree_of(codes, table, queue, stop_at)


def _rounds(spark: SparkSession, codes: np.ndarray, table: np.ndarray, stop: int) -> MergeTree:
    """Approximate: each round merges all pairs that are each other's best. Slices of the contexts search all contexts on
    the executors; one row a context comes back. The count matrix that is sent out is checked against the model limit."""
    if table.size > C.BROADCAST_CELLS:
        raise ValueError("too many contexts for one count matrix; reduce them first")
    tree = MergeTree(codes, table)
    rows, name, nodes = table.astype(float), np.arange(len(codes)), len(codes)
    total = max(tree.total, 1)
    while len(rows) > stop:
        sent = spark.sparkContext.broadcast((rows, excess(rows)))

        def search(batches):
            every, own = sent.value
            for batch in batches:
                ids = batch.column(0).to_numpy()
                best, cost = [], []
                for i in ids:
                    d = _pair_costs(every[i], own[i], every, own, total)
                    d[i] = np.inf
                    best.append(int(d.argmin())), cost.append(float(d.min()))
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(best, pa.int64()), pa.array(cost)], names=["i", "best", "cost"])

        slices = max(1, min(len(rows) // 64, spark.sparkContext.defaultParallelism * 4))
        got = spark.range(0, len(rows), 1, slices).mapInArrow(search, "i long, best long, cost double").toArrow()
        order = np.argsort(got.column("i").to_numpy())
        best, cost = got.column("best").to_numpy()[order], got.column("cost").to_numpy()[order]
        sent.unpersist()
        mutual = [(cost[i], i, int(best[i])) for i in range(len(rows)) if best[best[i]] == i and i < best[i]]
        if not mutual:  # ties in a ring: take the cheapest
            i = int(cost.argmin())
            mutual = [(cost[i], min(i, int(best[i])), max(i, int(best[i])))]
        keep = np.ones(len(rows), bool)
        for d, a, b in sorted(mutual)[: len(rows) - stop]:
            tree.left.append(int(min(name[a], name[b]))), tree.right.append(int(max(name[a], name[b]))), tree.delta.append(float(d))
            rows[a] += rows[b]
            name[a], keep[b], nodes = nodes, False, nodes + 1
        rows, name = rows[keep], name[keep]
    return tree


def build_trees(counts: DataFrame, by: str, m: int, max_bins: int | None = None, max_loss: float | None = None) -> DataFrame:
    """A tree for every group, grown on the executors and cut there: by, ctx, bin. Groups hold one context table each."""
    kind = counts.schema[by].dataType.simpleString()

    def kernel(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        codes, at = np.unique(pdf["ctx"].to_numpy(), return_inverse=True)
        table = np.zeros((len(codes), m), np.int64)
        np.add.at(table, (at, pdf["sym"].to_numpy()), pdf["n"].to_numpy())
        tree = tree_of(codes, table)
        bins = cut(tree, MaxBins(max_bins) if max_bins else MaxLoss(max_loss if max_loss is not None else 0.01))
        return pd.DataFrame({by: key[0], "ctx": codes, "bin": bins})

    return counts.groupBy(by).applyInPandas(kernel, f"{by} {kind}, ctx long, bin int")


@dataclass(frozen=True)
class MaxBins:
    bins: int

    def more(self, bins: int, loss: float, gain: float) -> bool:
        return bins < self.bins


@dataclass(frozen=True)
class MaxLoss:
    """Open nodes until the loss against all contexts is at most this many bits per value."""

    loss: float

    def more(self, bins: int, loss: float, gain: float) -> bool:
        return loss > self.loss + 1e-12


@dataclass(frozen=True)
class MinGain:
    """Open nodes while that gains at least this many bits per value."""

    gain: float

    def more(self, bins: int, loss: float, gain: float) -> bool:
        return gain >= self.gain


def cut(tree: MergeTree, rule, order: str = "reverse") -> np.ndarray:
    """Bin of every leaf. The root's frontier is opened node by node: last merge first, or costliest node first."""
    n, merges = tree.leaves, len(tree.left)
    if not n:
        return np.zeros(0, np.int64)
    children = set(tree.left) | set(tree.right)
    roots = [x for x in range(n + merges) if x not in children]
    frontier = set(roots)
    loss = float(sum(tree.delta))
    key = (lambda x: -x) if order == "reverse" else (lambda x: (-tree.delta[x - n], -x))
    heap = [(key(x), x) for x in roots if x >= n]
    heapq.heapify(heap)
    while heap:
        x = heap[0][1]
        gain = tree.delta[x - n]
        if not rule.more(len(frontier), loss, gain):
            break
        heapq.heappop(heap)
        frontier.remove(x)
        loss -= gain
        for child in (tree.left[x - n], tree.right[x - n]):
            frontier.add(child)
            if child >= n:
                heapq.heappush(heap, (key(child), child))
    owner = np.full(n + merges, -1)
    for x in frontier:
        owner[x] = x
    for x in range(n + merges - 1, n - 1, -1):
        if owner[x] >= 0:
            owner[tree.left[x - n]] = owner[tree.right[x - n]] = owner[x]
    _, first, bins = np.unique(owner[:n], return_index=True, return_inverse=True)
    rank = np.empty(len(first), np.int64)
    rank[np.argsort(first)] = np.arange(len(first))  # bins are numbered by their least context
    return rank[bins]


def cut_many(tree: MergeTree, rules: list, order: str = "reverse") -> list[np.ndarray]:
    """Several cuts of one tree; cuts in reverse order are nested in one another."""
    return [cut(tree, r, order) for r in rules]


def binned_rate(tree: MergeTree, bins: np.ndarray) -> float:
    summed = np.zeros((bins.max() + 1, tree.table.shape[1]))
    np.add.at(summed, bins, tree.table)
    return float(excess(summed).sum() / tree.total)


def loss_curve(tree: MergeTree) -> list[tuple[int, float]]:
    """(bins, bits per value) for every number of bins, from one tree."""
    full, loss = tree.full_rate(), np.concatenate([[0], np.cumsum(tree.delta)])
    return [(tree.leaves - i, full + float(x)) for i, x in enumerate(loss)][::-1]


def two_level(codes: np.ndarray, table: np.ndarray, fine: int, shift: int) -> tuple[np.ndarray, np.ndarray]:
    """Bins numbered so that ``bin >> shift`` is a coarser binning: (bin of each context, rows of the fine bins' counts).

    The fine bins become the contexts of a second tree whose nodes hold at most 2^shift of them; unfilled numbers stay unused.
    """
    tree = tree_of(codes, table)
    bins = cut(tree, MaxBins(fine))
    rows = np.zeros((bins.max() + 1, table.shape[1]))
    np.add.at(rows, bins, table)
    second = MergeTree(np.arange(len(rows)), rows)
    _grow_nearest(second, max(1, -(-len(rows) // (1 << shift))), capacity=1 << shift)
    groups = cut(second, MaxBins(1))  # open nothing: the remaining roots are the groups
    place = np.zeros(len(rows), np.int64)
    for x in np.unique(groups):
        own = np.flatnonzero(groups == x)
        place[own] = (x << shift) + np.arange(len(own))
    return place[bins], rows


def bin_frame(spark: SparkSession, codes: np.ndarray, bins: np.ndarray) -> DataFrame:
    return spark.createDataFrame(pa.table({"ctx": pa.array(codes, pa.int64()), "bin": pa.array(bins.astype(np.int32))}))


def dense_table(codes: np.ndarray, bins: np.ndarray, size: int, fallback: int | None = None) -> tuple:
    """The bin of every possible context; contexts not seen get ``fallback`` (default: the bin with most contexts)."""
    if fallback is None:
        fallback = int(np.bincount(bins).argmax()) if len(bins) else 0
    out = np.full(size, fallback, np.int64)
    out[codes] = bins
    return tuple(out.tolist())


def apply_bins(df: DataFrame, table: tuple | DataFrame, column: str = "ctx", fallback: int = 0) -> DataFrame:
    """Adds ``bin``. A dense table of up to 64k contexts is an array literal inside the generated code; a bin DataFrame is
    joined by key, and Spark decides by its size whether to send it out."""
    if isinstance(table, DataFrame):
        joined = df.join(table.select(F.col("ctx").alias(column), "bin"), column, "left")
        return joined.withColumn("bin", F.coalesce("bin", F.lit(fallback)))
    if len(table) > 1 << 16:
        raise ValueError("pass a DataFrame of bins for more than 64k contexts")
    literal = F.lit(list(map(int, table)))
    return df.withColumn("bin", F.coalesce(F.get(literal, F.col(column).cast("int")), F.lit(fallback)).cast("int"))


def rebin_counts(counts: DataFrame, bins: DataFrame) -> DataFrame:
    """Count table with the bins as contexts."""
    return counts.join(bins, "ctx").groupBy(F.col("bin").cast("long").alias("ctx"), "sym").agg(F.sum("n").alias("n"))


def bin_ranges(bins: DataFrame) -> DataFrame:
    """bin, first, last, members, runs: whether each bin is one contiguous range of codes (runs = 1)."""
    order = Window.orderBy("ctx")
    islands = bins.withColumn("new", (F.coalesce(F.lag("bin").over(order), F.lit(-1)) != F.col("bin")).cast("int"))
    return islands.groupBy("bin").agg(F.min("ctx").alias("first"), F.max("ctx").alias("last"), F.count("*").alias("members"), F.sum("new").alias("runs"))
