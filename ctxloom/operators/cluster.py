"""Model clustering: k-means over reads whose centroids are statistical models and whose distance is the bits they need.

Assignment and refit are one pass: a kernel values every read under all models, adds its counts to the cheapest, and
only pooled counts leave a partition. The relational twin (read_counts, costs_by_join, assign_by_join, refit) does the
same with joins, for models too large to send out and for comparison with SQL.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.operators import rates as R
from ctxloom.operators.contexts import Context
from ctxloom.operators.counts import BROADCAST_CELLS
from ctxloom.operators.stream import Flat, Stream, pieces
from ctxloom.session import schema_with


def _cells(f: Flat, spec: Context, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Model cell of each counted symbol, and its sequence."""
    ctx, valid = spec.codes(f, m)
    cell, owner = ctx * m + f.codes, f.owner()
    return (cell, owner) if valid.all() else (cell[valid], owner[valid])


def _costs(cell: np.ndarray, owner: np.ndarray, bits: np.ndarray, sequences: int) -> np.ndarray:
    """(sequences, k) bits under each of k models (k, cells)."""
    return np.stack([np.bincount(owner, table[cell], sequences) for table in bits], axis=1) if len(bits) else np.zeros((sequences, 0))


def _id_schema(stream: Stream) -> T.StructType:
    return T.StructType([stream.df.schema[c] for c in stream.ids])


def read_counts(stream: Stream, spec: Context) -> DataFrame:
    """ids, read_no, ctx, sym, n per read, counted inside the row: no shuffle."""
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    schema = schema_with(_id_schema(stream), "read_no int, ctx long, sym int, n long")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            cell, owner = _cells(f, spec, m)
            span = spec.size(m) * m
            key, n = np.unique(owner * span + cell, return_counts=True)
            seq, cell = key // span, key % span
            cols = [batch.column(c).take(pa.array(f.row[seq])) for c in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth[seq], pa.int32()), pa.array(cell // m), pa.array(cell % m, pa.int32()), pa.array(n, pa.int64())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)


def read_costs(stream: Stream, spec: Context, bits: np.ndarray) -> DataFrame:
    """ids, read_no, bits array<double> (one per model), n."""
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    if bits.size > BROADCAST_CELLS:
        raise ValueError("these models are too large to send out; use costs_by_join")
    schema = schema_with(_id_schema(stream), "read_no int, bits array<double>, n long")
    sent = stream.df.sparkSession.sparkContext.broadcast(bits.reshape(len(bits), -1))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            cell, owner = _cells(f, spec, m)
            cost = _costs(cell, owner, sent.value, len(f.row))
            k = cost.shape[1]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(cost) * k + 1, k), pa.int32()), pa.array(cost.ravel()))
            cols = [batch.column(c).take(pa.array(f.row)) for c in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), lists, pa.array(np.bincount(owner, minlength=len(f.row)), pa.int64())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)


def header_costs(k: int, kind: str = "none", shares: np.ndarray | None = None) -> np.ndarray:
    """Bits of naming each model: none, lg k each, or lg of the inverse share."""
    if kind == "entropy" and shares is not None:
        return -np.log2(np.maximum(shares, 1e-12) / max(shares.sum(), 1e-12))
    return np.full(k, np.log2(k) if kind == "flat" else 0.0)


def assign(costs: DataFrame, header: np.ndarray | None = None, k: int | None = None) -> DataFrame:
    """The cheapest model of each read (ties: lowest id): cluster, bits (with the header's), and the other columns."""
    extra = F.lit([float(x) for x in header]) if header is not None else None
    total = F.col("bits") if extra is None else F.zip_with("bits", extra, lambda a, b: a + b)
    ranked = F.transform(total, lambda b, i: F.struct(F.round(b, 9).alias("bits"), i.alias("cluster")))
    return costs.withColumn("_best", F.array_min(ranked)).withColumn("cluster", F.col("_best.cluster")).withColumn("bits", F.col("_best.bits")).drop("_best")


@dataclass
class Clustering:
    spec: object
    m: int
    alpha: float
    tables: np.ndarray  # (k, contexts, m) pooled counts
    history: list[float] = field(default_factory=list)  # total bits at each assignment
    penalised: list[float] = field(default_factory=list)
    sizes: np.ndarray | None = None

    @property
    def k(self) -> int:
        return len(self.tables)

    def bits(self) -> np.ndarray:
        return model_bits(self.tables, self.alpha)

    def assign(self, stream: Stream, header: str = "none") -> DataFrame:
        extra = header_costs(self.k, header, self.sizes)
        return assign(read_costs(stream, self.spec, self.bits()), None if header == "none" else extra)


def model_bits(tables: np.ndarray, alpha: float) -> np.ndarray:
    full = tables + alpha
    return np.log2(full.sum(axis=-1, keepdims=True)) - np.log2(full)


def _read_numbers(stream: Stream) -> DataFrame:
    """ids, read_no of every read that has symbols: by lengths alone, without reading symbols."""
    size = F.coalesce(F.length(stream.payload) if stream.kind != "array" else F.size(stream.payload), F.lit(0))
    if stream.read_length:
        reads = F.ceil(size / stream.read_length) if stream.tail == "keep" else F.floor(size / stream.read_length)
    else:
        reads = (size > 0).cast("int")
    rows = stream.df.select(*stream.ids, F.greatest(reads, F.lit(0)).cast("int").alias("reads")).where("reads > 0")
    return rows.select(*stream.ids, F.explode(F.sequence(F.lit(0), F.col("reads") - 1)).alias("read_no"))


def pick_reads(stream: Stream, spec: Context, k: int, how: str = "random", seed: int = 0) -> np.ndarray:
    """(k, contexts, m) counts of k reads: those with the least digest of ids, number and seed, or the first by id.

    Every partition offers its best k; k reads reach the driver. Reads of one name count once, with their greatest symbols.
    """
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    names = _read_numbers(stream)
    order = [*ids, "read_no"] if how == "first" else [R.draw([*ids, "read_no"], seed), *ids, "read_no"]
    picked = names.orderBy(*order).limit(2 * k).collect()
    if len(set(picked)) < k <= len(picked):  # repeated names fill the first places
        picked = names.distinct().orderBy(*order).limit(k).collect()
    seen: dict[tuple, int] = {}
    for r in picked:
        if len(seen) < k:
            seen.setdefault(tuple(r), len(seen))
    wanted = {}
    for key, place in seen.items():
        wanted.setdefault(key[:-1], []).append((key[-1], place))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            keys = list(zip(*[batch.column(i + 1).to_pylist() for i in range(len(ids))])) or [()] * batch.num_rows
            own = [i for i, key in enumerate(keys) if key in wanted]
            if not own:
                continue
            f = flat(batch.column(0).take(pa.array(own)))
            at = {(int(r), int(n)): s for s, (r, n) in enumerate(zip(f.row, f.nth))}
            for r, i in enumerate(own):
                for n, place in wanted[keys[i]]:
                    if (r, n) in at:
                        s = at[r, n]
                        yield pa.RecordBatch.from_arrays([pa.array([place], pa.int32()), pa.array([f.codes[f.starts[s] : f.starts[s + 1]].tolist()], pa.list_(pa.int32()))], names=["place", "syms"])

    rows = stream.select(*ids).mapInArrow(kernel, "place int, syms array<int>").groupBy("place").agg(F.max("syms").alias("syms")).orderBy("place").collect()
    out = np.zeros((len(rows), spec.size(m), m))
    for i, r in enumerate(rows):
        f = Flat(np.array(r.syms, np.int64), np.array([0, len(r.syms)]), np.zeros(1, np.int64), np.zeros(1, np.int64))
        cell, _ = _cells(f, spec, m)
        out[i] = np.bincount(cell, minlength=spec.size(m) * m).reshape(-1, m)
    return out


def worst_read(stream: Stream, spec: Context, bits: np.ndarray) -> np.ndarray:
    """Counts of the read that costs most bits a value under its best model (ties: the greatest symbols)."""
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    if bits.size > BROADCAST_CELLS:
        raise ValueError("these models are too large to send out")
    sent = stream.df.sparkSession.sparkContext.broadcast(bits.reshape(len(bits), -1))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top: tuple = ()
        for batch in pieces(batches):
            f = flat(batch.column(0))
            cell, owner = _cells(f, spec, m)
            n = np.bincount(owner, minlength=len(f.row))
            cost = np.round(np.where(n > 0, _costs(cell, owner, sent.value, len(f.row)).min(axis=1) / np.maximum(n, 1), -1), 9)
            if len(cost) and (not top or cost.max() >= top[0]):
                tied = [f.codes[f.starts[s] : f.starts[s + 1]].tolist() for s in np.flatnonzero(cost == cost.max())]
                top = max(top, (float(cost.max()), max(tied))) if top else (float(cost.max()), max(tied))
        if top:
            yield pa.RecordBatch.from_arrays([pa.array([top[0]]), pa.array([top[1]], pa.list_(pa.int32()))], names=["c", "syms"])

    row = stream.select(*ids).mapInArrow(kernel, "c double, syms array<int>").agg(F.max(F.struct("c", "syms")).alias("t")).first()["t"]
    sent.unpersist()
    syms = np.array(row["syms"] if row else [], np.int64)
    cell, _ = _cells(Flat(syms, np.array([0, len(syms)]), np.zeros(1, np.int64), np.zeros(1, np.int64)), spec, m)
    return np.bincount(cell, minlength=spec.size(m) * m).reshape(-1, m).astype(float)


def assign_and_pool(stream: Stream, spec: Context, bits: np.ndarray, update: str = "joint") -> tuple[np.ndarray, float, np.ndarray]:
    """One pass: pooled counts (k, contexts, m) of the reads that each model codes cheapest, their total bits, reads per model."""
    m, flat = stream.m, stream.flat
    k, span = len(bits), spec.size(m) * m
    if bits.size > BROADCAST_CELLS:
        raise ValueError("these models are too large to send out; use the relational form")
    sent = stream.df.sparkSession.sparkContext.broadcast(bits.reshape(k, -1))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pool, cost_of, reads = np.zeros(k * span), np.zeros(k), np.zeros(k)
        for batch in pieces(batches):
            f = flat(batch.column(0))
            cell, owner = _cells(f, spec, m)
            n = np.bincount(owner, minlength=len(f.row))
            cost = np.round(_costs(cell, owner, sent.value, len(f.row)), 9)
            best = cost.argmin(axis=1)
            best[n == 0] = 0
            weight = None
            if update == "conditional":  # each read gives its conditional distributions, by its length
                pair, inverse = np.unique(owner * (span // m) + cell // m, return_inverse=True)
                weight = n[owner] / np.bincount(inverse)[inverse]
            pool += np.bincount(best[owner] * span + cell, weight, k * span)
            cost_of += np.bincount(best, cost[np.arange(len(best)), best], k)
            reads += np.bincount(best[n > 0], minlength=k)
        at = np.flatnonzero(pool)
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate([at, -1 - np.arange(k)])), pa.array(np.concatenate([pool[at], cost_of])), pa.array(np.concatenate([np.zeros(len(at)), reads]))], names=["cell", "v", "r"]
        )

    got = stream.select().mapInArrow(kernel, "cell long, v double, r double").groupBy("cell").agg(F.sum("v").alias("v"), F.sum("r").alias("r")).toArrow()
    sent.unpersist()
    cell, v, r = (got.column(c).to_numpy() for c in ("cell", "v", "r"))
    pool = np.zeros(k * span)
    pool[cell[cell >= 0]] = v[cell >= 0]
    reads = np.zeros(k)
    reads[-1 - cell[cell < 0]] = r[cell < 0]
    return pool.reshape(k, -1, m), float(v[cell < 0].sum()), reads


def cluster_models(
    stream: Stream, spec: Context, k: int, init: str | np.ndarray = "random", tol: float = 1e-4, max_iter: int = 20, seed: int = 0,
    alpha: float = 0.1, update: str = "joint", empty: str = "reseed", restarts: int = 1, sample: float = 1.0,
) -> Clustering:
    """Clusters the stream's reads. Each round is one pass over the reads; only the k models visit the driver.

    Smoothing ``alpha`` is needed, as a model of one read has empty cells. ``sample`` trains on a hash sample of the rows; assign
    the whole stream afterwards. ``empty`` clusters get the worst-coded read, or are dropped.
    """
    if restarts > 1:
        runs = [cluster_models(stream, spec, k, init, tol, max_iter, seed + i, alpha, update, empty, 1, sample) for i in range(restarts)]
        return min(runs, key=lambda c: c.history[-1])
    train = stream
    if sample < 1:
        train = stream.where(R.draw(list(stream.ids), seed) < sample)
    if isinstance(init, np.ndarray):
        tables = init
    elif init == "spread":
        tables = pick_reads(train, spec, 1, "random", seed)
        while 0 < len(tables) < k:
            tables = np.concatenate([tables, worst_read(train, spec, model_bits(tables, alpha))[None]])
    else:
        tables = pick_reads(train, spec, k, init, seed)
    out = Clustering(spec, stream.m, alpha, tables)
    if not len(tables):
        return out
    for _ in range(max_iter):
        bits = model_bits(out.tables, alpha)
        pool, total, reads = assign_and_pool(train, spec, bits, update)
        out.history.append(total)
        out.penalised.append(total + alpha * float(bits.sum()))
        if empty == "drop":
            pool, reads = pool[reads > 0], reads[reads > 0]
        elif (reads == 0).any() and reads.sum() >= len(reads):
            for j in np.flatnonzero(reads == 0):
                pool[j] = worst_read(train, spec, model_bits(pool[reads > 0], alpha))
        out.tables, out.sizes = pool, reads
        if len(out.history) > 1 and abs(out.history[-2] - total) <= tol * max(abs(total), 1e-12):
            break
    return out


def costs_by_join(counts: DataFrame, models: DataFrame, keys: list[str]) -> DataFrame:
    """keys, cluster, bits, n: sparse read counts joined with models (cluster, ctx, sym, bits) on the cell."""
    return counts.join(models, ["ctx", "sym"]).groupBy(*keys, "cluster").agg(F.sum(F.col("n") * F.col("bits")).alias("bits"), F.sum("n").alias("n"))


def assign_by_join(costs: DataFrame, keys: list[str]) -> DataFrame:
    best = F.min(F.struct(F.round("bits", 9).alias("bits"), "cluster", "n")).alias("best")
    return costs.groupBy(*keys).agg(best).select(*keys, "best.cluster", "best.bits", "best.n")


def refit(counts: DataFrame, assignment: DataFrame, keys: list[str], alpha: float, contexts: int, m: int) -> DataFrame:
    """Models (cluster, ctx, sym, bits) from pooled counts plus ``alpha`` in every cell."""
    pooled = counts.join(assignment.select(*keys, "cluster"), keys).groupBy("cluster", "ctx", "sym").agg(F.sum("n").alias("n"))
    spark = counts.sparkSession
    grid = pooled.select("cluster").distinct().join(spark.range(contexts * m).select((F.expr(f"id div {m}")).alias("ctx"), (F.col("id") % m).cast("int").alias("sym")))
    full = grid.join(pooled, ["cluster", "ctx", "sym"], "left").withColumn("n", F.coalesce("n", F.lit(0)) + F.lit(alpha))
    total = full.groupBy("cluster", "ctx").agg(F.sum("n").alias("t"))
    return full.join(total, ["cluster", "ctx"]).select("cluster", "ctx", "sym", F.log2(F.col("t") / F.col("n")).alias("bits"))


def cluster_report(assignment: DataFrame, width: float = 0.1) -> DataFrame:
    """Histogram of bits a value by cluster: cluster, bucket (its lower end), reads."""
    return assignment.where("n > 0").groupBy("cluster", (F.floor(F.col("bits") / F.col("n") / width) * width).alias("bucket")).agg(F.count("*").alias("reads"))


def context_shares(c: Clustering) -> np.ndarray:
    """(k, contexts) probability of each context in each cluster."""
    n = c.tables.sum(axis=2)
    return n / np.maximum(n.sum(axis=1, keepdims=True), 1e-300)


def train_library(stream: Stream, spec: Context, n: int = 20, **options) -> Clustering:
    """A default set of models from a large data set, to be chosen from per file."""
    return cluster_models(stream, spec, n, **options)


def _same_file(left: DataFrame, right: DataFrame, file: str) -> DataFrame:
    """Inner join on the file key, where null is a file, too."""
    named = right.withColumnRenamed(file, "_file")
    return left.join(named, left[file].eqNullSafe(named["_file"])).drop("_file")


def choose_menu(costs: DataFrame, file: str, k: int, size: int = 4, method: str = "greedy") -> DataFrame:
    """file, menu array<int>, bits: the models with least total bits when each read takes its best of them.

    Greedy adds one model at a time, one aggregation each, for all files at once. Exhaustive values all subsets in one pass
    (C(k, size) sums a file).
    """
    if method == "greedy":
        rows = costs.select(file, "bits", F.lit(float("inf")).alias("best"))
        menus = None
        for _ in range(size):
            sums = [F.sum(F.least("best", F.col("bits")[j])).alias(f"s{j}") for j in range(k)]
            per = rows.groupBy(file).agg(*sums)
            ranked = F.array_min(F.array(*[F.struct(F.round(f"s{j}", 6).alias("bits"), F.lit(j).alias("pick")) for j in range(k)]))
            pick = per.select(file, ranked.alias("r")).select(file, F.col("r.pick").alias("pick"), F.col("r.bits").alias("total"))
            menus = pick.select(file, F.array("pick").alias("menu"), "total") if menus is None else _same_file(menus.drop("total"), pick, file).select(file, F.array_append("menu", F.col("pick")).alias("menu"), "total")
            rows = _same_file(rows, pick.select(file, "pick"), file).select(file, "bits", F.least("best", F.get("bits", F.col("pick"))).alias("best"))
        return menus.select(file, F.array_sort("menu").alias("menu"), F.col("total").alias("bits"))
    from itertools import combinations

    subsets = np.array(list(combinations(range(k), size)))
    kind = costs.schema[file].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict = {}
        for batch in batches:
            names = np.array(batch.column(0).to_pylist(), object)
            bits = batch.column(1).flatten().to_numpy().reshape(-1, k)
            for name in set(names):
                own = bits[names == name]
                s = sum((own[i : i + 512][:, subsets].min(axis=2).sum(axis=0) for i in range(0, len(own), 512)), np.zeros(len(subsets)))
                total[name] = total.get(name, 0) + s
        for name, s in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(s), batch.schema.field(0).type), pa.array(np.arange(len(s))), pa.array(s)], names=[file, "subset", "bits"])

    per = costs.select(file, "bits").mapInArrow(kernel, f"{file} {kind}, subset long, bits double").groupBy(file, "subset").agg(F.round(F.sum("bits"), 6).alias("bits"))
    best = per.groupBy(file).agg(F.min(F.struct("bits", "subset")).alias("b"))
    menus = F.get(F.lit([list(map(int, s)) for s in subsets]), F.col("b.subset").cast("int"))
    return best.select(file, menus.alias("menu"), F.col("b.bits").alias("bits"))


def menu_costs(costs: DataFrame, menus: DataFrame, file: str) -> DataFrame:
    """Each read's cost under its file's menu, and its choice (place in the menu)."""
    joined = _same_file(costs, menus.select(file, "menu"), file)
    ranked = F.transform("menu", lambda j, i: F.struct(F.round(F.get(F.col("bits"), j), 9).alias("bits"), i.alias("choice")))
    return joined.withColumn("_b", F.array_min(ranked)).withColumn("choice", F.col("_b.choice")).withColumn("bits", F.col("_b.bits")).drop("_b", "menu")


@dataclass(frozen=True)
class Selected:
    """A k times larger model whose context carries the read's cluster: the selector is the last symbol's block in the row.

    ``inner`` contexts are offset by selector * size; the selector is read from the sequence's batch row by ``selectors``.
    """

    inner: object
    k: int
    bits: tuple  # (k, cells) the models that choose

    def size(self, m: int) -> int:
        return self.k * self.inner.size(m)

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        ctx, valid = self.inner.codes(f, m)
        cell, owner = (ctx * m + f.codes)[valid], f.owner()[valid]
        best = np.round(_costs(cell, owner, np.asarray(self.bits), len(f.row)), 9).argmin(axis=1)
        return ctx + np.repeat(best, f.size) * self.inner.size(m), valid


def soft_switch(stream: Stream, spec: Context, bits: np.ndarray, forget: float = 0.95, mixture: bool = True) -> DataFrame:
    """ids, read_no, bits, n when models are switched by the symbols themselves, without a header.

    Model j weighs 2^-(its forgotten bits so far); symbols are coded under the weighted mixture, or under the best so far.
    All reads of a batch advance together, place by place.
    """
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    schema = schema_with(_id_schema(stream), "read_no int, bits double, n long")
    tables = bits.reshape(len(bits), -1)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            ctx, valid = spec.codes(f, m)
            cell = ctx * m + f.codes
            order = np.argsort(-f.size, kind="stable")
            size, start = f.size[order], f.starts[:-1][order]
            past, spent = np.zeros((len(order), len(tables))), np.zeros(len(order))
            for t in range(int(size[0]) if len(size) else 0):
                live = int(np.searchsorted(-size, -t, "left"))
                at = start[:live] + t
                cost = tables[:, cell[at]].T
                used = valid[at]
                if mixture:
                    w = np.exp2(-(past[:live] - past[:live].min(axis=1, keepdims=True)))
                    now = -np.log2((w * np.exp2(-cost)).sum(axis=1) / w.sum(axis=1))
                else:
                    now = cost[np.arange(live), past[:live].argmin(axis=1)]
                spent[:live] += np.where(used, now, 0)
                past[:live] = np.where(used[:, None], forget * past[:live] + cost, past[:live])
            back = np.empty(len(order))
            back[order] = spent
            n = np.bincount(f.owner()[valid], minlength=len(f.row))
            cols = [batch.column(c).take(pa.array(f.row)) for c in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), pa.array(back), pa.array(n, pa.int64())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)
