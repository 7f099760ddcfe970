"""Adaptivity: exponentially forgotten averages, half-life fitting, and integer shifts of (per-context) distribution functions.

Scans are sequential inside a row (a read, a block or one key's events) and independent across rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.operators.contexts import Context, Previous
from ctxloom.operators.counts import Model
from ctxloom.operators.stream import Flat, Stream, array_stream, pieces
from ctxloom.session import schema_with

CDF_BITS = 15
FLOOR = 1e-6


def half_life(eta: Column) -> Column:
    """Distance at which a contribution has halved."""
    return -1 / F.log2(eta)


def eta_from_half_life(mu: Column) -> Column:
    return F.pow(F.lit(2.0), -1 / mu)


def eta_from_rate(rate: Column) -> Column:
    """A shift by ``rate`` forgets like this factor."""
    return 1 - F.pow(F.lit(2.0), -rate)


def ema(values: Column, eta: float, init: float = 0.0) -> Column:
    """The moving average after the last element of an array: v <- eta v + (1 - eta) x."""
    return F.aggregate(values, F.lit(float(init)), lambda v, x: v * eta + x * (1 - eta))


def ema_trail(values: Column, eta: float, init: float = 0.0) -> Column:
    """The average before each element (code first, update then)."""
    return F.aggregate(
        values, F.struct(F.lit(float(init)).alias("v"), F.array().cast("array<double>").alias("trail")),
        lambda a, x: F.struct((a["v"] * eta + x * (1 - eta)).alias("v"), F.array_append(a["trail"], a["v"]).alias("trail")), lambda a: a["trail"],
    )


def ema_location_scale(values: Column, eta: float) -> Column:
    """Struct of centre and scale (mean absolute deviation from the moving centre) after the array."""
    first = F.coalesce(F.get(values, F.lit(0)), F.lit(0.0))
    return F.aggregate(
        values, F.struct(first.alias("centre"), F.lit(0.0).alias("scale")),
        lambda a, x: F.struct((a["centre"] * eta + x * (1 - eta)).alias("centre"), (a["scale"] * eta + F.abs(x - a["centre"]) * (1 - eta)).alias("scale")),
    )


def ema_cov(rows: DataFrame, key: str, order: str, vector: str, eta: float) -> DataFrame:
    """key, n, cov array<array<double>>: moving covariance of each key's vectors in order. One task holds one key's rows at a time."""
    kind = rows.schema[key].dataType.simpleString()

    def kernel(name: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.array(pdf.sort_values(order)[vector].tolist(), float)
        mean, cov = x[0].copy(), np.zeros((x.shape[1],) * 2)
        for v in x:
            d = v - mean
            cov = eta * (cov + (1 - eta) * np.outer(d, d))
            mean += (1 - eta) * d
        return pd.DataFrame({key: [name[0]], "n": [len(x)], "cov": [cov.tolist()]})

    return rows.select(key, order, vector).groupBy(key).applyInPandas(kernel, f"{key} {kind}, n long, cov array<array<double>>")


def power_scale(values: Column, eta: float, kappa: float = 1.0) -> Column:
    """Moving scale of the density exp(-|x / s|^kappa) around 0 after the array: s^kappa = kappa * average of |x|^kappa."""
    return F.pow(kappa * ema(F.transform(values, lambda x: F.pow(F.abs(x), F.lit(kappa))), eta), F.lit(1.0 / kappa))


def adaptive_regression(rows: DataFrame, key: str, order: str, x: str, y: str, eta: float, ridge: float = 1e-6) -> DataFrame:
    """key, n, weights, mse: least squares from moving moments of (x, y), each row predicted before it is used. ``x`` is an array."""
    kind = rows.schema[key].dataType.simpleString()

    def kernel(name: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order)
        X, Y = np.array(pdf[x].tolist(), float), pdf[y].to_numpy(float)
        xx, xy, w, error = ridge * np.eye(X.shape[1]), np.zeros(X.shape[1]), np.zeros(X.shape[1]), 0.0
        for a, b in zip(X, Y):
            error += (b - a @ w) ** 2
            xx = eta * xx + (1 - eta) * (np.outer(a, a) + ridge * np.eye(len(a)))
            xy = eta * xy + (1 - eta) * a * b
            w = np.linalg.solve(xx, xy)
        return pd.DataFrame({key: [name[0]], "n": [len(Y)], "weights": [w.tolist()], "mse": [error / max(len(Y), 1)]})

    return rows.select(key, order, x, y).groupBy(key).applyInPandas(kernel, f"{key} {kind}, n long, weights array<double>, mse double")


def _frequencies(codes: np.ndarray, m: int, eta: float) -> np.ndarray:
    """Averaged frequency of each symbol just before it is coded, starting uniform, without a loop over symbols.

    Within a chunk short enough for eta^-length to stay small (differences of running sums keep their digits), the average is
    a scaled running sum.
    """
    n = len(codes)
    out = np.empty(n)
    step = max(16, min(1 << 16, int(14 / -math.log(eta)))) if eta < 1 else max(n, 1)
    state = np.full(m, 1.0 / m)
    for a in range(0, n, step):
        part = codes[a : a + step]
        decay = eta ** np.arange(len(part) + 1)
        order = np.argsort(part, kind="stable")
        ordered = part[order]
        gain = (1 - eta) / decay[1:][order]
        total = np.cumsum(gain)
        first = np.searchsorted(ordered, np.arange(m + 1))
        before = total - gain - np.concatenate([[0], total])[first[ordered]]
        out[a + order] = decay[:-1][order] * (state[ordered] + before)
        ends = np.concatenate([[0], total])
        state = decay[len(part)] * (state + ends[first[1:]] - ends[first[:-1]])
    return out


def adaptive_bits(codes: np.ndarray, m: int, eta: float, floor: float = FLOOR) -> float:
    """Bits of a sequence under the order-0 adaptive model. A symbol long unseen keeps probability ``floor``."""
    return float(-np.log2((1 - m * floor) * _frequencies(codes, m, eta) + floor).sum())


def golden(cost, low: float, high: float, steps: int = 24) -> tuple[float, float]:
    """Least cost over an interval of lg half-lives by golden-section search."""
    ratio = (math.sqrt(5) - 1) / 2
    a, b = low, high
    x, y = b - ratio * (b - a), a + ratio * (b - a)
    fx, fy = cost(x), cost(y)
    for _ in range(steps):
        if fx <= fy:
            b, y, fy = y, x, fx
            x = b - ratio * (b - a)
            fx = cost(x)
        else:
            a, x, fx = x, y, fy
            y = a + ratio * (b - a)
            fy = cost(y)
    return (x, fx) if fx <= fy else (y, fy)


def fit_eta(blocks: DataFrame, m: int, grid: list[float] | None = None) -> DataFrame:
    """block_no, n, eta, half_life, bpv of the forgetting rate that codes each block best. ``blocks``: block_no, syms.

    Blocks are independent; each is searched in one task, over a grid or by golden section over half-lives from 2 to 2^16.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, no in enumerate(batch.column(0).to_pylist()):
                codes = batch.column(1)[i].values.to_numpy().astype(np.int64)
                if grid:
                    bits, eta = min((round(adaptive_bits(codes, m, e), 6), e) for e in grid)
                else:
                    lg, bits = golden(lambda x: adaptive_bits(codes, m, 2 ** (-1 / 2**x)), 1, 16)
                    eta = 2 ** (-1 / 2**lg)
                yield pa.RecordBatch.from_arrays([pa.array([no], pa.int64()), pa.array([len(codes)], pa.int64()), pa.array([eta]), pa.array([-1 / math.log2(eta)]), pa.array([bits / max(len(codes), 1)])], names=["block_no", "n", "eta", "half_life", "bpv"])

    return blocks.select(F.col("block_no").cast("long"), "syms").mapInArrow(kernel, "block_no long, n long, eta double, half_life double, bpv double")


def long_blocks(stream: Stream, block: int, order: str = "doc_id", bucket: int = 4096, tail: str = "drop", digits: bool = False) -> DataFrame:
    """block_no, syms: the rows' sequences end to end in order of an integer column, cut into blocks (a short last one is dropped or kept).
    ``digits`` as in :meth:`Stream.frame`.

    Offsets come from sums per bucket of the order column and a running sum inside each bucket, so no task orders all rows,
    and rows carry their symbols along: rows of one order value follow each other by their symbols, rows without one
    come first. Only a block's own symbols meet in one task.
    """
    frame = stream.frame(digits).select(F.col(order).cast("long").alias("o"), "read_no", "syms")
    size, part = (F.length, F.substring) if digits else (F.size, F.slice)
    frame = frame.withColumn("n", size("syms").cast("long")).withColumn("b", F.expr(f"o div {bucket}")).where("n > 0")
    before = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    base = frame.groupBy("b").agg(F.sum("n").alias("n")).select(F.col("b").alias("base_b"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("b").orderBy("o", "read_no", F.xxhash64("syms")).rowsBetween(Window.unboundedPreceding, -1)
    placed = frame.withColumn("inside", F.coalesce(F.sum("n").over(inside), F.lit(0))).join(base, F.col("b").eqNullSafe(F.col("base_b")))
    rows = placed.select("syms", (F.col("base") + F.col("inside")).alias("start"))
    first, last = F.expr(f"start div {block}"), F.expr(f"(start + {'length' if digits else 'size'}(syms) - 1) div {block}")
    split = rows.withColumn("block_no", F.explode(F.sequence(first, last)))
    begin = F.greatest(F.lit(0), F.col("block_no") * block - F.col("start"))
    end = F.least(size("syms").cast("long"), (F.col("block_no") + 1) * block - F.col("start"))
    cut = split.select("block_no", (F.col("start") + begin).alias("at"), part("syms", (begin + 1).cast("int"), (end - begin).cast("int")).alias("syms"))
    parts = F.transform(F.array_sort(F.collect_list(F.struct("at", "syms"))), lambda x: x["syms"])
    whole = cut.groupBy("block_no").agg((F.array_join(parts, "") if digits else F.flatten(parts)).alias("syms"))
    return whole if tail == "keep" else whole.where(size("syms") == block)


def step_target(m: int, symbol: int, bits: int = CDF_BITS) -> list[int]:
    """The distribution function of one symbol, with room for all others: every gap stays at least 1 under shifts."""
    top = 1 << bits
    return [j if j <= symbol else top - m + j for j in range(m + 1)]


def uniform_cdf(m: int, bits: int = CDF_BITS) -> list[int]:
    return [(j << bits) // m for j in range(m + 1)]


def cdf_shift(cdf: Column, target: Column, rate: int) -> Column:
    """cdf + (target - cdf) >> rate, element by element."""
    return F.zip_with(cdf, target, lambda c, t: c + F.shiftright(t - c, rate))


def cdf_after(syms: Column, m: int, rate: int, bits: int = CDF_BITS) -> Column:
    """The distribution function after an array of symbols, as one Catalyst expression."""
    targets = F.lit([step_target(m, s, bits) for s in range(m)])
    return F.aggregate(syms, F.lit(uniform_cdf(m, bits)), lambda c, x: cdf_shift(c, F.get(targets, x), rate))


def cdf_bits(syms: Column, m: int, rate: int, bits: int = CDF_BITS) -> Column:
    """Bits of an array of symbols under the order-0 adaptive integer model (code first, update then)."""
    targets = F.lit([step_target(m, s, bits) for s in range(m)])
    start = F.struct(F.lit(uniform_cdf(m, bits)).alias("cdf"), F.lit(0.0).alias("bits"))

    def step(a: Column, x: Column) -> Column:
        gap = F.get(a["cdf"], x + 1) - F.get(a["cdf"], x)
        return F.struct(cdf_shift(a["cdf"], F.get(targets, x), rate).alias("cdf"), (a["bits"] + bits - F.log2(gap.cast("double"))).alias("bits"))

    return F.aggregate(syms, start, step, lambda a: a["bits"])


def _scan_four(codes: list[int], ctx: list[int], rate: int, bits: int) -> list[int]:
    """The loop of :func:`scan_cdfs` for four symbols, with the three inner values of each function written out."""
    targets = [step_target(4, s, bits) for s in range(4)]
    start, tables, gaps = uniform_cdf(4, bits), {}, []
    for c, x in zip(ctx, codes):
        t = tables.get(c)
        if t is None:
            t = tables[c] = list(start)
        gaps.append(t[x + 1] - t[x])
        _, a, b, d, _ = targets[x]
        t[1] += (a - t[1]) >> rate
        t[2] += (b - t[2]) >> rate
        t[3] += (d - t[3]) >> rate
    return gaps


def scan_cdfs(codes: np.ndarray, ctx: np.ndarray, m: int, rate: int, every: int = 1, bits: int = CDF_BITS, trace: int = 0) -> tuple[np.ndarray, list]:
    """Frequency of each symbol when it is coded, with one integer distribution function per context; and a trace of them.

    With ``every`` > 1 a context gathers that many of its symbols and then shifts towards their distribution function.
    """
    if m == 4 and every == 1 and not trace:
        return np.array(_scan_four(codes.tolist(), ctx.tolist(), rate, bits), np.int64), []
    targets = [step_target(m, s, bits) for s in range(m)]
    tables: dict[int, list[int]] = {}
    start = uniform_cdf(m, bits)
    gaps, seen = [], []
    trail: list[tuple[int, int, list[int]]] = []
    top = (1 << bits) - m
    for i, (c, x) in enumerate(zip(ctx.tolist(), codes.tolist())):
        table = tables.get(c)
        if table is None:
            table = start
        gaps.append(table[x + 1] - table[x])
        if every == 1:
            target = targets[x]
            tables[c] = [a + ((b - a) >> rate) for a, b in zip(table, target)]
        else:
            tables[c] = table
            seen = tables.setdefault(-1 - c, [])
            seen.append(x)
            if len(seen) == every:
                steps = [0] * (m + 1)
                for s in seen:
                    steps[s + 1] += 1
                total, target = 0, []
                for j, k in enumerate(steps):
                    total += k
                    target.append(j + top * total // every)
                tables[c] = [a + ((b - a) >> rate) for a, b in zip(table, target)]
                tables[-1 - c] = []
        if trace and i % trace == 0:
            trail.append((i, c, list(tables[c])))
    return np.array(gaps, np.int64), trail


def _run_lanes(sym: np.ndarray, begin: np.ndarray, length: np.ndarray, state: np.ndarray, targets: np.ndarray, rate: int, note: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Runs stretches of ``sym`` (begin, length) side by side from their states: gaps of each stretch end to end, states at the
    places ``note``, and last states. Stretches come longest first."""
    starts = np.concatenate([[0], np.cumsum(length)])
    gaps = np.empty(int(starts[-1]), np.int32)
    noted = state.copy()
    rows = np.arange(len(begin))
    ends = np.searchsorted(-length, -np.arange(int(length[0]) if len(length) else 0), "left")  # how many are still running
    notes: dict[int, np.ndarray] = {int(t): np.flatnonzero(note == t) for t in np.unique(note[note > 0])}
    for t, live in enumerate(ends.tolist()):
        if t in notes:
            noted[notes[t]] = state[notes[t]]
        x = sym[begin[:live] + t]
        now, on = state[:live], rows[:live]
        gaps[starts[:live] + t] = now[on, x + 1] - now[on, x]
        now += (targets[x] - now) >> rate
    return noted, state, [gaps[a:b] for a, b in zip(starts[:-1], starts[1:])]


def lane_gaps(codes: np.ndarray, ctx: np.ndarray, m: int, rate: int, bits: int = CDF_BITS, piece: int = 4096, halo: int = 6144) -> np.ndarray:
    """What :func:`scan_cdfs` gives for updates at every symbol, for all contexts at once.

    Contexts never interact, so each one's symbols are a stretch of their own, and all stretches advance side by side. Long
    ones are cut into pieces that begin ``halo`` symbols early: shifts bring functions from any start together. A piece whose
    function at its true begin is not the one its predecessor ended with is run again from that, so the result is exact.
    """
    if not len(codes):
        return np.zeros(0, np.int64)
    order = np.argsort(ctx, kind="stable")
    sym, ctx = codes[order].astype(np.int32), ctx[order]
    first = np.flatnonzero(np.concatenate([[True], ctx[1:] != ctx[:-1]]))
    size = np.diff(np.append(first, len(sym)))
    pieces_of = np.maximum(1, -(-size // piece))
    owner = np.repeat(np.arange(len(first)), pieces_of)
    nth = np.arange(len(owner)) - np.repeat(np.cumsum(pieces_of) - pieces_of, pieces_of)
    true_begin = nth * piece
    lead = np.minimum(true_begin, halo)
    length = np.minimum(size[owner] - true_begin, piece) + lead
    begin = first[owner] + true_begin - lead
    targets = np.array([step_target(m, s, bits) for s in range(m)], np.int32)
    uniform = np.array(uniform_cdf(m, bits), np.int32)
    by_length = np.argsort(-length, kind="stable")
    state = np.tile(uniform, (len(owner), 1))
    noted, last, parts = _run_lanes(sym, begin[by_length], length[by_length], state, targets, rate, lead[by_length])
    back = np.empty(len(owner), np.int64)
    back[by_length] = np.arange(len(owner))
    noted, last = noted[back], last[back]
    out = np.empty(len(sym), np.int64)
    for i in range(len(owner)):
        at = begin[i] + lead[i]
        if nth[i] and (noted[i] != last[i - 1]).any():
            n = np.array([length[i] - lead[i]])
            _, again, found = _run_lanes(sym, np.array([at]), n, last[i - 1 : i].copy(), targets, rate, np.zeros(1, np.int64))
            last[i], gaps = again[0], found[0]
        else:
            gaps = parts[back[i]][lead[i] :]
        out[at : at + len(gaps)] = gaps
    result = np.empty(len(sym), np.int64)
    result[order] = out
    return result


def adaptive_context_bits(stream: Stream, spec: Context, rate: int, every: int = 1) -> DataFrame:
    """ids, read_no, bits, n: every sequence coded by itself with adaptive functions per context, starting uniform."""
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    schema = schema_with(T.StructType([stream.df.schema[c] for c in ids]), "read_no int, bits double, n long")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            ctx, valid = spec.codes(f, m)
            if every == 1:  # the sequences' contexts side by side
                owner, span = f.owner()[valid], int(ctx.max(initial=0)) + 1
                cost = CDF_BITS - np.log2(lane_gaps(f.codes[valid], owner * span + ctx[valid], m, rate))
                bits, n = np.bincount(owner, cost, len(f.row)), np.bincount(owner, minlength=len(f.row))
            else:
                bits, n = [], []
                for a, b in zip(f.starts[:-1], f.starts[1:]):
                    use = valid[a:b]
                    gaps, _ = scan_cdfs(f.codes[a:b][use], ctx[a:b][use], m, rate, every)
                    bits.append(float(CDF_BITS * len(gaps) - np.log2(gaps).sum())), n.append(int(use.sum()))
            cols = [batch.column(c).take(pa.array(f.row)) for c in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), pa.array(bits, pa.float64()), pa.array(n, pa.int64())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)


def adaptive_vs_static(blocks: DataFrame, m: int, orders: list[int], rate: int = 8) -> DataFrame:
    """ord, n, adaptive and static bpv over the blocks: one pass gives bits and counts of all orders.

    Static is the best stationary model of the whole sequence; adaptive restarts in each block.
    """

    read = array_stream(None, "syms", m).flat

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):  # short blocks side by side, a long one by itself
            f = read(batch.column(0))
            owner = f.owner()
            for some in (orders[j : j + 3] for j in range(0, len(orders), 3)):  # and a few orders at a time
                lanes, syms, ctxs, base = [], [], [], 0
                for l in some:  # noqa: E741
                    ctx, valid = Previous(l).codes(f, m)
                    lanes.append(base + owner[valid] * m**l + ctx[valid])
                    base += len(f.size) * m**l
                    ctxs.append(ctx[valid]), syms.append(f.codes[valid])
                gaps = lane_gaps(np.concatenate(syms), np.concatenate(lanes), m, rate)
                ends = np.cumsum([0] + [len(c) for c in ctxs])
                for l, ctx, sym, a, b in zip(some, ctxs, syms, ends[:-1], ends[1:]):  # noqa: E741
                    key, n = np.unique(ctx * m + sym, return_counts=True)
                    bits = np.zeros(len(key))
                    bits[:1] = CDF_BITS * (b - a) - np.log2(gaps[a:b]).sum()
                    yield pa.RecordBatch.from_arrays([pa.array([l] * len(key), pa.int32()), pa.array(key // m), pa.array(key % m, pa.int32()), pa.array(n.astype(np.int64)), pa.array(bits)], names=["ord", "ctx", "sym", "n", "bits"])

    cells = blocks.select("syms").mapInArrow(kernel, "ord int, ctx long, sym int, n long, bits double")
    per = cells.groupBy("ord", "ctx", "sym").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"))
    x = lambda c: F.when(c > 0, c * F.log2(c)).otherwise(0.0)
    ctx = per.groupBy("ord", "ctx").agg(F.sum("n").alias("n"), F.sum(x(F.col("n"))).alias("g"), F.sum("bits").alias("bits"))
    n = F.sum("n")
    return ctx.groupBy("ord").agg(n.alias("n"), F.round(F.sum("bits") / n, 6).alias("adaptive"), F.round(F.sum(x(F.col("n")) - F.col("g")) / n, 6).alias("static"))


def cdf_trace(blocks: DataFrame, m: int, order: int, rate: int, every: int) -> DataFrame:
    """block_no, at, ctx, cdf: the functions along each block, sampled every so many symbols."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, no in enumerate(batch.column(0).to_pylist()):
                codes = batch.column(1)[i].values.to_numpy().astype(np.int64)
                f = Flat(codes, np.array([0, len(codes)]), np.zeros(1, np.int64), np.zeros(1, np.int64))
                ctx, valid = Previous(order).codes(f, m)
                _, trail = scan_cdfs(codes[valid], ctx[valid], m, rate, trace=every)
                at, c, cdf = zip(*trail) if trail else ((), (), ())
                yield pa.RecordBatch.from_arrays([pa.array([no] * len(at), pa.int64()), pa.array(at, pa.int64()), pa.array(c, pa.int64()), pa.array(list(cdf), pa.list_(pa.int32()))], names=["block_no", "at", "ctx", "cdf"])

    return blocks.select(F.col("block_no").cast("long"), "syms").mapInArrow(kernel, "block_no long, at long, ctx long, cdf array<int>")


def adaptive_prior(model: Model, bits: int = CDF_BITS) -> list[list[int]]:
    """Starting functions from a trained model instead of uniform ones: every gap at least 1, ending at 2^bits."""
    p = 2.0 ** -model.bits
    gaps = np.maximum(1, np.floor(p * ((1 << bits) - model.m)).astype(int))
    out = np.concatenate([np.zeros((len(gaps), 1), int), np.cumsum(gaps, axis=1)], axis=1)
    out[:, -1] = 1 << bits
    return out.tolist()
