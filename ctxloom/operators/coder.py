"""An entropy coder: range ANS per read under any model, to show that the measured bits can be reached and undone.

Frequencies are integers with a power-of-two sum and no zeros. Reads are coded each by itself, so a container can be
written and read in parallel.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.operators.contexts import Context
from ctxloom.operators.stream import SLICE_SYMBOLS, Flat, Stream, pieces, syms_array, syms_type
from ctxloom.session import schema_with

TOTAL_BITS = 14
_LOW = 1 << 23


def quantize_freqs(p: np.ndarray, bits: int = TOTAL_BITS) -> np.ndarray:
    """Integer frequencies (rows sum to 2^bits, all at least 1): floors first, the rest to the largest remainders."""
    p = np.atleast_2d(np.asarray(p, float))
    p = p / p.sum(axis=1, keepdims=True)
    room = (1 << bits) - p.shape[1]
    want = p * room
    out = np.floor(want).astype(np.int64)
    rest = room - out.sum(axis=1)
    order = np.argsort(-(want - out), axis=1, kind="stable")
    for i, k in enumerate(rest):
        out[i, order[i, :k]] += 1
    return out + 1


def quantization_loss(p: np.ndarray, weights: np.ndarray, bits: int = TOTAL_BITS) -> float:
    """Extra bits a value of the integer frequencies against the ideal, rows weighed by ``weights``."""
    p = np.atleast_2d(p)
    q = quantize_freqs(p, bits) / (1 << bits)
    with np.errstate(divide="ignore", invalid="ignore"):
        d = np.where(p > 0, p * np.log2(p / q), 0).sum(axis=1)
    return float((d * weights).sum() / max(weights.sum(), 1e-300))


def encode_read(cells: list[tuple[int, int]], bits: int = TOTAL_BITS) -> bytes:
    """(start, frequency) of each symbol in order -> bytes. Symbols are pushed last first."""
    state, out = _LOW, bytearray()
    for start, freq in reversed(cells):
        limit = ((_LOW >> bits) << 8) * freq
        while state >= limit:
            out.append(state & 0xFF)
            state >>= 8
        state = ((state // freq) << bits) + state % freq + start
    out += state.to_bytes(4, "little")
    return bytes(out[::-1])


class Decoder:
    def __init__(self, data: bytes):
        self.state, self.data, self.at = int.from_bytes(data[:4], "big"), data, 4

    def slot(self, bits: int) -> int:
        return self.state & ((1 << bits) - 1)

    def advance(self, start: int, freq: int, bits: int) -> None:
        self.state = freq * (self.state >> bits) + self.slot(bits) - start
        while self.state < _LOW and self.at < len(self.data):
            self.state = self.state << 8 | self.data[self.at]
            self.at += 1


def encode_reads(start: np.ndarray, freq: np.ndarray, offsets: np.ndarray, bits: int = TOTAL_BITS) -> pa.Array:
    """What :func:`encode_read` makes of each of many reads, given end to end. All reads advance together, the longest first."""
    start, freq, size = start.astype(np.uint32), freq.astype(np.uint32), np.diff(offsets)
    order = np.argsort(-size, kind="stable")
    last = offsets[1:][order] - 1
    # a symbol gives two bytes at most, and a read's bytes are written from its end
    room = np.concatenate([[0], np.cumsum(2 * size[order] + 4)])
    out, at, state = np.empty(room[-1], np.uint8), room[1:].copy(), np.full(len(order), _LOW, np.uint32)
    shift, mask = np.uint32((_LOW >> bits << 8).bit_length() - 1), np.uint32(0xFF)
    for t, live in enumerate(_live(size[order])):
        f, s, x = freq[last[:live] - t], start[last[:live] - t], state[:live]
        limit = f << shift
        full = np.flatnonzero(x >= limit)
        while len(full):
            at[full] -= 1
            out[at[full]] = x[full] & mask
            x[full] >>= np.uint32(8)
            full = full[x[full] >= limit[full]]
        q = x // f
        state[:live] = (q << np.uint32(bits)) + (x - q * f) + s
    for k in range(4):
        at -= 1
        out[at] = state >> np.uint32(8 * k) & mask
    back = np.empty_like(order)
    back[order] = np.arange(len(order))
    length, at = (room[1:] - at)[back], at[back]
    ends = np.concatenate([[0], np.cumsum(length)])
    data = out[np.repeat(at - ends[:-1], length) + np.arange(ends[-1])]
    return pa.Array.from_buffers(pa.binary(), len(order), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(data)])


def decode_reads(payload: pa.Array, model: np.ndarray, n: np.ndarray, order: int, m: int, freqs: np.ndarray, starts: np.ndarray, bits: int = TOTAL_BITS) -> np.ndarray:
    """Symbols (int32, end to end) of reads of ``n`` symbols, coded under models with Previous(order, 'pad') contexts."""
    payload = payload.cast(pa.large_binary())
    ends = np.frombuffer(payload.buffers()[1], np.int64)[payload.offset : payload.offset + len(payload) + 1]
    data = np.frombuffer(payload.buffers()[2] or b"", np.uint8)
    contexts, begin, by_size = (m + 1) ** order, np.cumsum(n) - n, np.argsort(-n, kind="stable")
    at, end, begin, row = ends[:-1][by_size], ends[1:][by_size], begin[by_size], model[by_size] * contexts
    out, ctx, state = np.empty(int(n.sum()), np.int32), np.full(len(n), contexts - 1), np.zeros(len(n), np.int64)
    for _ in range(4):
        state, at = state << 8 | data[at], at + 1
    # a symbol is found by halving; places beyond the last symbol begin beyond every slot
    width = 1 << (m - 1).bit_length()
    table = np.full((starts.shape[0] * contexts, width), 1 << bits, np.int64)
    table[:, :m] = starts[..., :-1].reshape(-1, m)
    table, freq = table.ravel(), freqs.reshape(-1)
    for t, live in enumerate(_live(n[by_size])):
        cell, s = row[:live] + ctx[:live], state[:live]
        slot, x, step = s & ((1 << bits) - 1), np.zeros(live, np.int64), width >> 1
        while step:
            x += step * (table[cell * width + x + step] <= slot)
            step >>= 1
        s = freq[cell * m + x] * (s >> bits) + slot - table[cell * width + x]
        short = np.flatnonzero((s < _LOW) & (at[:live] < end[:live]))
        while len(short):
            s[short] = s[short] << 8 | data[at[short]]
            at[short] += 1
            short = short[(s[short] < _LOW) & (at[short] < end[short])]
        state[:live] = s
        out[begin[:live] + t] = x
        if order:
            ctx[:live] = ctx[:live] * (m + 1) % contexts + x
    return out


def _live(size: np.ndarray) -> list[int]:
    """How many reads, sorted from the longest, have a symbol at each place."""
    return np.searchsorted(-size, -np.arange(int(size[0]) if len(size) else 0), "left").tolist()


def _one(codes: list[int]) -> Flat:
    return Flat(np.array(codes, np.int64), np.array([0, len(codes)]), np.zeros(1, np.int64), np.zeros(1, np.int64))


def _id_schema(stream: Stream) -> T.StructType:
    return T.StructType([stream.df.schema[c] for c in stream.ids])


def encode(stream: Stream, spec: Context, bits: np.ndarray, model_of: DataFrame | None = None) -> DataFrame:
    """ids, read_no, model_id, n, payload. ``bits`` is (k, contexts, m); the cheapest model codes the read.

    The context must say something about every symbol (head 'pad' or 'backoff', position, state ...).
    """
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    freqs = np.stack([quantize_freqs(2.0**-b) for b in bits])
    starts = np.concatenate([np.zeros((*freqs.shape[:2], 1), np.int64), np.cumsum(freqs, axis=2)], axis=2)
    ideal, first = TOTAL_BITS - np.log2(freqs), starts[..., :-1].ravel()
    schema = schema_with(_id_schema(stream), "read_no int, model_id int, n int, payload binary")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            ctx, valid = spec.codes(f, m)
            if not valid.all():
                raise ValueError("this context leaves symbols without a distribution")
            owner, cell = f.owner(), ctx * m + f.codes
            cost = np.stack([np.bincount(owner, table[cell], len(f.row)) for table in ideal.reshape(len(bits), -1)], axis=1)
            chosen = np.round(cost, 9).argmin(axis=1)
            cell += (chosen * freqs[0].size)[owner]
            data = encode_reads(first[cell], freqs.ravel()[cell], f.starts)
            cols = [batch.column(k).take(pa.array(f.row)) for k in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), pa.array(chosen, pa.int32()), pa.array(f.size, pa.int32()), data], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)


def decode(container: DataFrame, ids: list[str], order: int, m: int, bits: np.ndarray, digits: bool = False) -> DataFrame:
    """ids, read_no, syms of a container coded with Previous(order, 'pad') contexts; ``digits`` as in :meth:`Stream.frame`."""
    freqs = np.stack([quantize_freqs(2.0**-b) for b in bits])
    starts = np.concatenate([np.zeros((*freqs.shape[:2], 1), np.int64), np.cumsum(freqs, axis=2)], axis=2)
    schema = schema_with(T.StructType([container.schema[c] for c in ids]), f"read_no int, syms {syms_type(m, digits)}")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, SLICE_SYMBOLS):
            model, n = (batch.column(c).to_numpy().astype(np.int64) for c in ("model_id", "n"))
            syms = decode_reads(batch.column("payload"), model, n, order, m, freqs, starts)
            back = syms_array(syms, np.concatenate([[0], np.cumsum(n)]), digits)
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in ids], batch.column("read_no"), back], names=schema.names)

    return container.select(*ids, "read_no", "model_id", "n", "payload").mapInArrow(kernel, schema)


def encode_adaptive(codes: list[int], ctx: list[int], m: int, rate: int) -> bytes:
    """One sequence under adaptive functions per context; the decoder repeats the same shifts."""
    from ctxloom.operators.adapt import CDF_BITS, step_target, uniform_cdf

    targets, tables, cells = [step_target(m, s) for s in range(m)], {}, []
    for c, x in zip(ctx, codes):
        table = tables.get(c) or uniform_cdf(m)
        cells.append((table[x], table[x + 1] - table[x]))
        tables[c] = [a + ((b - a) >> rate) for a, b in zip(table, targets[x])]
    return encode_read(cells, CDF_BITS)


def adaptive_round_trip(stream: Stream, spec: Context, order: int, rate: int) -> DataFrame:
    """ids, read_no, syms, payload_bits: every sequence coded by itself under adaptive functions of Previous(order, 'pad')
    contexts, and what the decoder makes of the bytes."""
    m, flat, ids = stream.m, stream.flat, list(stream.ids)
    schema = schema_with(_id_schema(stream), "read_no int, syms array<int>, payload_bits long")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            ctx, _ = spec.codes(f, m)
            back, bits = [], []
            for a, b in zip(f.starts[:-1].tolist(), f.starts[1:].tolist()):
                data = encode_adaptive(f.codes[a:b].tolist(), ctx[a:b].tolist(), m, rate)
                back.append(decode_adaptive(data, b - a, order, m, rate)), bits.append(8 * len(data))
            cols = [batch.column(k).take(pa.array(f.row)) for k in ids]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth, pa.int32()), pa.array(back, pa.list_(pa.int32())), pa.array(bits, pa.int64())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)


def decode_adaptive(data: bytes, n: int, order: int, m: int, rate: int) -> list[int]:
    from bisect import bisect_right

    from ctxloom.operators.adapt import CDF_BITS, step_target, uniform_cdf

    targets, tables, d = [step_target(m, s) for s in range(m)], {}, Decoder(data)
    past, out = [m] * order, []
    for _ in range(n):
        c = sum(v * (m + 1) ** k for k, v in enumerate(past))
        table = tables.get(c) or uniform_cdf(m)
        x = bisect_right(table, d.slot(CDF_BITS)) - 1
        d.advance(table[x], table[x + 1] - table[x], CDF_BITS)
        tables[c] = [a + ((b - a) >> rate) for a, b in zip(table, targets[x])]
        past = [x, *past[:-1]] if order else past
        out.append(x)
    return out


def write_container(coded: DataFrame, menu: DataFrame, path: str) -> None:
    """Payloads partitioned by model, and the menu of models beside them."""
    coded.write.mode("overwrite").partitionBy("model_id").parquet(f"{path}/reads")
    menu.write.mode("overwrite").parquet(f"{path}/menu")


def read_container(spark, path: str) -> tuple[DataFrame, DataFrame]:
    return spark.read.parquet(f"{path}/reads"), spark.read.parquet(f"{path}/menu")


def huffman_lengths(weights: list[float]) -> list[int]:
    """Whole-bit code lengths; a lone symbol has length 1, symbols without weight 0."""
    heap = [(w, i, (i,)) for i, w in enumerate(weights) if w > 0]
    length = [0] * len(weights)
    if len(heap) == 1:
        length[heap[0][1]] = 1
    heapq.heapify(heap)
    while len(heap) > 1:
        (a, i, left), (b, j, right) = heapq.heappop(heap), heapq.heappop(heap)
        for s in left + right:
            length[s] += 1
        heapq.heappush(heap, (a + b, min(i, j), left + right))
    return length


def prefix_rate(counts: DataFrame, m: int) -> DataFrame:
    """n, bpv with a prefix code per context, and bpv with fractional bits."""
    import pandas as pd

    def kernel(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        w = np.zeros(m)
        w[pdf["sym"]] = pdf["n"]
        used = w[w > 0]
        return pd.DataFrame({"n": [int(w.sum())], "prefix": [float((w * np.array(huffman_lengths(w.tolist()))).sum())], "ideal": [float((used * np.log2(used.sum() / used)).sum())]})

    per = counts.groupBy("ctx").applyInPandas(kernel, "n long, prefix double, ideal double")
    n = F.sum("n")
    return per.agg(n.alias("n"), F.round(F.sum("prefix") / n, 6).alias("prefix_bpv"), F.round(F.sum("ideal") / n + 0.0, 6).alias("ideal_bpv"))
