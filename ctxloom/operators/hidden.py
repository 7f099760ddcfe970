"""Hidden-state context models: one transition table replaces several lookups.

A machine is an int matrix (states, symbols). Each symbol is coded under the current state; then the state moves. Machines come
from chained bins of a window of previous values, from counters, from products of both, or from :mod:`soft`.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxloom.operators import counts as C
from ctxloom.operators import merge as M
from ctxloom.operators import rates as R
from ctxloom.operators.contexts import Lag, Product
from ctxloom.operators.stream import Flat, Stream, pieces


#: Longer sequences are cut into pieces of so many symbols that run side by side.
PIECE = 2048
#: Machines of at most so many states are run from all of them where they never forget where they began.
MAP_STATES = 64
#: The starts of at most so many chunks are sent to the chunks; of more, both are joined by a shuffle.
FEW_CHUNKS = 1 << 20


@functools.lru_cache(maxsize=64)
def _memory(data: bytes, states: int, most: int) -> int | None:
    table = np.frombuffer(data, np.int64).reshape(states, -1)
    apart = ~np.eye(states, dtype=bool)  # pairs of states that some word of this length keeps apart
    for depth in range(most + 1):
        if not apart.any():
            return depth
        a, b = np.nonzero(apart)
        now = np.zeros_like(apart)
        for x in range(table.shape[1]):
            now[table[a, x], table[b, x]] = True
        np.fill_diagonal(now, False)
        if (now == apart).all():
            return None
        apart = now
    return None


def memory(table: np.ndarray, most: int = 256) -> int | None:
    """After how many symbols the state no longer depends on where the machine began; None if it may always do (counters)."""
    table = np.ascontiguousarray(table, np.int64)
    return _memory(table.tobytes(), len(table), most) if len(table) <= 2048 else None


def _in_step(codes: np.ndarray, begin: np.ndarray, size: np.ndarray, state: np.ndarray, table: np.ndarray, out: np.ndarray | None, lead: np.ndarray | None = None) -> np.ndarray:
    """Runs stretches side by side, place by place, the longest first. States are written to ``out`` from place ``lead`` on;
    the states after the last symbols are returned. ``state`` is one start a stretch, or one row of starts a stretch."""
    order = np.argsort(-size, kind="stable")
    size, begin, state = size[order], begin[order], state[order].copy()
    lead = np.zeros(len(order), np.int64) if lead is None else lead[order]
    ends = np.searchsorted(-size, -np.arange(int(size[0]) if len(size) else 0), "left")
    first = int(lead.max(initial=0))
    for t, live in enumerate(ends.tolist()):
        at = begin[:live] + t
        if out is not None:
            if t < first:
                shown = lead[:live] <= t
                out[at[shown]] = state[:live][shown]
            else:
                out[at] = state[:live]
        x = codes[at]
        state[:live] = table[state[:live], x] if state.ndim == 1 else table[state[:live], x[:, None]]
    back = np.empty_like(state)
    back[order] = state
    return back


def _cut_pieces(f: Flat) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Owner, number, begin and length of the pieces of all sequences."""
    n = np.maximum(1, -(-f.size // PIECE))
    owner = np.repeat(np.arange(len(n)), n)
    nth = np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)
    return owner, nth, f.starts[:-1][owner] + nth * PIECE, np.minimum(f.size[owner] - nth * PIECE, PIECE)


def sequence_maps(f: Flat, table: np.ndarray) -> np.ndarray:
    """(sequences, states): the state behind each sequence by the state before it."""
    owner, nth, at, length = _cut_pieces(f)
    maps = _in_step(f.codes, at, length, np.tile(np.arange(len(table)), (len(owner), 1)), table, None)
    out = np.tile(np.arange(len(table)), (len(f.size), 1))
    for k in range(int(nth.max(initial=-1)) + 1):
        own = np.flatnonzero(nth == k)
        out[owner[own]] = np.take_along_axis(maps[own], out[owner[own]], axis=1)
    return out


def run_machine(f: Flat, table: np.ndarray, start: int | np.ndarray = 0) -> np.ndarray:
    """State under which each symbol is coded. All sequences advance together, place by place; ``start`` may be one a sequence.

    Long sequences are cut into pieces, so that the longest one does not set the pace: of a machine that forgets after d
    symbols a piece begins d symbols early; of another with few states all pieces are mapped from every state first, and
    the maps, composed in order, tell where each piece begins.
    """
    table = np.ascontiguousarray(table, np.int64)
    out = np.zeros(len(f.codes), np.int64)
    size, begin = f.size, f.starts[:-1]
    start = np.full(len(size), start, np.int64)
    if int(size.max(initial=0)) <= 2 * PIECE:
        _in_step(f.codes, begin, size, start, table, out)
        return out
    halo = memory(table)
    if halo is None and len(table) > MAP_STATES:
        _in_step(f.codes, begin, size, start, table, out)
        return out
    owner, nth, at, length = _cut_pieces(f)
    if halo is not None:
        lead = np.minimum(nth * PIECE, halo)
        _in_step(f.codes, at - lead, length + lead, start[owner], table, out, lead)
        return out
    maps = _in_step(f.codes, at, length, np.tile(np.arange(len(table)), (len(owner), 1)), table, None)
    starts = start[owner]
    for i in np.flatnonzero(nth > 0):
        starts[i] = maps[i - 1, starts[i - 1]]
    _in_step(f.codes, at, length, starts, table, out)
    return out


@dataclass(frozen=True)
class State:
    """The machine's state as a context. ``skip`` leaves out the first places of a sequence, while a window fills up."""

    table: tuple
    start: int = 0
    skip: int = 0
    feed: tuple[int, int] | None = None  # (width, cap): the coarse position is put into the symbols that move the state

    def size(self, m: int) -> int:
        return len(self.table)

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        moved = position_symbols(f, m, *self.feed) if self.feed else f
        return run_machine(moved, np.asarray(self.table, np.int64), self.start), f.position() >= self.skip


def machine(table: np.ndarray, start: int = 0, skip: int = 0, feed: tuple[int, int] | None = None) -> State:
    return State(tuple(map(tuple, np.asarray(table).tolist())), start, skip, feed)


def run_states(syms: Column, table: np.ndarray, start: int = 0) -> Column:
    """The states as an array column, as one Catalyst fold (for short arrays)."""
    flat = F.lit([int(x) for x in np.asarray(table).ravel()])
    m = np.asarray(table).shape[1]
    init = F.struct(F.lit(start).alias("s"), F.array().cast("array<int>").alias("trail"))
    step = lambda a, x: F.struct(F.get(flat, a["s"] * m + x).alias("s"), F.array_append(a["trail"], a["s"]).alias("trail"))
    return F.aggregate(syms, init, step, lambda a: a["trail"])


def count_states(stream: Stream, table: np.ndarray, start: int = 0, skip: int = 0, extra=None) -> DataFrame:
    """Counts by state, or by (state, another context)."""
    spec = machine(table, start, skip)
    return C.count_windows(stream, Product((spec, extra)) if extra is not None else spec)


def _chunk_starts(chunks: DataFrame, seq: str, chunk_no: str, syms: str, table: np.ndarray, start: int) -> DataFrame:
    """seq, chunk_no, syms, lead (symbols to run through first), start. Only ends or maps of chunks meet in a sequence's task."""
    rows = chunks.select(F.col(seq).alias("seq"), F.col(chunk_no).cast("long").alias("chunk_no"), F.col(syms).alias("syms"))
    kind, digits = rows.schema["seq"].dataType.simpleString(), _kind(rows) == "digits"
    size, none = (F.length, F.lit("")) if digits else (F.size, F.array().cast("array<int>"))

    few = rows.count() <= FEW_CHUNKS

    def met(begins: DataFrame) -> DataFrame:
        named = begins.withColumnsRenamed({"seq": "_seq", "chunk_no": "_no"})
        named = F.broadcast(named) if few else named
        return rows.join(named, rows["seq"].eqNullSafe(named["_seq"]) & rows["chunk_no"].eqNullSafe(named["_no"])).select("seq", "chunk_no", "syms", "lead", "start")

    halo, order = memory(table), Window.partitionBy("seq").orderBy("chunk_no")
    if halo is not None:
        # as many earlier chunks' ends as a window of ``halo`` symbols may need: one, where chunks are at least that long
        sizes = rows.select("seq", "chunk_no", size("syms").alias("n"))
        shortest = sizes.withColumn("last", F.lead("chunk_no").over(order).isNull()).where("not last").agg(F.min("n")).first()[0]
        if shortest is None or shortest >= halo:
            begin = F.greatest(F.lit(1), size("syms") - halo + 1)
            end = none if not halo else F.substring("syms", begin, F.lit(halo)) if digits else F.slice("syms", begin, F.lit(halo))
            ends = rows.select("seq", "chunk_no", end.alias("end"))
            return met(ends.select("seq", "chunk_no", F.coalesce(F.lag("end").over(order), none).alias("lead"), F.lit(start).alias("start")))
    if len(table) > C.BROADCAST_CELLS >> 12:
        raise ValueError("too many states to map every chunk from all of them")
    read = Stream(None, "syms", table.shape[1], _kind(rows)).flat

    def to_maps(batches):
        for batch in pieces(batches):
            maps = sequence_maps(read(batch.column(2)), table)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.ListArray.from_arrays(pa.array(np.arange(0, maps.size + 1, len(table)), pa.int32()), pa.array(maps.ravel().astype(np.int32)))], names=["seq", "chunk_no", "map"])

    def compose(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("chunk_no")
        state, starts = start, []
        for one in pdf["map"]:
            starts.append(state)
            state = int(one[state])
        return pd.DataFrame({"seq": pdf["seq"], "chunk_no": pdf["chunk_no"], "start": starts})

    begins = rows.mapInArrow(to_maps, f"seq {kind}, chunk_no long, map array<int>").groupBy("seq").applyInPandas(compose, f"seq {kind}, chunk_no long, start int")
    return met(begins.select("seq", "chunk_no", none.alias("lead"), "start"))


def _kind(rows: DataFrame) -> str:
    return "digits" if rows.schema["syms"].dataType.simpleString() == "string" else "array"


def _states_of(batch: pa.RecordBatch, read, table: np.ndarray) -> tuple[Flat, np.ndarray]:
    f, g = read(batch.column(2)), read(batch.column(3))
    warm = _in_step(g.codes, g.starts[:-1], g.size, batch.column(4).to_numpy().astype(np.int64), table, None)
    return f, run_machine(f, table, warm)


def run_chunks(chunks: DataFrame, seq: str, chunk_no: str, syms: str, table: np.ndarray, start: int = 0) -> DataFrame:
    """seq, chunk_no, syms, states for long sequences that lie in several rows, chunk after chunk. Null keys are keys.

    A machine that forgets gets the end of the chunk before as a halo: only those few symbols move, by one window per
    sequence. For another machine each chunk's map of all states goes to its sequence's group, which composes them in order
    and returns a start a chunk; chunks then run from their true starts. Chunks shorter than the halo use maps, too.
    Symbols are arrays or strings of digits (:meth:`Stream.frame`).
    """
    table = np.ascontiguousarray(table, np.int64)
    rows = _chunk_starts(chunks, seq, chunk_no, syms, table, start)
    kind, read = rows.schema["seq"].dataType.simpleString(), Stream(None, "syms", table.shape[1], _kind(rows)).flat

    def kernel(batches):
        for batch in pieces(batches):
            f, out = _states_of(batch, read, table)
            states = pa.ListArray.from_arrays(pa.array(f.starts, pa.int32()), pa.array(out.astype(np.int32)))
            syms = pa.ListArray.from_arrays(pa.array(f.starts, pa.int32()), pa.array(f.codes.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), syms, states], names=["seq", "chunk_no", "syms", "states"])

    return rows.mapInArrow(kernel, f"seq {kind}, chunk_no long, syms array<int>, states array<int>")


def count_chunks(chunks: DataFrame, seq: str, chunk_no: str, syms: str, table: np.ndarray, start: int = 0, skip: int = 0) -> DataFrame:
    """ctx (state), sym, n over :func:`run_chunks`, counted where the symbols are; the first ``skip`` places of chunks 0 do not count."""
    table = np.ascontiguousarray(table, np.int64)
    rows, m = _chunk_starts(chunks, seq, chunk_no, syms, table, start), table.shape[1]
    read = Stream(None, "syms", m, _kind(rows)).flat

    def kernel(batches):
        total = np.zeros(table.size, np.int64)
        for batch in pieces(batches):
            f, out = _states_of(batch, read, table)
            cell = out * m + f.codes
            total += np.bincount(cell, minlength=table.size)
            for i in np.flatnonzero(batch.column(1).to_numpy(zero_copy_only=False) == 0):
                total -= np.bincount(cell[f.starts[i] : min(f.starts[i] + skip, f.starts[i + 1])], minlength=table.size)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at // m), pa.array(at % m, pa.int32()), pa.array(total[at])], names=["ctx", "sym", "n"])

    return rows.mapInArrow(kernel, "ctx long, sym int, n long").groupBy("ctx", "sym").agg(F.sum("n").alias("n"))


def rate_states(run: DataFrame, skip: int = 0, head: str = "chunk_no = 0") -> DataFrame:
    """n, contexts, bpv of symbols under the states of :func:`run_chunks`; the first ``skip`` places of the head chunks do not count."""
    cells = run.select(F.expr(head).alias("head"), F.posexplode(F.arrays_zip(F.col("states").alias("ctx"), F.col("syms").alias("sym"))).alias("at", "c"))
    cells = cells.where((F.col("at") >= skip) | ~F.col("head"))
    return R.rate(cells.groupBy(F.col("c.ctx").cast("long").alias("ctx"), F.col("c.sym").alias("sym")).agg(F.count("*").alias("n")))


def counter_transition(m: int, cap: int) -> np.ndarray:
    """Counts value changes up to cap - 1; a state is (count, last value)."""
    count, last, x = np.meshgrid(np.arange(cap), np.arange(m), np.arange(m), indexing="ij")
    return (np.minimum(count + (last != x), cap - 1) * m + x).reshape(cap * m, m)


def run_length_transition(m: int, cap: int) -> np.ndarray:
    """Length of the current run up to cap - 1, with its value."""
    count, last, x = np.meshgrid(np.arange(cap), np.arange(m), np.arange(m), indexing="ij")
    return (np.where(last == x, np.minimum(count + 1, cap - 1), 0) * m + x).reshape(cap * m, m)


def position_symbols(f: Flat, m: int, width: int, cap: int) -> Flat:
    """Position fed through the symbol: code + m * coarse position."""
    return Flat(f.codes + m * np.minimum(f.position() // width, cap - 1), f.starts, f.row, f.nth)


def product_transition(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Both machines side by side: state = sa + |a| * sb."""
    sb, sa = np.divmod(np.arange(len(a) * len(b)), len(a))
    return a[sa] + len(a) * b[sb]


@dataclass
class Chain:
    """Bins for the value at each distance; level j + 1 bins the bins of level j, so a window of bins can be shifted."""

    m: int
    first: np.ndarray  # value -> bin
    reduce: list[np.ndarray]  # bin of level j -> bin of level j + 1
    sizes: list[int]

    @property
    def depth(self) -> int:
        return len(self.sizes)

    def level_table(self, level: int) -> np.ndarray:
        """Value -> its bin at a level."""
        out = self.first
        for r in self.reduce[:level]:
            out = r[out]
        return out

    def radices(self, pow2: bool = False) -> list[int]:
        return [1 << max(0, (n - 1).bit_length()) for n in self.sizes] if pow2 else list(self.sizes)


def lag_tables(stream: Stream, depth: int) -> list[np.ndarray]:
    """(m, m) counts of (value at distance j, symbol) for j = 1 .. depth, from one scan."""
    out = [np.zeros((stream.m, stream.m), np.int64) for _ in range(depth)]
    for r in C.count_many(stream, [Lag(j) for j in range(1, depth + 1)]).toLocalIterator():
        out[r.spec][r.ctx, r.sym] = r.n
    return out


def bin_chain(stream: Stream, sizes: list[int], mode: str = "levels", lags: list[np.ndarray] | None = None) -> Chain:
    """Level 1 bins the previous value; level j bins level j - 1's bins by how the value at distance j predicts.

    ``one_tree`` cuts a single tree at all sizes instead: cuts of one tree are nested. ``lags`` may hold the counts already.
    """
    m = stream.m
    lags = lags or lag_tables(stream, 1 if mode == "one_tree" else len(sizes))
    if mode == "one_tree":
        cuts = M.cut_many(M.tree_of(np.arange(m), lags[0]), [M.MaxBins(s) for s in sizes])
        reduce = [np.array([int(b[a == i][0]) for i in range(int(a.max()) + 1)]) for a, b in zip(cuts, cuts[1:])]
        return Chain(m, cuts[0], reduce, [int(c.max()) + 1 for c in cuts])
    chain: Chain | None = None
    for size, table in zip(sizes, lags):
        if chain is not None:
            summed = np.zeros((chain.sizes[-1], m), np.int64)
            np.add.at(summed, chain.level_table(chain.depth - 1), table)
            table = summed
        bins = M.cut(M.tree_of(np.arange(len(table)), table), M.MaxBins(size)) if size < len(table) else np.arange(len(table))
        n = int(bins.max()) + 1
        chain = Chain(m, bins, [], [n]) if chain is None else Chain(m, chain.first, [*chain.reduce, bins], [*chain.sizes, n])
    return chain


def pack(bins: list[Column], radices: list[int]) -> Column:
    out, base = F.lit(0), 1
    for b, r in zip(bins, radices):
        out, base = out + b * base, base * r
    return out


def unpack(state: Column, radices: list[int]) -> list[Column]:
    out, base = [], 1
    for r in radices:
        out.append((F.floor(state / base) % r).cast("int"))
        base *= r
    return out


def pack_codes(bins: np.ndarray, radices: list[int]) -> np.ndarray:
    return bins @ np.cumprod([1, *radices[:-1]])


def unpack_codes(state: np.ndarray, radices: list[int]) -> np.ndarray:
    return np.stack([(state // b) % r for b, r in zip(np.cumprod([1, *radices[:-1]]), radices)], axis=-1)


def chain_transition(chain: Chain, pow2: bool = False) -> np.ndarray:
    """All (state, value): unpack, move every bin one place back through its own reduction, put the new value's bin first, pack."""
    radices = chain.radices(pow2)
    states = int(np.prod(radices))
    window = unpack_codes(np.arange(states), radices)
    # bins beyond a level's count (only with power-of-two radices) are never reached; they map to bin 0
    moved = [r[np.where(window[:, j] < len(r), window[:, j], 0)] for j, r in enumerate(chain.reduce)]
    out = np.empty((states, chain.m), np.int64)
    for x in range(chain.m):
        out[:, x] = pack_codes(np.stack([np.full(states, chain.first[x]), *moved], axis=-1), radices)
    return out


def transition_frame(spark: SparkSession, table: np.ndarray) -> DataFrame:
    state, sym = np.divmod(np.arange(table.size), table.shape[1])
    return spark.createDataFrame(pa.table({"state": pa.array(state, pa.int32()), "sym": pa.array(sym, pa.int32()), "next_state": pa.array(table.ravel(), pa.int32())}))


def search_machines(stream: Stream, candidates: dict[str, np.ndarray], skip: int = 0) -> DataFrame:
    """machine, states, n, bpv of every candidate, from one pass that counts them all."""
    m, flat = stream.m, stream.flat
    tables = {k: np.asarray(v, np.int64) for k, v in candidates.items()}

    def kernel(batches):
        total = {k: np.zeros(t.size, np.int64) for k, t in tables.items()}
        for batch in pieces(batches):
            f = flat(batch.column(0))
            use = f.position() >= skip
            for k, t in tables.items():
                total[k] += np.bincount((run_machine(f, t) * m + f.codes)[use], minlength=t.size)
        for k, n in total.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([k] * len(at), pa.string()), pa.array(at // m), pa.array(at % m, pa.int32()), pa.array(n[at])], names=["machine", "ctx", "sym", "n"])

    counted = stream.select().mapInArrow(kernel, "machine string, ctx long, sym int, n long").groupBy("machine", "ctx", "sym").agg(F.sum("n").alias("n"))
    return R.rate(counted, "machine").withColumnRenamed("contexts", "states")
