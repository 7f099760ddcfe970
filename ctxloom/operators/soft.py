"""Soft hidden-state machines and their hardening.

States are distributions; a symbol moves them by its row-stochastic matrix. The objective sums the state-weighted log
emission over all symbols (nats, negative). Parameters are softmax logits; some rows of the transitions may be fixed. A pass
over the reads returns objective and gradient sums (a few numbers per state, symbol and state), whatever the data.

Gradient: with lambda = 0 after the last symbol and lambda_i(r) = d(x_i, r) + sum_s T_x(r, s) lambda_{i+1}(s), the derivative
by T_x(r, s) is the sum over i with x_i = x of P_i(r) lambda_{i+1}(s), and by d(x, s) that of P_i(s).

Many passes over one stream run over words instead of symbols (:func:`sheets`): a word moves the states by one matrix and adds
an objective that is linear in them, so its occurrences are summed by word, and the gradients follow exactly from those sums.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxloom.operators.stream import Flat, Stream, pieces
from ctxloom.session import materialise


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def batch_gradient(f: Flat, T: np.ndarray, d: np.ndarray, start: np.ndarray) -> tuple[float, np.ndarray, np.ndarray, float]:
    """Objective, gradients by T (m, S, S) and d (m, S), and lg of the state-weighted mixture, summed over a batch.

    T: (m, S, S) transition probabilities; d: (m, S) log emissions. Reads advance together, the longest first.
    """
    order = np.argsort(-f.size, kind="stable")
    size, begin = f.size[order], f.starts[:-1][order]
    longest = int(size[0]) if len(size) else 0
    P = np.zeros((longest + 1, len(order), len(start)))
    P[0] = start
    lives = [int(np.searchsorted(-size, -t, "left")) for t in range(longest)]
    symbols, objective, mixed = [], 0.0, 0.0
    for t in range(longest):
        live = lives[t]
        x = f.codes[begin[:live] + t]
        symbols.append(x)
        here = P[t, :live]
        objective += float((here * d[x]).sum())
        mixed += float(np.log2((here * np.exp(d[x])).sum(axis=1)).sum())
        P[t + 1, :live] = np.einsum("ns,nst->nt", here, T[x])
    gT, gd = np.zeros_like(T), np.zeros_like(d)
    back = np.zeros((len(order), len(start)))
    for t in range(longest - 1, -1, -1):
        live, x = lives[t], symbols[t]
        here = P[t, :live]
        for s in np.unique(x):
            own = x == s
            gT[s] += here[own].T @ back[:live][own]
            gd[s] += here[own].sum(axis=0)
        back[:live] = d[x] + np.einsum("nst,nt->ns", T[x], back[:live])
    return objective, gT, gd, mixed


#: Words have as many symbols as keep the number of possible ones within this, and sheets hold so many reads.
WORDS, SHEET_READS = 1 << 16, 8192


@dataclass(frozen=True)
class Words:
    """The words that occur, with all their beginnings, as a tree: a node is a word without its last symbol, then that symbol."""

    node_of: np.ndarray  # number of a word -> node
    bounds: list[int]  # nodes of each length
    parent: np.ndarray  # -1: none
    last: np.ndarray

    @classmethod
    def of(cls, numbers: np.ndarray, m: int, length: int) -> Words:
        first = np.concatenate([[0], np.cumsum([m**k for k in range(1, length + 1)])])
        levels, own = [], np.zeros(0, np.int64)
        for k in range(length, 0, -1):  # a word's beginnings occur, too
            inside = numbers[(numbers >= first[k - 1]) & (numbers < first[k])] - first[k - 1]
            own = np.union1d(inside, own // m).astype(np.int64)
            levels.insert(0, own)
        bounds = np.cumsum([0, *map(len, levels)])
        node_of, parents = np.zeros(first[-1], np.int32), []
        for k, codes in enumerate(levels):
            node_of[first[k] + codes] = bounds[k] + np.arange(len(codes))
            parents.append(node_of[first[k - 1] + codes // m] if k else np.full(len(codes), -1))
        return cls(node_of, bounds.tolist(), np.concatenate(parents).astype(np.int64), np.concatenate(levels) % m)

    def tables(self, T: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Matrix (nodes, S, S) and objective by the state before it (nodes, S) of every word."""
        M, c = np.empty((len(self.last), *T.shape[1:])), np.empty((len(self.last), d.shape[1]))
        for k, (a, b) in enumerate(zip(self.bounds, self.bounds[1:])):
            x, u = self.last[a:b], self.parent[a:b]
            M[a:b] = T[x] if not k else M[u] @ T[x]
            c[a:b] = d[x] if not k else c[u] + (M[u] @ d[x][..., None])[..., 0]
        return M, c

    def gradients(self, A: np.ndarray, B: np.ndarray, M: np.ndarray, T: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Gradients by T and d from sums by word of P (nodes, S) and of P x lambda behind the word (nodes, S, S).

        From the longest down, an occurrence of a word is one of the word without its last symbol and one of that symbol.
        """
        gT, gd = np.zeros_like(T), np.zeros_like(d)
        for k in range(len(self.bounds) - 2, -1, -1):
            a, b = self.bounds[k], self.bounds[k + 1]
            x, u = self.last[a:b], self.parent[a:b]
            if k and b > a:
                at = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
                A[u[at]] += np.add.reduceat(A[a:b], at)
                B[u[at]] += np.add.reduceat(A[a:b, :, None] * d[x][:, None] + B[a:b] @ T[x].transpose(0, 2, 1), at)
            here, met = (A[a:b], B[a:b]) if not k else ((A[a:b, None] @ M[u])[:, 0], M[u].transpose(0, 2, 1) @ B[a:b])
            for s in range(len(T)):
                gd[s] += here[x == s].sum(axis=0)
                gT[s] += met[x == s].sum(axis=0)
        return gT, gd


@dataclass(frozen=True)
class Sheets:
    """A stream as words, place by place: a row holds how many reads have a word at each place, and the words' numbers."""

    df: DataFrame
    words: object  # broadcast of Words


def sheets(stream: Stream) -> Sheets:
    """Writes the stream's words once, for many passes."""
    m, flat, spark = stream.m, stream.flat, stream.df.sparkSession
    length = max(1, int(np.log(WORDS + 0.5) / np.log(max(m, 2))))
    first = np.concatenate([[0], np.cumsum([m**k for k in range(1, length + 1)])])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            n = -(-f.size // length)
            order = np.argsort(-n, kind="stable")
            for a in range(0, len(order), SHEET_READS):
                own = order[a : a + SHEET_READS]
                own = own[n[own] > 0]
                live = np.searchsorted(-n[own], -np.arange(int(n[own].max(initial=0))), "left")
                begin = np.concatenate([f.starts[own[:k]] + t * length for t, k in enumerate(live)] or [np.zeros(0, np.int64)])
                end = np.concatenate([np.minimum(f.starts[own[:k]] + (t + 1) * length, f.starts[own[:k] + 1]) for t, k in enumerate(live)] or [begin])
                number = np.zeros(len(begin), np.int64)
                for j in range(length):
                    has = np.flatnonzero(begin + j < end)
                    number[has] = number[has] * m + f.codes[begin[has] + j]
                number += first[end - begin - 1]
                yield pa.RecordBatch.from_arrays([pa.array([live.tolist()], pa.list_(pa.int32())), pa.array([number.astype(np.int32).tobytes()], pa.binary())], names=["live", "words"])

    rows = materialise(stream.select().mapInArrow(kernel, "live array<int>, words binary"), "sheets")

    def used(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(first[-1], bool)
        for batch in batches:
            for w in batch.column(0):
                seen[np.frombuffer(w.as_buffer(), np.int32)] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(seen))], names=["number"])

    numbers = rows.select("words").mapInArrow(used, "number long").distinct().toArrow().column("number").to_numpy()
    return Sheets(rows, spark.sparkContext.broadcast(Words.of(np.sort(numbers), m, length)))


class Sweep:
    """Sums by word over sheets, one pass each. As P sums to 1 and gradients by logits do not change when lambda moves by a constant,
    P of the last state and lambda of the first one (taken as 0) are not carried."""

    def __init__(self, words: Words, T: np.ndarray, d: np.ndarray, start: np.ndarray):
        self.words, self.T, self.d, self.start = words, T, d, start
        self.M, self.c = words.tables(T, d)
        S = len(start)
        soa = lambda x: np.ascontiguousarray(x.reshape(len(x), -1).T)
        self.ahead, self.ahead0 = soa(self.M[:, :-1, :-1] - self.M[:, -1:, :-1]), soa(self.M[:, -1, :-1])
        self.back, self.back0 = soa(self.M[:, 1:, 1:] - self.M[:, :1, 1:]), soa(self.c[:, 1:] - self.c[:, :1])
        self.A, self.B = np.zeros((len(self.M), S)), np.zeros((len(self.M), S, S))

    def add(self, live: np.ndarray, numbers: np.ndarray, gradient: bool) -> None:
        w, S, nodes = self.words.node_of[numbers].astype(np.int64), len(self.start), len(self.M)
        ends = np.cumsum(live)
        places = list(zip((ends - live).tolist(), ends.tolist()))
        P = np.empty((S, len(w)))
        for (a, b), (i, j) in zip(places, [*places[1:], (0, 0)]):
            if a == 0:
                P[:, :b] = self.start[:, None]
            here, now = w[a : a + j - i], P[:, a : a + j - i]
            for t in range(S - 1 if j > i else 0):
                to = P[t, i:j]
                self.ahead0[t].take(here, out=to, mode="clip")
                for s in range(S - 1):
                    to += now[s] * self.ahead[s * (S - 1) + t].take(here, mode="clip")
            if j > i:
                P[S - 1, i:j] = 1 - P[: S - 1, i:j].sum(axis=0)
        for r in range(S):
            self.A[:, r] += np.bincount(w, P[r], nodes)
        if not gradient:
            return
        L = np.zeros((S - 1, len(w)))  # behind the word at each place
        for (a, b), (i, j) in zip(places[-2::-1], places[:0:-1]):
            here, now = w[i:j], L[:, i:j]
            for r in range(S - 1):
                to = L[r, a : a + j - i]
                self.back0[r].take(here, out=to, mode="clip")
                for s in range(S - 1):
                    to += now[s] * self.back[r * (S - 1) + s].take(here, mode="clip")
        for r in range(S):
            for s in range(S - 1):
                self.B[:, r, s + 1] += np.bincount(w, P[r] * L[s], nodes)

    def sums(self, gradient: bool) -> tuple[float, np.ndarray, np.ndarray]:
        value = float((self.A * self.c).sum())
        return (value, *self.words.gradients(self.A, self.B, self.M, self.T, self.d)) if gradient else (value, np.zeros_like(self.T), np.zeros_like(self.d))


@dataclass
class SoftMachine:
    states: int
    m: int
    emission: str = "free"  # or estimated: ratio of state mass
    seed: int = 0
    jitter: float = 1e-2
    start: str = "fixed"  # all reads begin in state 0, or uniform
    t: np.ndarray = None
    d: np.ndarray = None
    fixed: np.ndarray = None  # (m, S): target state of fixed transitions, else -1
    history: list[float] = field(default_factory=list)
    mixture_bits: float = 0.0

    def __post_init__(self) -> None:
        # equal parameters are a stationary point up to relabelling: a seeded jitter breaks the symmetry
        r = np.random.default_rng(self.seed)
        self.t = r.normal(0, self.jitter, (self.m, self.states, self.states)) if self.t is None else self.t
        self.d = r.normal(0, self.jitter, (self.states, self.m)) if self.d is None else self.d
        self.fixed = np.full((self.m, self.states), -1) if self.fixed is None else self.fixed

    def transitions(self) -> np.ndarray:
        T = softmax(self.t)
        x, r = np.nonzero(self.fixed >= 0)
        T[x, r] = 0
        T[x, r, self.fixed[x, r]] = 1
        return T

    def emissions(self) -> np.ndarray:
        """(m, S) log probabilities."""
        return np.log(softmax(self.d) + 1e-300).T

    def begin(self) -> np.ndarray:
        return np.eye(self.states)[0] if self.start == "fixed" else np.full(self.states, 1 / self.states)

    def evaluate(self, stream: Stream | Sheets, gradient: bool = True) -> tuple[float, np.ndarray, np.ndarray, float]:
        """Objective, gradients by logits t and d, and mixture bits over all reads: one pass, sums by index.

        Over sheets there are no mixture bits (nan), which are not linear in the states, and gradients may be left out (0).
        """
        T, e, start = self.transitions(), self.emissions(), self.begin()
        if isinstance(stream, Sheets):
            words = stream.words

            def by_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                sweep = None
                for batch in batches:
                    for live, numbers in zip(batch.column(0), batch.column(1)):
                        sweep = sweep or Sweep(words.value, T, e, start)
                        sweep.add(live.values.to_numpy().astype(np.int64), np.frombuffer(numbers.as_buffer(), np.int32), gradient)
                if sweep is not None:
                    f, gT, gd = sweep.sums(gradient)
                    total = np.concatenate([[f, np.nan], gT.ravel(), gd.ravel()])
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["i", "v"])

            return self._gradients(stream.df.mapInArrow(by_words, "i long, v double"), T, e)
        flat = stream.flat

        def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(2 + T.size + e.size)
            for batch in pieces(batches):
                f, gT, gd, mixed = batch_gradient(flat(batch.column(0)), T, e, start)
                total += np.concatenate([[f, mixed], gT.ravel(), gd.ravel()])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["i", "v"])

        return self._gradients(stream.select().mapInArrow(kernel, "i long, v double"), T, e)

    def _gradients(self, sums: DataFrame, T: np.ndarray, e: np.ndarray) -> tuple[float, np.ndarray, np.ndarray, float]:
        got = sums.groupBy("i").agg(F.sum("v").alias("v")).toArrow()
        v = np.zeros(2 + T.size + e.size)
        v[got.column("i").to_numpy()] = got.column("v").to_numpy()
        gT, gd = v[2 : 2 + T.size].reshape(T.shape), v[2 + T.size :].reshape(e.shape)
        gt = T * (gT - (T * gT).sum(axis=-1, keepdims=True))
        gt[self.fixed >= 0] = 0
        mass = gd.T  # (S, m) state mass per symbol
        p = softmax(self.d)
        if self.emission == "estimated":
            self.d = np.log(np.maximum(mass, 1e-9))
            gl = np.zeros_like(self.d)
        else:
            gl = mass - p * mass.sum(axis=-1, keepdims=True)
        return float(v[0]), gt, gl, float(-v[1])

    def fit(self, stream: Stream | Sheets, iterations: int = 40, rate: float = 0.1) -> SoftMachine:
        """Adam steps up the objective per symbol; the best parameters seen are kept."""
        moments = [np.zeros_like(self.t), np.zeros_like(self.d)]
        squares = [np.zeros_like(self.t), np.zeros_like(self.d)]
        best = None
        for i in range(1, iterations + 1):
            t, d = self.t.copy(), self.d.copy()
            value, gt, gd, mixed = self.evaluate(stream)
            self.history.append(value)
            if best is None or value > best[0]:
                best = (value, t, d, mixed)
            scale = max(1e-12, float(np.abs(gt).max()), float(np.abs(gd).max()))
            for k, grad in enumerate((gt / scale, gd / scale)):
                moments[k] = 0.9 * moments[k] + 0.1 * grad
                squares[k] = 0.99 * squares[k] + 0.01 * grad**2
                step = rate * moments[k] / (1 - 0.9**i) / (np.sqrt(squares[k] / (1 - 0.99**i)) + 1e-8)
                if k == 0:
                    self.t = self.t + step
                elif self.emission == "free":
                    self.d = self.d + step
        value, _, _, mixed = self.evaluate(stream, self.emission == "estimated")
        self.history.append(value)
        if best is not None and best[0] > value:
            _, self.t, self.d, mixed = best
        self.mixture_bits = mixed
        return self

    def table(self) -> np.ndarray:
        """(S, m) most probable next state: the transition table once all rows are fixed."""
        return self.transitions().argmax(axis=-1).T


def harden(machine: SoftMachine, stream: Stream | Sheets, refit: int = 3, per_round: int = 1, rate: float = 0.1) -> np.ndarray:
    """Fixes the most probable open transitions, refits, and repeats until all are fixed. Returns the (S, m) table."""
    while (machine.fixed < 0).any():
        T = np.where((machine.fixed < 0)[:, :, None], machine.transitions(), -1)
        top = T.max(axis=-1)
        for flat in np.argsort(-top, axis=None, kind="stable")[:per_round]:
            x, r = np.unravel_index(flat, top.shape)
            if machine.fixed[x, r] < 0:
                machine.fixed[x, r] = int(T[x, r].argmax())
        if refit and (machine.fixed < 0).any():
            machine.fit(stream, refit, rate)
    return machine.table()
