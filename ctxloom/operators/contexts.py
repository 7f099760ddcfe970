"""Contexts: how the key of a conditional distribution is computed from what precedes a symbol.

Each context turns a :class:`Flat` into one integer per symbol, and says which symbols count (the first ones of a sequence may
have no context). ``size`` is the number of codes; products are mixed-radix numbers. Nearest values are in the low digits.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Protocol

import numpy as np

from ctxloom.operators.stream import Flat


class Context(Protocol):
    def size(self, m: int) -> int: ...

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        """Context code of each symbol, and whether it counts."""


def heads(f: Flat, places: int) -> np.ndarray:
    """Where the first ``places`` symbols of each sequence are (without a pass over all symbols)."""
    size, begin = f.size, f.starts[:-1]
    found = [begin[size > j] + j for j in range(min(places, int(size.max(initial=0))))]
    return np.concatenate(found) if found else np.zeros(0, np.int64)


def _shifted(f: Flat, lag: int, fill: int) -> np.ndarray:
    out = np.full(len(f.codes), fill, np.int64)
    if lag < len(f.codes):
        out[lag:] = f.codes[:-lag] if lag else f.codes
    out[heads(f, lag)] = fill
    return out


def lagged(f: Flat, lag: int, fill: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The value ``lag`` places before, and whether there is one in the same sequence."""
    return _shifted(f, lag, fill), f.position() >= lag


@dataclass(frozen=True)
class Previous:
    """The ``order`` previous values. The first values of a sequence are skipped, padded with a symbol of their own, or
    back off to the longest context they have (codes of lower orders follow those of the full order)."""

    order: int
    head: str = "skip"
    start: int = 0  # windows begin at this position at least, to rate several orders over the same windows

    def size(self, m: int) -> int:
        if self.head == "pad":
            return (m + 1) ** self.order
        return sum(m**k for k in range(self.order + 1)) if self.head == "backoff" else m**self.order

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        base = m + 1 if self.head == "pad" else m
        ctx, valid = np.zeros(len(f.codes), np.int64), np.ones(len(f.codes), bool)
        for lag in range(1, self.order + 1):
            value = _shifted(f, lag, m if self.head == "pad" else 0)
            value *= base ** (lag - 1)
            ctx += value
        valid[heads(f, max(self.start, self.order if self.head == "skip" else 0))] = False
        if self.head == "backoff":
            offset, position = m**self.order, f.position()
            for k in range(self.order - 1, -1, -1):
                ctx[position == k] += offset
                offset += m**k
        return ctx, valid


@dataclass(frozen=True)
class Lag:
    """The one value at a distance."""

    lag: int

    def size(self, m: int) -> int:
        return m

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        return lagged(f, self.lag)


@dataclass(frozen=True)
class Position:
    """Place in the sequence, in steps of ``width``, at most ``cap - 1``."""

    width: int = 1
    cap: int = 1 << 10

    def size(self, m: int) -> int:
        return self.cap

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        return np.minimum(f.position() // self.width, self.cap - 1), np.ones(len(f.codes), bool)


def _running(f: Flat, step: np.ndarray) -> np.ndarray:
    """Sum of ``step`` over the symbols of the sequence before each symbol."""
    total = np.concatenate([[0], np.cumsum(step)])
    return total[:-1] - np.repeat(total[f.starts[:-1]], f.size)


@dataclass(frozen=True)
class ChangeCount:
    """How often the value has changed so far, in steps of ``quant``, at most ``cap - 1``."""

    cap: int = 8
    quant: int = 1

    def size(self, m: int) -> int:
        return self.cap

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        before, has = lagged(f, 1)
        return np.minimum(_running(f, has & (before != f.codes)) // self.quant, self.cap - 1), np.ones(len(f.codes), bool)


@dataclass(frozen=True)
class RunningSum:
    """Sum of the values so far, in steps of ``quant``, at most ``cap - 1``."""

    cap: int = 8
    quant: int = 1

    def size(self, m: int) -> int:
        return self.cap

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        return np.minimum(_running(f, f.codes) // self.quant, self.cap - 1), np.ones(len(f.codes), bool)


@dataclass(frozen=True)
class LowBits:
    """``order`` previous values, each without its low ``drop`` bits."""

    order: int
    drop: int

    def size(self, m: int) -> int:
        return (((m - 1) >> self.drop) + 1) ** self.order

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        base, ctx = ((m - 1) >> self.drop) + 1, np.zeros(len(f.codes), np.int64)
        for lag in range(1, self.order + 1):
            ctx += (lagged(f, lag)[0] >> self.drop) * base ** (lag - 1)
        return ctx, f.position() >= self.order


@dataclass(frozen=True)
class Product:
    """Several contexts at once."""

    parts: tuple

    def size(self, m: int) -> int:
        return int(np.prod([p.size(m) for p in self.parts], dtype=object))

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        ctx, valid, base = np.zeros(len(f.codes), np.int64), np.ones(len(f.codes), bool), 1
        for p in self.parts:
            c, v = p.codes(f, m)
            ctx, valid, base = ctx + c * base, valid & v, base * p.size(m)
        return ctx, valid


@dataclass(frozen=True)
class Binned:
    """A context looked up in a bin table (a dense array; codes never seen in training have the fallback bin)."""

    inner: object
    table: tuple
    bins: int

    def size(self, m: int) -> int:
        return self.bins

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        ctx, valid = self.inner.codes(f, m)
        return np.asarray(self.table, np.int64)[ctx], valid


@dataclass(frozen=True)
class DelayedBin:
    """A bin that was computed ``lag`` symbols ago: the state of an earlier place, reused without a new lookup."""

    inner: object
    lag: int

    def size(self, m: int) -> int:
        return self.inner.size(m)

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        ctx, valid = self.inner.codes(f, m)
        g = Flat(ctx, f.starts, f.row, f.nth)
        value, has = lagged(g, self.lag)
        before, _ = lagged(Flat(valid.astype(np.int64), f.starts, f.row, f.nth), self.lag)
        return value, has & (before > 0)


@dataclass(frozen=True)
class From:
    """A context whose first symbols count only from a given position on: rates over the same windows."""

    inner: object
    start: int

    def size(self, m: int) -> int:
        return self.inner.size(m)

    def codes(self, f: Flat, m: int) -> tuple[np.ndarray, np.ndarray]:
        ctx, valid = self.inner.codes(f, m)
        return ctx, valid & (f.position() >= self.start)


def handmade(m: int, orders: int = 2, drop: int = 2, position_width: int = 16, position_cap: int = 8, changes: int = 4) -> Product:
    """The usual hand-made context: previous values without low bits, coarse position, number of changes."""
    return Product((LowBits(orders, drop), Position(position_width, position_cap), ChangeCount(changes, 8)))


NONE = Previous(0)
