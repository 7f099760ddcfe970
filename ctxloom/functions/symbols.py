"""Symbols: fixed alphabets, column encoders, packing and grouping.

Column functions are plain Catalyst expressions; the lookup tables serve the Arrow kernels of :mod:`ctxloom.operators.stream`.
"""

from __future__ import annotations

import functools

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# The 41 characters of the text alphabet (code 41 stands for all else), and the vowels of the four-class one.
TEXT_ALPHABET = " \nabcdefghijklmnopqrstuvwxyzéóèñçüêäößí.,"
VOWELS = "aeiouyáéíóúàèìòùâêîôûäëïöü"
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
ROLES = ("system", "user", "assistant")
_BMP = 1 << 16


@functools.lru_cache(maxsize=8)
def text_table(alphabet: str, other: int) -> np.ndarray:
    """Code of every character of the basic plane, by its lower-case form; the last entry serves all characters beyond it."""
    table = np.full(_BMP + 1, other, np.int16)
    codes = {c: i for i, c in enumerate(alphabet)}
    for cp in range(_BMP):
        if not 0xD800 <= cp < 0xE000 and (low := chr(cp).lower()) in codes:
            table[cp] = codes[low]
    return table


@functools.lru_cache(maxsize=1)
def class_table() -> np.ndarray:
    """0 vowel, 1 other letter, 2 white space, 3 the rest."""
    table = np.full(_BMP + 1, 3, np.int16)
    for cp in range(_BMP):
        if not 0xD800 <= cp < 0xE000:
            c = chr(cp)
            table[cp] = 0 if c.lower() in VOWELS else 1 if c.isalpha() else 2 if c.isspace() else 3
    return table


def encode_text(col: Column, alphabet: str = TEXT_ALPHABET, other: int | None = None) -> Column:
    """array<int> of codes, one a character; characters outside the alphabet get ``other`` (default: the next code)."""
    other = len(alphabet) if other is None else other
    chars = F.split(F.lower(col), "")
    return F.transform(chars, lambda c: F.when(F.instr(F.lit(alphabet), c) > 0, F.instr(F.lit(alphabet), c) - 1).otherwise(F.lit(other)).cast("int"))


def encode_category(col: Column, values: tuple[str, ...]) -> Column:
    """Place of the value in the list; values outside it are null."""
    place = F.array_position(F.array(*map(F.lit, values)), col)
    return F.when(place > 0, place - 1).cast("int")


def quantize(col: Column, step: float = 1.0, cap: int | None = None, edges: list[float] | None = None) -> Column:
    """floor(x / step), or the number of edges at or below x; at most ``cap``."""
    code = F.floor(col / F.lit(step)) if edges is None else sum(((col >= F.lit(e)).cast("int") for e in edges), F.lit(0))
    return (F.least(code, F.lit(cap)) if cap is not None else code).cast("int")


def pack_pair(high: Column, low: Column, low_bits: int) -> Column:
    """Two symbols in one: the first shifted, the second in the low bits."""
    return F.shiftleft(high, low_bits).bitwiseOR(low)


def unpack_pair(packed: Column, low_bits: int) -> tuple[Column, Column]:
    return F.shiftright(packed, low_bits), packed.bitwiseAND(F.lit((1 << low_bits) - 1))


def group_symbols(syms: Column, g: int, m: int, overlap: bool = False) -> Column:
    """array of g neighbouring symbols packed in one (first symbol most significant); a short tail is dropped."""
    steps = F.size(syms) - g + 1
    starts = F.when(steps > 0, F.sequence(F.lit(1), steps, F.lit(1 if overlap else g))).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda s: F.aggregate(F.slice(syms, s, F.lit(g)), F.lit(0), lambda acc, x: acc * m + x))


def raw_bits(m: int, whole: bool = True) -> float:
    """Bits of a symbol without a model: lg m, or rounded up."""
    return float(np.ceil(np.log2(m))) if whole else float(np.log2(m))
