"""Quality by a linear hinge-loss model over n-gram indicators that are scaled by naive Bayes log-count ratios.

The n-grams are byte 3-grams of the text as it stands, pairs of neighbouring word shapes, and how often a word or a pair of
words repeats its predecessor (in powers of two). Each indicator is scaled by the log ratio of its smoothed frequencies in the two
classes; the hinge-loss model is fitted by dual coordinate descent. The weights of the scaled indicators are then drawn towards
their mean magnitude (interpolation): at the mean itself every indicator would count by its log ratio alone, as in naive Bayes.

Labels are learned from a sample of at most PER_CLASS rows of each class (a documented bound); all texts are scored whole.
The score is a logistic curve of the margin with 0.7 at margin 0. Null and empty texts have no n-grams: their score is that of the
bias. With one class only, every score is 0.7 for it, else 0. An empty table gives an empty result. Only doc_id, text
and the labels are read; other columns, whatever their names, are not. A document with several labels is good only if all
of them say so; labels without a doc_id are skipped. A doc_id that occurs several times counts once in the sample, with its
least text; every row is scored by its own, so equal texts have equal scores.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.llm import labelled as L
from ctxloom.llm import textkernel as K
from ctxloom.session import load

SLOTS = 1 << 18
PER_CLASS = 2500
FOLDS, HELD_OUT = 4, 2
THRESHOLD = 0.7
# The shape class of each byte (1 lower case, 2 upper case, 3 digit, 4 space, 5 newline, 6 other ASCII, 7 beyond ASCII).
_SHAPE = np.full(256, 6, np.uint8)
_SHAPE[97:123], _SHAPE[65:91], _SHAPE[48:58], _SHAPE[[9, 32]], _SHAPE[[10, 11, 12, 13]], _SHAPE[128:] = 1, 2, 3, 4, 5, 7


def features(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, int]:
    """Distinct (row, n-gram slot), ordered by row."""
    data, offsets = K.flat_bytes(texts)
    rows = len(offsets) - 1
    keys: list[np.ndarray] = []
    for a, b, row in K.chunks(offsets, 2):
        part = data[a:b].astype(np.int64)
        if len(part) > 2:
            keys.append(_distinct(row[:-2], part[:-2] | part[1:-1] << 8 | part[2:] << 16, row[:-2] == row[2:]))
    shape = _SHAPE[data]
    change = np.ones(len(data), bool)  # runs of one class count as one
    change[1:] = shape[1:] != shape[:-1]
    change[offsets[:-1][np.diff(offsets) > 0]] = True
    runs = shape[change]
    for a, b, row in K.chunks(np.concatenate([[0], np.cumsum(change)])[offsets], 4):
        run = runs[a:b].astype(np.int64)
        if len(run) > 4:
            code = sum(run[i : len(run) - 4 + i] << (3 * i) for i in range(5))
            keys.append(_distinct(row[:-4], code | 1 << 25, row[:-4] == row[4:]))
    w = K.words(texts)
    owner = K.owners(w.starts)
    for lag in (1, 2):
        if len(w.hashes) > lag:
            same = np.bincount(owner[lag:], (w.hashes[lag:] == w.hashes[:-lag]) & (owner[lag:] == owner[:-lag]), rows)
            share = same / np.maximum(np.diff(w.starts), 1)
            for i, bound in enumerate((0.02, 0.05, 0.1, 0.2, 0.4)):
                hit = np.flatnonzero(share > bound)
                keys.append(hit << 32 | (1 << 26) + lag * 16 + i)
    if not keys:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), rows
    key = np.concatenate(keys)
    row = key >> 32
    slot = (K.mix((key & 0xFFFFFFFF).astype(np.uint64)) % np.uint64(SLOTS)).astype(np.int64)
    row, slot, _ = K.counted(row, slot)
    return row, slot, rows


def _distinct(row: np.ndarray, gram: np.ndarray, inside: np.ndarray) -> np.ndarray:
    return np.unique(row[inside] << 32 | gram[inside])


def log_ratios(marks: np.ndarray, index: np.ndarray, starts: np.ndarray, least: int) -> np.ndarray:
    """Log of the smoothed share of each slot among the good rows over that among the bad; 0 for slots of few rows."""
    counts = np.bincount(np.repeat(marks, np.diff(starts)) * SLOTS + index, minlength=2 * SLOTS)
    bad, good = counts[:SLOTS], counts[SLOTS:]
    ratio = np.log((good + 1) / (good.sum() + SLOTS)) - np.log((bad + 1) / (bad.sum() + SLOTS))
    ratio[good + bad < least] = 0
    return ratio


def descend(y: np.ndarray, index: np.ndarray, value: np.ndarray, starts: np.ndarray, most: np.ndarray, passes: int) -> tuple[np.ndarray, float, np.ndarray]:
    """Weights, bias and dual variables (0 .. ``most`` each) of the hinge-loss model over sparse rows of unit length or none."""
    w, bias, alpha = np.zeros(SLOTS), 0.0, np.zeros(len(y))
    shuffle = np.random.default_rng(7)
    for _ in range(passes):
        for i in shuffle.permutation(len(y)):
            f, v = index[starts[i] : starts[i + 1]], value[starts[i] : starts[i + 1]]
            slope = y[i] * (w[f] @ v + bias) - 1
            new = min(max(alpha[i] - slope / 2.0, 0.0), most[i])  # a row's squared norm with the bias is 2
            if new != alpha[i]:
                w[f] += (new - alpha[i]) * y[i] * v
                bias += (new - alpha[i]) * y[i]
                alpha[i] = new
    return w, bias, alpha


def interpolate(w: np.ndarray, used: np.ndarray, blend: float) -> np.ndarray:
    """``blend`` of the weights and 1 - ``blend`` of their mean magnitude over the used slots; unused slots stay 0."""
    mean = np.abs(w[used]).sum() / max(int(used.sum()), 1)
    return np.where(used, (1 - blend) * mean + blend * w, 0)


def fit(marks: np.ndarray, index: np.ndarray, starts: np.ndarray, cost: float = 0.1, passes: int = 20, least: int = 3, blend: float = 0.9) -> tuple[np.ndarray, float, np.ndarray]:
    """Weights per slot (log ratio folded in), bias, and the log ratios."""
    y = np.where(marks == 1, 1.0, -1.0)
    ratio = log_ratios(marks, index, starts, least)
    value = ratio[index]
    scale = np.sqrt(np.maximum(L.row_sums(value**2, starts), 1e-12))  # rows of unit length
    value = value / np.repeat(scale, np.diff(starts))
    most = 10 * cost * len(y) / 2 / np.where(y > 0, max((y > 0).sum(), 1), max((y < 0).sum(), 1))
    w, bias, _ = descend(y, index, value, starts, most, passes)
    return (interpolate(w, ratio != 0, blend) * ratio).astype(np.float32), float(bias), ratio.astype(np.float32)


class Scorer:
    """Margins of rows, scaled to unit length as in training."""

    def __init__(self, weights: np.ndarray, bias: float, ratio: np.ndarray):
        self.weights, self.bias, self.ratio = weights, bias, ratio

    def score(self, row: np.ndarray, slot: np.ndarray, rows: int) -> np.ndarray:
        length = np.sqrt(np.maximum(np.bincount(row, self.ratio[slot] ** 2, rows), 1e-12))
        margin = np.bincount(row, self.weights[slot], rows) / length + self.bias
        return np.round(1 / (1 + np.exp(-np.clip(4 * margin + np.log(THRESHOLD / (1 - THRESHOLD)), -30, 30))), 9)


class Constant:
    def __init__(self, value: float):
        self.value = value

    def score(self, row: np.ndarray, slot: np.ndarray, rows: int) -> np.ndarray:
        return np.full(rows, self.value)


def train(docs: DataFrame, labels: DataFrame) -> Scorer | Constant:
    known = L.one_label(labels, "quality", F.min).where(L.fold(F.col("doc_id"), FOLDS) != HELD_OUT)
    known = known.join(docs.select("doc_id").distinct(), "doc_id", "left_semi")
    chosen = L.thinned(known, {1: PER_CLASS, 0: PER_CLASS}, F.col("mark"))
    marks, index, starts = L.collect_features(L.sampled_texts(docs, chosen), features, "mark")
    if len(set(marks.tolist())) < 2:
        return Constant(0.7 if len(marks) and marks[0] == 1 else 0.0)
    return Scorer(*fit(marks, index, starts))


def score(docs: DataFrame, model: Scorer | Constant) -> DataFrame:
    return L.score_with(docs, features, model.score, THRESHOLD, FOLDS, HELD_OUT)


def good(docs: DataFrame, model: Scorer | Constant) -> DataFrame:
    """The documents that score at least THRESHOLD, with all their columns, in place."""
    return L.keep_rows(docs, lambda texts: model.score(*features(texts)) >= THRESHOLD)


def op9_nbsvm_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return score(docs, train(docs, load(spark, sf_dir, "labels")))


QUERIES = {"op9_nbsvm_quality": op9_nbsvm_quality}
ORACLES: dict[str, str] = {}
