"""Toxicity by non-negative positive-unlabelled learning.

Confirmed toxic texts are the positives; all other training texts count as unlabelled, whatever their label says. With the
class prior p (the share of toxic rows among labelled training rows) the risk of a linear scorer g is

    p E_pos[loss(g)] + max(0, E_unl[loss(-g)] - p E_pos[loss(-g)])

with logistic loss. Where the bracket falls below zero, the step goes up its gradient instead, which stops the scorer from
fitting the positives hidden among the unlabelled. Features are the words a text has (hashed, present or not), kept if
the positives have them clearly more often than the unlabelled (a z-score and a ratio) and in
more than a few texts; training is full-batch in numpy on the driver.

Labels are learned from a sample of at most POSITIVES toxic and UNLABELLED other rows (documented bounds); all texts are
scored whole. Null and empty texts have no features: their score is that of the bias alone. If there is no toxic training
row, every score is 0. An empty table gives an empty result. Only doc_id, text and the labels are read; other columns,
whatever their names, are not. A document with several labels is toxic if one of them says so; labels without a doc_id
are skipped. A doc_id that occurs several times counts once in the sample, with its least text; every row is scored by its own.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.llm import labelled as L
from ctxloom.llm import textkernel as K
from ctxloom.session import load

SLOTS = 1 << 32
POSITIVES, UNLABELLED = 3000, 6000
FOLDS, HELD_OUT = 5, 0
STEPS = 400


def features(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, int]:
    """Distinct (row, word slot), ordered by row."""
    w = K.words(texts)
    row, slot, _ = K.counted(K.owners(w.starts), (w.hashes % np.uint64(SLOTS)).astype(np.int64))
    return row, slot, len(w.starts) - 1


@dataclass
class LinearScorer:
    slots: np.ndarray  # sorted
    weights: np.ndarray
    bias: float

    def margin(self, row: np.ndarray, slot: np.ndarray, rows: int) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.slots, slot), max(len(self.slots) - 1, 0))
        if not len(self.slots):
            return np.full(rows, self.bias)
        known = self.slots[at] == slot
        return self.bias + np.bincount(row[known], self.weights[at[known]], rows)

    def probability(self, row: np.ndarray, slot: np.ndarray, rows: int) -> np.ndarray:
        return _sigmoid(self.margin(row, slot, rows))


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def risk(g: np.ndarray, pos: np.ndarray, prior: float) -> tuple[float, np.ndarray, bool]:
    """The risk of margins g, the direction that training follows (one slope a row), and whether the bracket fell below zero.

    With the bracket above zero the direction is the risk's gradient; below zero it is the bracket's gradient, turned round."""
    n_pos, n_unl = int(pos.sum()), int((~pos).sum())
    p = _sigmoid(g)
    bracket = np.logaddexp(0, g[~pos]).mean() - prior * np.logaddexp(0, g[pos]).mean()
    value = prior * np.logaddexp(0, -g[pos]).mean() + max(bracket, 0.0)
    slope = np.where(pos, -prior * p / n_pos, p / n_unl)
    if bracket < 0:
        return float(value), -slope, True
    return float(value), slope + np.where(pos, -prior * (1 - p) / n_pos, 0), False


def fit(marks: np.ndarray, index: np.ndarray, starts: np.ndarray, prior: float, steps: int = STEPS, rate: float = 0.05, decay: float = 1e-4, evidence: float = 4.5, lift: float = 10.0, spread: float = 0.012) -> LinearScorer:
    """marks: 1 for positives, 0 for unlabelled rows."""
    pos = marks == 1
    n_pos, n_unl = int(pos.sum()), int((~pos).sum())
    if not n_pos or not n_unl:
        return LinearScorer(np.zeros(0, np.int64), np.zeros(0), -30.0)
    row = np.repeat(np.arange(len(marks)), np.diff(starts))
    seen, index = np.unique(index, return_inverse=True)
    in_pos = np.bincount(index[pos[row]], minlength=len(seen))
    in_unl = np.bincount(index[~pos[row]], minlength=len(seen))
    a, b = in_pos / n_pos, in_unl / n_unl
    clean = np.maximum(b - prior * a, 0) / (1 - prior)  # how often texts that are not toxic have the word
    both = (in_pos + in_unl) / (n_pos + n_unl)
    z = (a - b) / np.sqrt(np.maximum(both * (1 - both), 1e-12) * (1 / n_pos + 1 / n_unl))
    keep = (in_pos >= max(5, spread * n_pos)) & (z > evidence) & (a > lift * clean)
    slots = seen[keep]
    used = keep[index]
    row, col = row[used], (np.cumsum(keep) - 1)[index[used]]
    w, b = np.zeros(len(slots)), np.log(prior / (1 - prior))
    moment, square = np.zeros(len(slots) + 1), np.zeros(len(slots) + 1)
    for t in range(1, steps + 1):
        _, slope, _ = risk(b + np.bincount(row, w[col], len(marks)), pos, prior)
        grad = np.append(np.bincount(col, slope[row], len(slots)) + decay * w, slope.sum())
        moment = 0.9 * moment + 0.1 * grad
        square = 0.999 * square + 0.001 * grad**2
        step = rate * (moment / (1 - 0.9**t)) / (np.sqrt(square / (1 - 0.999**t)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    return LinearScorer(slots, w, float(b))


def train(docs: DataFrame, labels: DataFrame) -> LinearScorer:
    known = L.one_label(labels, "toxic", F.max).where(L.fold(F.col("doc_id"), FOLDS) != HELD_OUT)
    n, toxic = known.agg(F.count("*"), F.sum("mark")).first()
    if not n or not toxic:
        return LinearScorer(np.zeros(0, np.int64), np.zeros(0), -30.0)
    ids = docs.select("doc_id").where(F.col("doc_id").isNotNull() & (L.fold(F.col("doc_id"), FOLDS) != HELD_OUT)).distinct()
    rows = ids.join(known, "doc_id", "left").select("doc_id", F.coalesce(F.col("mark"), F.lit(0)).alias("mark"))
    chosen = L.thinned(rows, {1: POSITIVES, 0: UNLABELLED}, F.col("mark"))
    return fit(*L.collect_features(L.sampled_texts(docs, chosen), features, "mark"), prior=min(max(toxic / n, 1e-3), 0.9))


def op8_nnpu_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    scorer = train(docs, load(spark, sf_dir, "labels"))
    return L.score_with(docs, features, scorer.probability, 0.5, FOLDS, HELD_OUT)


QUERIES = {"op8_nnpu_toxicity": op8_nnpu_toxicity}
ORACLES: dict[str, str] = {}
