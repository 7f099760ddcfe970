"""Stupid-backoff scores from n-gram counts over the whole corpus, by hash-partitioned count tables and joins.

S(w | u) = count(u w) / count(u) if the pair (u, w) occurs at least ``least`` times, else BACKOFF * count(w) / N. Counts are
over all documents. A document's score is the sum of lg S over its words; the first word of a document follows a start mark.

The relations are kept as columns of blocks. Documents are grouped by a hash of their id into groups of a few MB. Each group
lists its distinct words and pairs once, with counts (so a frequent n-gram costs one entry a group, however often it
occurs), cut by n-gram hash into partitions of the count tables. A partition adds the entries up and answers every group
with the totals, in the order asked. Groups join the answers to their exploded n-grams and sum per document.

Null and empty texts have no words: score 0, perplexity null. Equal texts have equal scores. An empty table gives an empty
result. Only doc_id and text are read. Hash collisions (64 bits) are neglected.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.llm import textkernel as K
from ctxloom.session import load

BACKOFF = 0.4
LEAST = 2
GROUP_BYTES = 10 << 20
PART_BYTES = 12 << 20  # input per partition of the count tables
START = np.uint64(0x5BD1E9955BD1E995)


def _ngrams(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Row, context word, word and pair of every position."""
    w = K.words(texts)
    row = K.owners(w.starts)
    before = np.concatenate([[START], w.hashes[:-1]]) if len(w.hashes) else w.hashes
    before[w.starts[:-1][np.diff(w.starts) > 0]] = START
    return row, before, w.hashes, K.mix(K.mix(before) * np.uint64(3) + w.hashes) | np.uint64(1)


def _keys(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The group's distinct n-grams, sorted, with their counts. Pairs have odd keys; words, contexts and N even ones."""
    _, before, word, pair = _ngrams(texts)
    even = ~np.uint64(1)
    starts = np.count_nonzero(before == START)
    single, n1 = np.unique(word & even, return_counts=True)
    double, n2 = np.unique(pair, return_counts=True)
    extra = np.array([START & even, 0], np.uint64)
    key, n = np.concatenate([single, double, extra]), np.concatenate([n1, n2, [starts, len(word)]])
    order = np.argsort(key, kind="stable")
    return key[order], n[order]


def _split(key: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """Order of the keys by partition (stable) and the partitions' starts. Key 0 (the number of words) is in all partitions' reach by partition 0."""
    part = (K.mix(key) % np.uint64(parts)).astype(np.int64)
    order = np.argsort(part, kind="stable")
    return order, np.searchsorted(part[order], np.arange(parts + 1))


def _planes(x: np.ndarray) -> bytes:
    """Bytes of equal weight side by side: small numbers then are runs of zeros, which the shuffle's compression removes."""
    return np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.dtype.itemsize).T.tobytes()


def _from_planes(data: bytes, kind: type) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(size, -1).T).view(kind).ravel()


def _ask(parts: int):
    def kernel(pdf: pd.DataFrame) -> pd.DataFrame:
        key, n = _keys(pa.array(pdf["text"], pa.string()))
        order, at = _split(key, parts)
        key, n = key[order], n[order].astype(np.uint32)
        # keys are sorted within a partition and sent as differences
        rows = [(int(pdf["grp"].iloc[0]), p, _planes(np.diff(key[a:b], prepend=np.uint64(0))), _planes(n[a:b])) for p, (a, b) in enumerate(zip(at[:-1], at[1:])) if b > a]
        return pd.DataFrame(rows, columns=["grp", "part", "keys", "counts"])

    return kernel


def _answer(pdf: pd.DataFrame) -> pd.DataFrame:
    keys = [np.cumsum(_from_planes(k, np.uint64), dtype=np.uint64) for k in pdf["keys"]]
    every = np.concatenate(keys)
    n = np.concatenate([_from_planes(c, np.uint32) for c in pdf["counts"]]).astype(np.uint64)
    order = np.argsort(every, kind="stable")
    ordered = every[order]
    new = np.ones(len(every), bool)
    new[1:] = ordered[1:] != ordered[:-1]
    total = np.add.reduceat(n[order], np.flatnonzero(new))
    back = np.empty(len(every), np.uint64)
    back[order] = total[np.cumsum(new) - 1]
    cuts = np.cumsum([len(k) for k in keys])[:-1]
    return pd.DataFrame({"grp": pdf["grp"], "part": pdf["part"], "totals": [_planes(x) for x in np.split(back, cuts)]})


def _score(parts: int, least: int, backoff: float):
    def kernel(docs: pd.DataFrame, answers: pd.DataFrame) -> pd.DataFrame:
        texts = pa.array(docs["text"], pa.string())
        key, _ = _keys(texts)
        order, _ = _split(key, parts)
        total = np.empty(len(key))
        total[order] = np.concatenate([_from_planes(t, np.uint64) for t in answers.sort_values("part")["totals"]])
        even = ~np.uint64(1)
        row, before, word, pair = _ngrams(texts)
        count = lambda k: total[np.searchsorted(key, k)]
        words = float(count(np.uint64(0)))
        seen = count(pair)
        high = seen >= least
        bits = np.log2(np.where(high, seen / count(before & even), backoff * count(word & even) / max(words, 1)))
        n = np.bincount(row, minlength=len(docs))
        return pd.DataFrame(
            {
                "doc_id": docs["doc_id"], "n_words": n, "score": np.round(np.bincount(row, bits, len(docs)), 6),
                "backed_off": np.bincount(row, ~high, len(docs)).astype(np.int64),
            }
        )

    return kernel


RESULT = "doc_id long, n_words long, score double, backed_off long"


def stupid_backoff(docs: DataFrame, least: int = LEAST, backoff: float = BACKOFF) -> DataFrame:
    """doc_id, n_words, score (sum of lg S), backed_off (positions scored by the lower order), perplexity."""
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)), F.count("*")).first()
    groups = max(1, math.ceil((size[0] + 64 * size[1]) / GROUP_BYTES))
    parts = max(1, math.ceil(size[0] / PART_BYTES), min(groups, 8))
    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("grp", F.pmod(F.xxhash64("doc_id", F.crc32(F.encode("text", "UTF-8"))), F.lit(groups)).cast("int"))
    # a few hundred groups a task or fewer: a group is the unit of memory, a partition only a batch of groups
    rows = rows.repartition(groups, "grp")
    asked = rows.groupBy("grp").applyInPandas(_ask(parts), "grp int, part int, keys binary, counts binary")
    answers = asked.groupBy("part").applyInPandas(_answer, "grp int, part int, totals binary")
    scored = rows.groupBy("grp").cogroup(answers.groupBy("grp")).applyInPandas(_score(parts, least, backoff), RESULT)
    return scored.withColumn("perplexity", F.when(F.col("n_words") > 0, F.round(F.pow(F.lit(2.0), -F.col("score") / F.col("n_words")), 6)))


def op7_stupid_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stupid_backoff(load(spark, sf_dir, "documents"))


QUERIES = {"op7_stupid_backoff": op7_stupid_backoff}
ORACLES: dict[str, str] = {}
