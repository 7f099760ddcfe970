"""Language identification by bit-sliced Bloom filters of byte 4-grams.

One Bloom filter per language, stored side by side: slot s of the table holds a mask with a bit per language (a 64-bit word
for every 64 languages), so reading an n-gram's slots and joining the masks by AND returns all languages whose filter has it. A language's filter holds the 4-grams
that make up at least LEAST of its training windows and at least SHARE of the largest such share among the languages. A
text's hits per language are the popcount of that bit over its n-grams; the filter's false-positive rate (its fill to the
power of the number of hashes) is taken out, and the language with most corrected hits wins (ties: first in order).

The filters learn from about PER_LANGUAGE documents of each language (a documented bound); every lang value with a 4-gram in
its training rows has a filter. All texts are scored whole. Windows lie within one text, over lower-cased letters with all else as one
space. A text without letters, or null, is ``und`` with score 0. With no training rows all texts are ``und``. An empty table
gives an empty result. Only doc_id, text and, for learning, lang are read; other columns, whatever their names, are not.
Repeated rows are learned from as often as they occur, and every row is predicted by its own text; a null doc_id is an id
like the others.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxloom.llm import labelled as L
from ctxloom.llm import textkernel as K
from ctxloom.llm.textkernel import slices, tidy
from ctxloom.session import load

SLOTS = 1 << 20
HASHES = 2
PER_LANGUAGE = 1500
WORD = 64  # languages of one mask word
GRAMS = 1 << 16  # kept per language, the most frequent
LEAST, SHARE = 2e-6, 0.25
FOLDS, HELD_OUT = 3, 1
#: Least corrected share of a text's windows in its best language for the text to count as known.
KNOWN = 0.2
_LETTER = np.full(256, 32, np.uint8)
_LETTER[97:123] = np.arange(97, 123)
_LETTER[128:] = np.arange(128, 256)


def grams(texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row of each window, 4-gram), piece by piece."""
    data, offsets = K.flat_bytes(K.lower(texts))
    letters = _LETTER[data]
    keep = np.ones(len(letters), bool)
    keep[1:] = (letters[1:] != 32) | (letters[:-1] != 32)
    keep[offsets[:-1][np.diff(offsets) > 0]] = True
    letters, offsets = letters[keep], np.concatenate([[0], np.cumsum(keep)])[offsets]
    for a, b, row in K.chunks(offsets, 3):
        part = letters[a:b].astype(np.uint32)
        if len(part) > 3:
            inside = row[:-3] == row[3:]
            gram = part[:-3] | part[1:-2] << np.uint32(8) | part[2:-1] << np.uint32(16) | part[3:] << np.uint32(24)
            yield row[:-3][inside], gram[inside]


def _slots(gram: np.ndarray) -> list[np.ndarray]:
    h = K.mix(gram.astype(np.uint64))
    return [((h >> np.uint64(20 * i)) & np.uint64(SLOTS - 1)).astype(np.int64) for i in range(HASHES)]


@dataclass
class LanguageFilters:
    languages: list[str]
    masks: np.ndarray  # uint64, slots x words
    false_rate: np.ndarray  # per language

    @staticmethod
    def build(per_language: dict[str, tuple[np.ndarray, np.ndarray]]) -> LanguageFilters:
        """From each language's 4-grams and their shares of its windows."""
        names = sorted(per_language)
        every = np.unique(np.concatenate([per_language[n][0] for n in names])) if names else np.zeros(0, np.uint32)
        top = np.zeros(len(every))
        for gram, share in per_language.values():
            at = np.searchsorted(every, gram)
            top[at] = np.maximum(top[at], share)
        masks = np.zeros((SLOTS, -(-len(names) // WORD)), np.uint64)
        fill = np.zeros(len(names))
        for i, n in enumerate(names):
            gram, share = per_language[n]
            word, bit = masks[:, i // WORD], np.uint64(1 << i % WORD)
            for s in _slots(gram[(share >= LEAST) & (share >= SHARE * top[np.searchsorted(every, gram)])]):
                word[s] |= bit
            fill[i] = np.count_nonzero(word & bit) / SLOTS
        return LanguageFilters(names, masks, fill**HASHES)

    def languages_of(self, gram: np.ndarray) -> np.ndarray:
        """A row of mask words per 4-gram."""
        a = np.full((len(gram), self.masks.shape[1]), ~np.uint64(0))
        for s in _slots(gram):
            a &= self.masks[s]
        return a

    def corrected(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Share of each row's windows per language without false positives, and the rows' windows."""
        rows = len(texts)
        hits, seen = np.zeros((rows, len(self.languages))), np.zeros(rows, np.int64)
        for row, gram in grams(texts):
            if not len(row):
                continue
            r0, n = int(row[0]), int(row[-1] - row[0]) + 1
            seen[r0 : r0 + n] += np.bincount(row - r0, minlength=n)
            mask = self.languages_of(gram)
            for i in range(len(self.languages)):
                hits[r0 : r0 + n, i] += np.bincount(row - r0, (mask[:, i // WORD] >> np.uint64(i % WORD)) & np.uint64(1), n)
        rate = hits / np.maximum(seen, 1)[:, None]
        return np.clip((rate - self.false_rate) / (1 - self.false_rate), 0, 1), seen

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score and the best language's corrected share of the windows."""
        share, _ = self.corrected(texts)
        data, offsets = K.flat_bytes(K.lower(texts))
        ascii_letter = np.concatenate([[0], np.cumsum((data >= 97) & (data <= 122))])
        lettered = (ascii_letter[offsets[1:]] - ascii_letter[offsets[:-1]]) > 0
        for i in np.flatnonzero(~lettered):
            lettered[i] = any(c.isalpha() for c in texts[int(i)].as_py() or "")
        if not self.languages:
            return ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts))
        best = share.argmax(axis=1)
        total = share.sum(axis=1)
        score = np.where(lettered & (total > 0), share[np.arange(len(share)), best] / np.maximum(total, 1e-12), 0)
        return [self.languages[b] if ok else "und" for b, ok in zip(best, lettered)], np.round(score, 9), np.where(lettered, share.max(axis=1), 0)


def train(docs: DataFrame) -> LanguageFilters:
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).where(L.fold(F.col("doc_id"), FOLDS) != HELD_OUT).select("doc_id", "lang", "text")
    names = [r.lang for r in known.select("lang").distinct().collect()]
    sample = L.thinned(known, dict.fromkeys(names, PER_LANGUAGE), F.col("lang")).select("lang", "text")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            langs = np.array(batch.column(0).to_pylist(), object)
            out: dict[str, list] = {}
            for row, gram in grams(batch.column(1)):
                for name in set(langs[np.unique(row)]):
                    out.setdefault(name, []).append(gram[langs[row] == name])
            for name, parts in out.items():
                key, n = np.unique(np.concatenate(parts), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(key), pa.string()), pa.array(key.astype(np.int64)), pa.array(n.astype(np.int64))], names=["lang", "gram", "n"])

    counts = sample.mapInArrow(tidy(kernel), "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    # the most frequent GRAMS of each language: at most that many rows a language reach the driver. A language whose 4-grams are all rare keeps them
    own = Window.partitionBy("lang")
    ranked = counts.withColumn("rank", F.row_number().over(own.orderBy(F.desc("n"), "gram"))).where(F.col("rank") <= GRAMS).withColumn("top", F.max("n").over(own))
    got = ranked.where(F.col("n") >= F.least(F.lit(3), "top")).select("lang", "gram", "n").toArrow()
    langs = got.column("lang").combine_chunks().dictionary_encode()
    langs = langs.combine_chunks() if isinstance(langs, pa.ChunkedArray) else langs
    gram, n = got.column("gram").to_numpy().astype(np.uint32), got.column("n").to_numpy().astype(float)
    code = langs.indices.to_numpy(zero_copy_only=False)
    order = np.lexsort((gram, code))
    starts = np.searchsorted(code[order], np.arange(len(langs.dictionary) + 1))
    per = {}
    for name, a, b in zip(langs.dictionary.to_pylist(), starts[:-1], starts[1:]):
        at = order[a:b]
        per[name] = (gram[at], n[at] / n[at].sum())
    return LanguageFilters.build(per)


RESULT = "doc_id long, held_out boolean, lang_pred string, score double"
_SHARED = RESULT + ", share double"


def identify(docs: DataFrame, filters: LanguageFilters) -> DataFrame:
    """Predicts every whole text in one narrow pass. The filters are SLOTS * 8 bytes for every 64 languages."""
    sent = docs.sparkSession.sparkContext.broadcast(filters)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            names, score, share = sent.value.predict(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(names, pa.string()), pa.array(score, pa.float64()), pa.array(share, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score", "share"])

    return docs.select(F.col("doc_id").cast("long"), "text", (L.fold(F.col("doc_id"), FOLDS) == HELD_OUT).alias("held_out")).mapInArrow(tidy(kernel), _SHARED)


def known_language(docs: DataFrame, filters: LanguageFilters) -> DataFrame:
    """The documents in a language that the filters know (at least KNOWN of the windows), with all their columns, in place."""
    sent = docs.sparkSession.sparkContext.broadcast(filters)

    def accept(texts: pa.Array) -> np.ndarray:
        names, _, share = sent.value.predict(texts)
        return (np.array(names, object) != "und") & (share >= KNOWN)

    return L.keep_rows(docs, accept)


def op10_bloom_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return identify(docs, train(docs)).drop("share")


QUERIES = {"op10_bloom_language": op10_bloom_language}
ORACLES: dict[str, str] = {}
