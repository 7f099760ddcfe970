"""A training-data pipeline: language, quality, near duplicates, mixture, tokens.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written as Parquet and read again as the next stage's
docs. Every stage works on all that its predecessor kept. All stages but the last return the columns of documents, whatever
these are. Filters decide each row by its own text, in place: texts are shuffled only where near copies are compared, and
where a document may be one that goes. Stages follow the null and empty rules of their operators: a null text has no
language and goes in the first stage. Repeated rows, and rows without an id, stay or go as the operators say.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ctxloom.llm import bytebpe, langid, minhash, mixing, quality
from ctxloom.session import load, materialise


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that the filters know: some filter has at least langid.KNOWN of the text's 4-grams. Those without letters go."""
    return langid.known_language(docs, langid.train(docs))


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts."""
    return quality.good(docs, quality.train(docs, load(spark, sf_dir, "labels")))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of every near-duplicate group."""
    return minhash.without_copies(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: never, once or twice."""
    return mixing.repeated(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Digests of every document's byte-level BPE ids and of the bytes they decode to."""
    return bytebpe.digests(docs, *bytebpe.public_vocabulary())


STAGES = [("language", language), ("quality", good_quality), ("near_duplicates", one_of_each), ("mixture", mixture), ("tokens", tokens)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
