"""The canonical symbol streams over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.functions import symbols as S
from ctxloom.operators.stream import Stream, array_stream, ordered_arrays, text_stream
from ctxloom.session import load


def text42(spark: SparkSession, sf_dir: str) -> Stream:
    return text_stream(load(spark, sf_dir, "documents"))


def class4(spark: SparkSession, sf_dir: str) -> Stream:
    return text_stream(load(spark, sf_dir, "documents"), kind="class")


def page101(spark: SparkSession, sf_dir: str, kind: str = "text") -> Stream:
    """The first 101 characters of every page that has them."""
    pages = load(spark, sf_dir, "pages").where(F.length("html") >= 101).select("page_id", F.substring("html", 1, 101).alias("head"))
    return text_stream(pages, "head", kind, ("page_id",))


def page_reads(spark: SparkSession, sf_dir: str, kind: str = "text") -> Stream:
    """Whole pages in reads of 101 characters, the last one shorter."""
    return text_stream(load(spark, sf_dir, "pages"), "html", kind, ("page_id",)).cut(101, "keep")


def emb16(spark: SparkSession, sf_dir: str) -> Stream:
    rows = load(spark, sf_dir, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: F.floor((x.cast("double") + 1) * 16).cast("int")).alias("syms"))
    return array_stream(rows, "syms", 33, ("vec_id",))


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events")


def ev_code():
    return S.encode_category(F.col("event_type"), S.EVENT_TYPES)


def val_code():
    return S.quantize(F.col("value"), 12, 41)


def ev5(spark: SparkSession, sf_dir: str) -> Stream:
    return ordered_arrays(_events(spark, sf_dir), "user_id", ["ts", "event_id"], ev_code(), 5)


def val42(spark: SparkSession, sf_dir: str) -> Stream:
    return ordered_arrays(_events(spark, sf_dir), "user_id", ["ts", "event_id"], val_code(), 42)


def packed(spark: SparkSession, sf_dir: str) -> Stream:
    return ordered_arrays(_events(spark, sf_dir), "user_id", ["ts", "event_id"], S.pack_pair(val_code(), ev_code(), 3), 336)


def wordlen16(spark: SparkSession, sf_dir: str) -> Stream:
    words = F.filter(F.split(F.col("text"), r"\s+"), lambda w: w != "")
    rows = load(spark, sf_dir, "documents").select("doc_id", F.transform(words, lambda w: F.least(F.length(w), F.lit(15))).alias("syms"))
    return array_stream(rows, "syms", 16, ("doc_id",))


def qty50(spark: SparkSession, sf_dir: str) -> Stream:
    rows = load(spark, sf_dir, "lineitem")
    return ordered_arrays(rows, "l_orderkey", ["l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"], (F.col("l_quantity") - 1).cast("int"), 50)


def role3(spark: SparkSession, sf_dir: str) -> Stream:
    return ordered_arrays(load(spark, sf_dir, "conversations"), "conv_id", ["turn"], S.encode_category(F.col("role"), S.ROLES), 3)


def reads(spark: SparkSession, sf_dir: str, kind: str = "text", length: int = 101, tail: str = "keep") -> Stream:
    """Documents in reads of a fixed length, the last one of each shorter."""
    return (text42 if kind == "text" else class4)(spark, sf_dir).cut(length, tail)
