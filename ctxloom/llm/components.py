"""Connected components of an edge table by repeated contraction towards smaller labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ctxloom.session import materialise


SALTS = 64  # a node's neighbours are spread over so many keys


def _with_least(edges: DataFrame) -> DataFrame:
    """Adds m, the least neighbour b of each row's node a. A node with very many neighbours is met in SALTS parts: minima are
    taken per part, then per node, and handed back to the parts, so no key has to take all rows of a hub."""
    salt = F.pmod(F.xxhash64("b"), F.lit(SALTS)).cast("int").alias("salt")
    parts = edges.groupBy("a", salt).agg(F.min("b").alias("part_m"))
    whole = parts.groupBy("a").agg(F.min("part_m").alias("m"))
    return edges.withColumn("salt", salt).join(parts.join(whole, "a").select("a", "salt", "m"), ["a", "salt"]).drop("salt")


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """node, root (smallest node of its component) for every node of ``edges`` (a, b long).

    Each round links every node's larger neighbours to its smallest one, and then every node's neighbours to the smallest
    of them, until the table is a set of stars. Tables are written between rounds; only their row counts reach the driver.
    """
    current = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    print_of = lambda df: tuple(df.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
    seen = print_of(current)
    for _ in range(rounds):
        # larger neighbours go to the smallest of the node and its neighbours
        both = current.unionByName(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = _with_least(both).where("b > a").select(F.col("b").alias("a"), F.least("m", "a").alias("b")).where("a <> b").distinct()
        # smaller neighbours and the node itself go to the smallest of them
        low = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        small = _with_least(low).select(F.explode(F.array(F.struct(F.col("b").alias("x"), F.col("m")), F.struct(F.col("a").alias("x"), F.col("m")))).alias("e")).select(F.col("e.x").alias("a"), F.col("e.m").alias("b")).where("a <> b").distinct()
        current = materialise(small, "edges")
        now = print_of(current)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    stars = current.groupBy("a").agg(F.min("b").alias("root")).withColumnRenamed("a", "node")
    roots = stars.select(F.col("root").alias("node"), F.col("root")).distinct()
    return stars.unionByName(roots)
