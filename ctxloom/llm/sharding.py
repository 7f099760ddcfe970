"""Sharding by fixed virtual slots.

Every record hashes to one of a fixed number of virtual slots; only the slot-to-shard map decides where a slot lives.
Bytes are summed per slot, and rebalancing edits the map: it takes slots from shards above the mean and gives them to
shards below it, writing the result as the next version. Records never rehash. A later run over the same table finds the
last version in the shared folder and edits that.

Null, empty and repeated rows: a null text has no bytes (size 1), equal rows share a slot, a null key hashes by its text.
An empty table gives an empty result. Columns of the input beyond the key and the text are not read.
"""

from __future__ import annotations

import hashlib
import json
from dataclasses import dataclass

import numpy as np
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window

from ctxloom.session import load, shared_dir

SLOTS = 8192
CHUNKS = 8
MAP_SCHEMA = T.StructType([T.StructField("virtual_slot", T.IntegerType()), T.StructField("shard", T.IntegerType())])


def virtual_slot(key: Column, slots: int = SLOTS) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(slots)).cast("int")


@dataclass(frozen=True)
class SlotMap:
    """One version of the map: ``shard_of[slot]``. Its size is the slot count, whatever the data."""

    shard_of: np.ndarray
    shards: int
    version: int = 1

    @staticmethod
    def even(shards: int, slots: int = SLOTS) -> SlotMap:
        return SlotMap(np.arange(slots, dtype=np.int32) % shards, shards)

    def rebalanced(self, load_of: np.ndarray) -> SlotMap:
        """Move as few slots as it takes to bring the shards' loads near the mean; swaps settle what moves can't."""
        where, load_of = self.shard_of.copy(), np.asarray(load_of, float)
        total = np.bincount(where, load_of, self.shards)
        mean = total.sum() / self.shards
        for _ in range(4 * len(where)):
            heavy, light = int(total.argmax()), int(total.argmin())
            gap = total[heavy] - total[light]
            if gap <= max(1.0, mean * 1e-6):
                break
            own = np.flatnonzero((where == heavy) & (load_of > 0) & (load_of < gap))
            if len(own):
                want = min(total[heavy] - mean, mean - total[light])
                slot = own[np.abs(load_of[own] - want).argmin()]
                where[slot], moved = light, load_of[slot]
            else:  # no slot is small enough: exchange the pair whose difference is nearest to half the gap
                mine, theirs = np.flatnonzero(where == heavy), np.flatnonzero(where == light)
                if not len(mine) or not len(theirs):
                    break
                theirs = theirs[np.argsort(load_of[theirs], kind="stable")]
                at = np.clip(np.searchsorted(load_of[theirs], load_of[mine] - gap / 2), 0, len(theirs) - 1)
                best = np.abs(load_of[mine] - load_of[theirs[at]] - gap / 2).argmin()
                moved = load_of[mine[best]] - load_of[theirs[at[best]]]
                if not 0 < moved < gap:
                    break
                where[mine[best]], where[theirs[at[best]]] = light, heavy
            total[heavy] -= moved
            total[light] += moved
        return SlotMap(where, self.shards, self.version + 1)

    def grown(self) -> SlotMap:
        """One more shard: it takes every (shards + 1)-th slot of each old shard; no other slot moves."""
        where = self.shard_of.copy()
        for shard in range(self.shards):
            own = np.flatnonzero(self.shard_of == shard)
            where[own[:: self.shards + 1]] = self.shards
        return SlotMap(where, self.shards + 1, self.version + 1)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, int(s)) for i, s in enumerate(self.shard_of)], MAP_SCHEMA)

    def save(self, spark: SparkSession, folder: str) -> str:
        """Adds ``version=N`` to the folder; older versions stay readable."""
        path = f"{folder}/version={self.version}"
        self.frame(spark).coalesce(1).write.mode("overwrite").parquet(path)
        return path

    @staticmethod
    def load(spark: SparkSession, folder: str, version: int | None = None) -> SlotMap:
        rows = spark.read.parquet(folder)
        version = version or rows.agg(F.max("version")).first()[0]
        pairs = sorted((r.virtual_slot, r.shard) for r in rows.where(F.col("version") == version).collect())
        where = np.array([s for _, s in pairs], np.int32)
        return SlotMap(where, int(where.max()) + 1, int(version))

    @staticmethod
    def current(spark: SparkSession, folder: str, shards: int, load_of: np.ndarray) -> SlotMap:
        """The map for these loads: the last version of the folder (an even one where there is none yet), edited where shards
        are out of balance. Every edit is kept as a version of its own."""
        try:
            last = SlotMap.load(spark, folder)
        except AnalysisException:  # no version yet
            last = SlotMap.even(shards, len(load_of))
            last.save(spark, folder)
        edited = last.rebalanced(load_of)
        if (edited.shard_of == last.shard_of).all():
            return last
        edited.save(spark, folder)
        return SlotMap.load(spark, folder, edited.version)

    def to_json(self) -> str:
        return json.dumps({"version": self.version, "shards": self.shards, "shard_of": self.shard_of.tolist()})


def slot_loads(rows: DataFrame, slots: int = SLOTS) -> np.ndarray:
    """Bytes per virtual slot; ``rows`` has virtual_slot and size. Partial sums go to the shuffle, ``slots`` rows to the driver."""
    out = np.zeros(slots)
    for r in rows.groupBy("virtual_slot").agg(F.sum("size").alias("b")).collect():
        out[r.virtual_slot] = r.b
    return out


def assign(rows: DataFrame, slot_map: SlotMap) -> DataFrame:
    """Adds shard, and slot: the row's place in its shard, 0, 1, 2 ... without gaps.

    Places come from per-slot counts (a table of slots x chunks rows) plus a row number inside each small group, so no
    task holds a whole shard.
    """
    spark = rows.sparkSession
    rows = rows.withColumn("chunk", F.pmod(F.xxhash64("text_crc32", "size"), F.lit(CHUNKS)).cast("int"))
    shard = F.broadcast(slot_map.frame(spark))  # as many rows as there are virtual slots
    before = Window.partitionBy("shard").orderBy("virtual_slot", "chunk").rowsBetween(Window.unboundedPreceding, -1)
    base = (
        rows.groupBy("virtual_slot", "chunk")
        .agg(F.count("*").alias("n"))
        .join(shard, "virtual_slot")
        .select("virtual_slot", "chunk", "shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    )
    place = Window.partitionBy("virtual_slot", "chunk").orderBy("doc_id", "text_crc32", "size")
    return (
        rows.withColumn("place", F.row_number().over(place) - 1)
        .join(base, ["virtual_slot", "chunk"])
        .withColumn("slot", (F.col("base") + F.col("place")).cast("long"))
        .drop("chunk", "place", "base")
    )


def op1_virtual_slot_shards(spark: SparkSession, sf_dir: str, shards: int = 8) -> DataFrame:
    """All documents in ``shards`` shards whose bytes are near equal (law ``bytes``)."""
    text = F.encode(F.coalesce(F.col("text"), F.lit("")), "UTF-8")
    rows = load(spark, sf_dir, "documents").select(
        "doc_id",
        (F.octet_length(F.coalesce(F.col("text"), F.lit(""))) + 1).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.when(F.col("doc_id").isNull(), virtual_slot(text)).otherwise(virtual_slot(F.col("doc_id"))).alias("virtual_slot"),
    )
    folder = f"{shared_dir(spark)}/slot-map-{hashlib.sha256(sf_dir.encode()).hexdigest()[:16]}-{shards}"
    current = SlotMap.current(spark, folder, shards, slot_loads(rows.select("virtual_slot", "size")))
    return assign(rows, current).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot",
        F.lit(None).cast("int").alias("grown_shard"), "virtual_slot", F.lit(current.version).alias("map_version"),
    )


QUERIES = {"op1_virtual_slot_shards": op1_virtual_slot_shards}
ORACLES: dict[str, str] = {}
