"""Near-duplicate documents by BagMinHash signatures, banding and exact multiset overlap.

A document is the multiset of its shingles of five words (words as in ``textkernel``). A shingle's weight is its count,
which the integers discretise: weight w covers the unit steps 1 .. w. The steps are grouped into dyadic blocks (1, 2, 3-4,
5-8 ...); every (shingle, block) has a Poisson process in time whose rate is the block's length, and each of its points has
a register and a step. Points above w do not count, so a heavier document sees the points of a lighter one and more. A
register holds its earliest point: two documents agree in a register with a probability equal to their weighted Jaccard
similarity. Points later than the time by which all registers are filled are never generated; a document with a register
still empty is run again for longer.

Exact copies become one class first. Class representatives meet in bands of registers; every bucket of a band is then
searched exactly, in blocks of bounded size, by counting common shingle occurrences. Nothing is capped. A bucket too large for
one block is cut into blocks that all share a few leaders: a group of copies, however large, then is connected through its
leaders at a cost in proportion to its size. Members that are still apart from the bucket's largest connected part are
compared with all others, in pairs of blocks, so no link between parts is lost. Only the links that connect a block's
documents leave it, so a group of thousands does not turn into millions of pairs. A missed pair needs all bands to differ:
under 4e-5 at similarity 0.8.

Null and empty texts are one class (no words). Texts under five words are alike only if they are equal after trimming.
Repeated rows are copies with one id; rows of one id, whatever their texts, stay or go together: their classes are one
group. Rows without an id are copies of others or stay. An empty table gives an empty result. Clashing columns of the
input do not matter: only the id and the text are read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.llm import textkernel as K
from ctxloom.llm.components import components
from ctxloom.llm.textkernel import slices
from ctxloom.session import load, materialise

SHINGLE = 5
SIMILARITY = 0.8
BANDS, ROWS = 26, 5
BLOCK_UNITS = 400_000  # shingle occurrences on one side of a block pair
BLOCK_DOCS = 512
LEADERS = 24  # about so many members of a bucket of several blocks are in all of them, or a quarter of a block's occurrences


def shingles(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """Distinct (row, shingle) with counts, and the number of rows."""
    s = K.windows(K.words(texts), SHINGLE)
    return *K.counted(K.owners(s.starts), s.hashes), len(s.starts) - 1


def occurrence_sets(texts: pa.Array) -> list[np.ndarray]:
    """Each row's shingle occurrences as a sorted set of hashes: the k-th occurrence of a shingle is an element of its own,
    so the multiset overlap of two rows is the size of a set intersection."""
    row, key, count, rows = shingles(texts)
    nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    element = K.mix(np.repeat(key, count) + nth.astype(np.uint64) * K.GOLD)
    row = np.repeat(row, count)
    order = np.lexsort((element, row))
    return np.split(element[order], np.searchsorted(row, np.arange(1, rows)))


def _uniform(x: np.ndarray) -> np.ndarray:
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53


def bag_signatures(row: np.ndarray, key: np.ndarray, count: np.ndarray, rows: int, registers: int = BANDS * ROWS) -> np.ndarray:
    """(rows, registers) earliest times; rows without shingles stay at infinity."""
    times = np.full((rows, registers), np.inf)
    weight = np.bincount(row, count, rows)
    limit = np.where(weight > 0, registers * (np.log(registers) + 4) / np.maximum(weight, 1), 0)
    # one process per dyadic block that the weight reaches
    blocks = 1 + np.ceil(np.log2(count)).astype(np.int64)
    owner = np.repeat(np.arange(len(count)), blocks)
    level = np.arange(len(owner)) - np.repeat(np.cumsum(blocks) - blocks, blocks)
    p_row, p_weight = row[owner], count[owner]
    length = np.where(level == 0, 1, 2.0 ** np.maximum(level - 1, 0))
    below = np.where(level == 0, 0, length)
    seed = K.mix(key[owner] ^ K.mix(level.astype(np.uint64) + np.uint64(17)))
    open_rows = weight > 0
    while open_rows.any():
        alive = np.flatnonzero(open_rows[p_row])
        clock = np.zeros(len(alive))
        n = 0
        while len(alive):
            draw = K.mix(seed[alive] + K.stride(3 * n + 1))
            u = _uniform(draw)
            room = limit[p_row[alive]] - clock
            go = u >= np.exp(-room * length[alive])  # arrives in time
            alive, clock, u = alive[go], clock[go], u[go]
            clock = clock - np.log(u) / length[alive]
            extra = K.mix(seed[alive] + K.stride(3 * n + 2))
            step = below[alive] + _uniform(K.mix(extra)) * length[alive]
            counts = step < p_weight[alive]
            np.minimum.at(times, (p_row[alive][counts], (extra[counts] % np.uint64(registers)).astype(np.int64)), clock[counts])
            n += 1
        open_rows = np.isinf(times).any(axis=1) & (weight > 0)
        limit = np.where(open_rows, limit * 2, limit)
    return times


def band_keys(times: np.ndarray, bands: int = BANDS, per_band: int = ROWS) -> np.ndarray:
    bits = np.ascontiguousarray(times).view(np.uint64).reshape(len(times), bands, per_band)
    h = np.broadcast_to(K.mix(np.arange(bands, dtype=np.uint64)), (len(times), bands)).copy()
    for i in range(per_band):
        h = K.mix(h * np.uint64(3) + bits[:, :, i])
    return h.view(np.int64)


SIGNED = "id long, h long, class_key string, units long, bands array<long>"


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        texts = batch.column(1)
        row, key, count, rows = shingles(texts)
        units = np.bincount(row, count, rows).astype(np.int64)
        # a multiset's identity: two independent sums over its (shingle, count) pairs
        mixed = K.mix(key ^ K.mix(count.astype(np.uint64)))
        sums = [np.zeros(rows, np.uint64), np.zeros(rows, np.uint64)]
        for s, salt in zip(sums, (0x1234567, 0x89ABCDE)):
            np.add.at(s, row, K.mix(mixed ^ np.uint64(salt)))
        keys = [f"{a:016x}{b:016x}" if n else "=" + hashlib.sha256((t.as_py() or "").strip().encode()).hexdigest() for a, b, n, t in zip(sums[0].tolist(), sums[1].tolist(), units.tolist(), texts)]
        able = units > 3  # smaller multisets reach 0.8 only if they are equal
        pick = able[row]
        place = np.cumsum(able) - 1
        bands = band_keys(bag_signatures(place[row[pick]], key[pick], count[pick], int(able.sum())))
        lists = np.where(able, BANDS, 0)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(2), pa.array(keys, pa.string()), pa.array(units), pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(lists)]), pa.int32()), pa.array(bands.ravel()))],
            names=["id", "h", "class_key", "units", "bands"],
        )


def _link(left: list[np.ndarray], right: list[np.ndarray] | None, similarity: float) -> list[tuple[int, int]]:
    """Links that connect the documents of one block, or of a pair of blocks: indices into left + right.

    A document is compared with all documents before it (of the other block, if there are two) at once, over an index of
    their elements; a link is kept only if it joins parts that were apart.
    """
    docs = left + (right or [])
    sizes = np.array([len(d) for d in docs])
    doc = np.repeat(np.arange(len(docs)), sizes)
    element = np.concatenate(docs)
    order = np.argsort(element, kind="stable")
    element, doc = element[order], doc[order]
    new = np.ones(len(element), bool)
    new[1:] = element[1:] != element[:-1]
    start = np.flatnonzero(new)
    ends = np.append(start[1:], len(element))
    shared = ends - start > 1
    distinct, start, ends = element[start[shared]], start[shared], ends[shared]
    parent = list(range(len(docs)))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    links = []
    for i in range(len(left) if right else 1, len(docs)):
        at = np.searchsorted(distinct, docs[i])
        inside = at < len(distinct)
        at = at[inside][distinct[at[inside]] == docs[i][inside]]
        if not len(at):
            continue
        length = ends[at] - start[at]
        flat = np.arange(length.sum()) + np.repeat(start[at] - (np.cumsum(length) - length), length)
        most = len(left) if right else i
        common = np.bincount(doc[flat], minlength=len(docs))[:most]
        alike = np.flatnonzero(common * (1 + similarity) >= similarity * (sizes[:most] + sizes[i]) - 1e-9)
        for j in alike.tolist():
            a, b = root(i), root(j)
            if a != b:
                parent[max(a, b)] = min(a, b)
                links.append((i, j))
    return links


def _verify(similarity: float):
    seen = [0]

    def kernel(pdf: pd.DataFrame) -> pd.DataFrame:
        seen[0] += len(pdf)
        if seen[0] > 4 * BLOCK_DOCS:  # now and then, as most blocks are small
            seen[0] = 0
            K.release()
        pdf = pdf.drop_duplicates(["side", "id", "h"]).sort_values(["side", "id", "h"])
        sets = occurrence_sets(pa.array(pdf["text"], pa.string()))
        n, ids = int((pdf["side"] == 0).sum()), pdf["id"].to_numpy()
        found = _link(sets[:n], sets[n:] if len(sets) > n else None, similarity) if n else []
        return pd.DataFrame({"a": [ids[i] for i, _ in found], "b": [ids[j] for _, j in found]}, dtype="int64")

    return kernel


def _texts(docs: DataFrame) -> DataFrame:
    """id, text, and h, which tells texts of one id apart."""
    return docs.select(F.col("doc_id").cast("long").alias("id"), "text", F.xxhash64("text").alias("h"))


def sign(docs: DataFrame) -> DataFrame:
    return _texts(docs).mapInArrow(K.tidy(_sign), SIGNED)


def _links(docs: DataFrame, spread: DataFrame, similarity: float) -> DataFrame:
    """(a, b) that connect the documents of each block or pair of blocks; ``spread`` has the block's key, side, id and h."""
    texts = K.may_match(_texts(docs), ["id"], spread.select("id").distinct()).dropDuplicates(["id", "h"])
    return spread.join(texts, ["id", "h"]).groupBy("kind", "band", "bucket", "lo", "hi").applyInPandas(_verify(similarity), "a long, b long")


def _blocks(n: Column, load_: Column) -> Column:
    return F.greatest(F.lit(1), F.ceil(n / BLOCK_DOCS), F.ceil(load_ / BLOCK_UNITS)).cast("int")


def _apart(members: DataFrame, roots: DataFrame) -> DataFrame:
    """Members of buckets of several blocks that are not in the bucket's largest connected part, with the pairs of blocks in
    which they meet each other (kind 1) and that part (kind 2)."""
    rooted = members.where("parts > 1").join(roots, F.col("id") == F.col("node"), "left").select("id", "h", "units", "band", "bucket", "block", "parts", F.coalesce("root", "id").alias("root"))
    per = rooted.groupBy("band", "bucket", "root").agg(F.count("*").alias("n"), F.sum("units").alias("load"))
    most = per.groupBy("band", "bucket").agg(F.max(F.struct("n", "root")).alias("top"), F.sum("n").alias("n"), F.sum("load").alias("load"))
    top = per.join(most.select("band", "bucket", F.col("top.root").alias("main"), F.col("n").alias("all_n"), F.col("load").alias("all_load")), ["band", "bucket"]).where("root = main")
    open_ = top.where("n < all_n").select("band", "bucket", "main", _blocks(F.col("all_n") - F.col("n"), F.col("all_load") - F.col("load")).alias("rest_parts"))
    met = materialise(rooted.join(open_, ["band", "bucket"]).withColumn("rest", F.col("root") != F.col("main")), "apart")
    own = F.pmod(F.xxhash64("id", F.lit(7)), F.col("rest_parts")).cast("int")
    up_to = lambda n: F.sequence(F.lit(0), n - 1)
    key = lambda kind, lo, hi, side: F.struct(F.lit(kind).alias("kind"), lo.alias("lo"), hi.alias("hi"), side.alias("side"))
    each = F.transform(up_to(F.col("rest_parts")), lambda j: key(1, F.least("own", j), F.greatest("own", j), (F.col("own") != F.least("own", j)).cast("int")))
    against = F.transform(up_to(F.col("parts")), lambda j: key(2, F.col("own"), j, F.lit(0)))
    main = F.transform(up_to(F.col("rest_parts")), lambda j: key(2, j, F.col("block"), F.lit(1)))
    pairs = F.when(F.col("rest"), F.concat(each, against)).otherwise(main)
    return met.withColumn("own", own).select("id", "h", "band", "bucket", F.explode(pairs).alias("p")).select("id", "h", "band", "bucket", "p.*")


def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, class_id (least id among equal multisets), group_id (least id among all that links connect), keep."""
    signed = materialise(sign(docs), "signed")
    first = F.min(F.when(F.col("id").isNotNull(), F.struct("id", "h")))
    classes = signed.groupBy("class_key").agg(first.alias("f"), F.first("units").alias("units"), F.first("bands").alias("bands"))
    classes = materialise(classes.select("class_key", F.col("f.id").alias("class_id"), F.col("f.h").alias("h"), "units", "bands"), "classes")
    placed = classes.where((F.size("bands") > 0) & F.col("class_id").isNotNull()).select(F.col("class_id").alias("id"), "h", "units", F.posexplode("bands").alias("band", "bucket"))
    mark = F.xxhash64("id", "h")
    buckets = placed.groupBy("band", "bucket").agg(
        F.count("*").alias("n"), F.sum("units").alias("load"), F.min("id").alias("first"), F.bit_xor(mark).alias("x"), F.sum(mark.cast("decimal(38,0)")).alias("y")
    ).where("n > 1")
    # buckets of the same members are searched once
    groups = buckets.groupBy("n", "x", "y", "first").agg(F.min(F.struct("band", "bucket", "load")).alias("s")).select("n", "s.*")
    groups = groups.select("band", "bucket", "n", _blocks(F.col("n"), F.col("load")).alias("parts"))
    members = materialise(placed.join(groups, ["band", "bucket"]).withColumn("block", F.pmod(F.xxhash64("id", F.lit(5)), F.col("parts")).cast("int")), "members")
    share = F.least(F.lit(float(LEADERS)) / F.col("n"), F.lit(min(LEADERS, 0.25)) / F.col("parts"))
    leads = (F.col("parts") > 1) & (F.pmod(F.xxhash64("id", F.lit(3)), F.lit(1 << 30)) < share * float(1 << 30))
    places = F.when(leads, F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array("block"))
    spread = members.select("id", "h", "band", "bucket", F.explode(places).alias("lo"))
    spread = spread.select("id", "h", F.lit(0).alias("kind"), "band", "bucket", "lo", F.col("lo").alias("hi"), F.lit(0).alias("side"))
    links = materialise(_links(docs, spread, similarity), "links")
    roots = components(links)
    if not members.where("parts > 1").isEmpty():
        roots = materialise(roots, "roots")
        apart = materialise(_apart(members, roots), "apart")
        if not apart.isEmpty():
            more = _links(docs, apart, similarity)
            roots = components(roots.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(more))
    of_class = classes.select("class_key", "class_id").join(roots, F.col("class_id") == F.col("node"), "left").select("class_key", "class_id", F.coalesce("root", "class_id").alias("group_id"))
    return signed.select("id", "class_key").join(of_class, "class_key").select(F.col("id").alias("doc_id"), "class_id", "group_id", F.col("id").eqNullSafe(F.col("group_id")).alias("keep"))


def without_copies(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The documents of every group's least id, with all their columns. Rows of one id, and rows without one, stay or go together."""
    gone = near_duplicates(docs, similarity).groupBy(F.col("doc_id").alias("gone_id")).agg(F.max("keep").alias("k")).where("not k").select("gone_id")
    return K.without(docs, [F.col("doc_id").cast("long")], materialise(gone, "gone"))


def op5_bagminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "documents"))


QUERIES = {"op5_bagminhash": op5_bagminhash}
ORACLES: dict[str, str] = {}
