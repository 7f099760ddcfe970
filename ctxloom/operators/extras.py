"""Joint coding of two streams, and differences from a consensus or a reference.

Sequences that share a stretch are found by minimizers: the least hash among the windows that begin in any SPAN neighbouring
places. Two sequences with a common stretch of WIDTH + SPAN - 1 symbols share one, wherever the stretch lies in either, and its
places tell how to lay one upon the other. Alignment is a shift; gaps are not modelled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxloom.operators import rates as R
from ctxloom.operators.stream import Flat, Stream, array_stream, pieces
from ctxloom.session import materialise, schema_with

WIDTH = 24
SPAN = 16
ANCHORS = 8
_ODD = np.uint64(0x9E3779B97F4A7C15)


def _scatter(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers whose order looks random."""
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def window_hashes(f: Flat, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the window that begins at each place, and whether it lies in one sequence: differences of weighted running sums,
    so the width costs nothing."""
    n = len(f.codes)
    if n < width:
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    power = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n, _ODD, np.uint64))])
    back = np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n, pow(int(_ODD), -1, 1 << 64), np.uint64))])
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((f.codes.astype(np.uint64) + np.uint64(1)) * power[:n])])
    begins = n - width + 1
    inside = np.repeat(f.size, f.size)[:begins] - f.position()[:begins] >= width
    return _scatter((sums[width:] - sums[:begins]) * back[:begins]), inside


def _minimizers(f: Flat, width: int, span: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of the minimizers, in order, and their hashes. A sequence with fewer than ``span`` windows has its least one."""
    h, inside = window_hashes(f, width)
    if not inside.any():
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    worst = np.uint64(0xFFFFFFFFFFFFFFFF)
    h = np.where(inside, np.minimum(h, worst - np.uint64(1)), worst)
    padded = np.concatenate([h, np.full(span - 1, worst)])
    least = np.lib.stride_tricks.sliding_window_view(padded, span)
    place = np.arange(len(h)) + least.argmin(axis=1)
    # a span that runs over its sequence's end would see the next one's windows: only whole spans and lone starts count
    owner = f.owner()
    room = np.maximum(f.size - width + 1, 0)[owner[: len(h)]] - f.position()[: len(h)]
    whole = inside & ((room >= span) | (f.position()[: len(h)] == 0))
    short = np.flatnonzero(whole & (room < span))
    for i in short:
        place[i] = i + int(h[i : i + int(room[i])].argmin())
    at = np.unique(place[whole])
    return at, h[at]


def minimizers(stream: Stream, width: int = WIDTH, span: int = SPAN) -> DataFrame:
    """ids, read_no, hash, at of every sequence; narrow."""
    flat, ids = stream.flat, list(stream.ids)
    schema = schema_with(T.StructType([stream.df.schema[c] for c in ids]), "read_no int, hash long, at int")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            f = flat(batch.column(0))
            at, h = _minimizers(f, width, span)
            owner = f.owner()[at]
            cols = [batch.column(i + 1).take(pa.array(f.row[owner])) for i in range(len(ids))]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(f.nth[owner], pa.int32()), pa.array(h.view(np.int64)), pa.array(f.position()[at], pa.int32())], names=schema.names)

    return stream.select(*ids).mapInArrow(kernel, schema)


def similar_groups(sequences: DataFrame, m: int, syms: str = "syms", anchors: int = ANCHORS, width: int = WIDTH) -> DataFrame:
    """g, syms, shift: sequences that share many of their least window hashes with different ones, wherever these lie.

    Every distinct sequence offers the ``anchors`` least hashes of its windows. One of which at least half are offered by
    others, too, joins the group of the rarest such hash (ties: the least), so a stretch that very many share does not
    swallow near copies; one that is left alone there joins the group of a partner. ``shift`` is that window's place: it lays the group's sequences upon one another. Sequences without
    a partner have no group.
    """
    keyed = materialise(sequences.where(F.size(syms) > 0).groupBy(F.xxhash64(syms).alias("key"), F.col(syms).alias("syms")).agg(F.count("*").alias("copies")), "sequences")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = array_stream(None, "syms", m).flat
        for batch in pieces(batches):
            f = read(batch.column(0))
            h, inside = window_hashes(f, width)
            at = np.flatnonzero(inside)
            owner = f.owner()[at]
            order = np.lexsort((at, h[at], owner))
            at, owner = at[order], owner[order]
            new = np.ones(len(at), bool)  # the first place of each hash
            new[1:] = (owner[1:] != owner[:-1]) | (h[at][1:] != h[at][:-1])
            at, owner = at[new], owner[new]
            rank = np.arange(len(at)) - np.searchsorted(owner, owner)
            at, owner = at[rank < anchors], owner[rank < anchors]
            yield pa.RecordBatch.from_arrays([batch.column(1).take(pa.array(owner)), pa.array(h[at].view(np.int64)), pa.array(f.position()[at], pa.int32())], names=["key", "hash", "at"])

    offered = materialise(keyed.select("syms", "key").mapInArrow(kernel, "key long, hash long, at int"), "anchors")
    shared = offered.groupBy("hash").agg(F.countDistinct("key").alias("n")).where("n > 1")
    own = offered.join(shared, "hash", "left").groupBy("key").agg(F.count("*").alias("all"), F.count("n").alias("common"), F.min(F.when(F.col("n").isNotNull(), F.struct("n", "hash", "at"))).alias("b"))
    best = materialise(own.where("common > 0 and 2 * common >= all").select("key", F.col("b.hash").alias("g"), F.col("b.at").alias("shift")), "chosen")
    full = best.groupBy("g").agg(F.count("*").alias("n")).where("n > 1").select("g")
    first = materialise(best.join(full, "g"), "grouped")
    # one whose partners all chose otherwise joins them through a hash that it has in common with a group's member
    doors = offered.join(first, "key").groupBy("hash").agg(F.min(F.struct("g", (F.col("at") - F.col("shift")).alias("rel"))).alias("d"))
    late = best.select("key").join(first.select("key"), "key", "left_anti").join(offered, "key").join(doors, "hash")
    late = late.groupBy("key").agg(F.min(F.struct("d.g", (F.col("at") - F.col("d.rel")).alias("shift"))).alias("b")).select("key", "b.g", "b.shift")
    found = first.select("key", "g", "shift").unionByName(late)
    return keyed.join(found, "key").select("g", "syms", "shift", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("c")).drop("c")


def nearest_reference(stream: Stream, references: Stream, width: int = WIDTH, span: int = SPAN) -> DataFrame:
    """ids, read_no, reference (its ids as one string), shift, hits: the reference, and how it is laid, that most minimizers of
    the sequence speak for (ties: the least reference, then the least shift). Sequences without any are left out.

    Both sides are joined on the hash; hits are counted before anything is compared, so a stretch that many share costs one
    row a place and reference.
    """
    name = F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in references.ids], F.col("read_no").cast("string"))
    known = minimizers(references, width, span).select("hash", name.alias("reference"), F.col("at").alias("there"))
    keys = [*stream.ids, "read_no"]
    met = minimizers(stream, width, span).join(known, "hash").groupBy(*keys, "reference", (F.col("at") - F.col("there")).alias("shift")).agg(F.count("*").alias("hits"))
    best = F.min(F.struct((-F.col("hits")).alias("neg"), "reference", "shift")).alias("b")
    return met.groupBy(*keys).agg(best).select(*keys, "b.reference", "b.shift", (-F.col("b.neg")).alias("hits"))


def pack_gain(rows: DataFrame, a: Column, b: Column) -> DataFrame:
    """n, h_a, h_b, h_ab and gain = h_a + h_b - h_ab bits a pair. One aggregation by pair; the margins are sums of it."""
    pairs = rows.groupBy(a.alias("a"), b.alias("b")).agg(F.count("*").alias("n"))
    x = R.xlog2x
    over = lambda c: F.sum("n").over(Window.partitionBy(c))
    wide = pairs.select("n", (F.col("n") * F.log2(over("a"))).alias("la"), (F.col("n") * F.log2(over("b"))).alias("lb"), x(F.col("n")).alias("lab"))
    n = F.sum("n")
    base = F.log2(n)
    h = lambda c: base - F.sum(c) / n
    return wide.agg(n.alias("n"), F.round(h("la"), 6).alias("h_a"), F.round(h("lb"), 6).alias("h_b"), F.round(h("lab"), 6).alias("h_ab"), F.round(h("la") + h("lb") - h("lab"), 6).alias("gain"))


def consensus(reads: DataFrame, group: str, syms: str = "syms", shift: str | None = None) -> DataFrame:
    """group, syms, first: the most frequent symbol at each place of the group's reads (ties: the least).

    Places are counted from a read's ``shift``, or from its begin; ``first`` is the least one. Places are counted before the
    group is put together, so a large group is only as long as its reads reach.
    """
    place = F.col("at") - (F.col(shift) if shift else F.lit(0))
    placed = reads.select(group, *([shift] if shift else []), F.posexplode(syms).alias("at", "sym")).groupBy(group, place.alias("at"), "sym").agg(F.count("*").alias("n"))
    best = placed.groupBy(group, "at").agg(F.max(F.struct("n", (-F.col("sym")).alias("neg"))).alias("b"))
    ordered = F.array_sort(F.collect_list(F.struct("at", (-F.col("b.neg")).alias("sym"))))
    return best.groupBy(group).agg(F.transform(ordered, lambda x: x["sym"]).alias("syms"), F.min("at").alias("first"))


def diff_rate(reads: DataFrame, references: DataFrame, group: str, m: int, syms: str = "syms", shift: str | None = None) -> DataFrame:
    """n, flag_bpv, replacement_bpv, bpv: each symbol as a mismatch flag against its reference, then a replacement if needed.

    With ``shift``, a read's place 0 lies on the reference's place -shift - first (``first`` from :func:`consensus`, or 0).
    Symbols beyond the reference's ends count as mismatches.
    """
    first = F.col("first") if "first" in references.columns else F.lit(0)
    ref = references.select(F.col(group).alias("_g"), F.col("syms").alias("ref"), first.alias("_first"))
    joined = reads.select(F.col(group).alias("g"), F.col(syms).alias("x"), (F.col(shift) if shift else F.lit(0)).alias("_shift")).join(ref, F.col("g").eqNullSafe(F.col("_g")))
    place = F.col("at") - F.col("_shift") - F.col("_first")
    cells = joined.select(F.posexplode("x").alias("at", "sym"), "ref", "_shift", "_first").select("sym", (F.coalesce(F.when(place >= 0, F.get("ref", place)), F.lit(-1)) != F.col("sym")).cast("int").alias("miss"))
    per = cells.groupBy("miss", "sym").agg(F.count("*").alias("n"))
    flags = per.groupBy("miss").agg(F.sum("n").alias("k"), F.sum(R.xlog2x(F.col("n"))).alias("g"))
    n = F.sum("k")
    flag_bits = R.xlog2x(n) - F.sum(R.xlog2x(F.col("k")))
    swap_bits = F.sum(F.when(F.col("miss") == 1, R.xlog2x(F.col("k")) - F.col("g")).otherwise(0.0))
    return flags.agg(n.alias("n"), F.round(flag_bits / n + 0.0, 6).alias("flag_bpv"), F.round(swap_bits / n + 0.0, 6).alias("replacement_bpv"), F.round((flag_bits + swap_bits) / n + 0.0, 6).alias("bpv"))
