"""One query for each method, variant or measure that the experiments do not show by themselves. Most have SQL for another engine
(:mod:`ctxloom.plans.experiment_sql`)."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxloom.operators import adapt as A
from ctxloom.operators import baselines as B
from ctxloom.operators import cluster as K
from ctxloom.operators import coder as Z
from ctxloom.operators import counts as C
from ctxloom.operators import extras as X
from ctxloom.operators import hidden as H
from ctxloom.operators import merge as M
from ctxloom.operators import nested as N
from ctxloom.operators import rates as R
from ctxloom.operators.contexts import Position, Previous
from ctxloom.operators.soft import SoftMachine
from ctxloom.operators.stream import Stream, array_stream
from ctxloom.plans import streams as T
from ctxloom.session import load, materialise, shared_dir
from ctxloom.sources import reads as Q


def _tree_steps(s: SparkSession, tree: M.MergeTree) -> DataFrame:
    return tree.frame(s).select("step", "node", "left", "right", F.round("delta", 6).alias("delta"), F.round("loss", 6).alias("loss"))


def merge_steps_text42(s: SparkSession, d: str) -> DataFrame:
    """step, node, left, right, delta, loss of the whole order-1 tree, grown with one nearest partner a node."""
    stream = T.text42(s, d)
    return _tree_steps(s, M.build_tree(C.count_windows(stream, Previous(1)), stream.m))


def merge_steps_heap(s: SparkSession, d: str) -> DataFrame:
    """The order-3 tree grown with a heap of all pairs, down to eight nodes."""
    stream = T.class4(s, d)
    return _tree_steps(s, M.build_tree(C.count_windows(stream, Previous(3)), stream.m, queue="heap", stop_at=8))


def cuts_class4_order3(s: SparkSession, d: str) -> DataFrame:
    """rule, ctx, bin: the order-3 tree cut by loss, by bins, by gain, and by bins with the costliest node opened first."""
    stream = T.class4(s, d)
    tree = M.build_tree(C.count_windows(stream, Previous(3)), stream.m)
    out = None
    for name, rule, order in (("loss", M.MaxLoss(0.01), "reverse"), ("bins", M.MaxBins(6), "reverse"), ("gain", M.MinGain(0.001), "reverse"), ("bins, largest gain", M.MaxBins(6), "largest_gain")):
        row = M.bin_frame(s, tree.codes, M.cut(tree, rule, order)).select(F.lit(name).alias("rule"), "ctx", "bin")
        out = row if out is None else out.unionByName(row)
    return out


def cut_levels_text42(s: SparkSession, d: str) -> DataFrame:
    """bins, ctx, bin: one tree cut at three sizes."""
    stream = T.text42(s, d)
    tree = M.build_tree(C.count_windows(stream, Previous(1)), stream.m)
    out = None
    for k, cut in zip((2, 8, 16), M.cut_many(tree, [M.MaxBins(k) for k in (2, 8, 16)])):
        row = M.bin_frame(s, tree.codes, cut).select(F.lit(k).alias("bins"), "ctx", "bin")
        out = row if out is None else out.unionByName(row)
    return out


def trees_by_language(s: SparkSession, d: str) -> DataFrame:
    """lang, ctx, bin: a tree of order-2 contexts for every language, grown and cut on the executors."""
    stream = Stream(load(s, d, "documents"), "text", 4, "class", ("lang",))
    return M.build_trees(C.count_windows(stream, Previous(2), ("lang",)), "lang", 4, max_bins=4)


def best_partitions_ev5(s: SparkSession, d: str) -> DataFrame:
    """bins, bpv: the best of all partitions of the five contexts into at most so many sets."""
    _, table = C.matrix(C.count_windows(T.ev5(s, d), Previous(1)), 5)
    return s.createDataFrame([(k, round(B.best_partition(table, k) + 0.0, 6)) for k in range(1, 6)], "bins int, bpv double")


def cluster_variants_ev5(s: SparkSession, d: str) -> DataFrame:
    """variant, cluster, reads, bits: users' events under three models after three rounds from random, spread and first seeds,
    with length-weighted means of conditionals, with empty clusters dropped, and the better of two starts."""
    stream = T.ev5(s, d)
    stream = stream.with_df(materialise(stream.df, "users"))
    common = {"tol": -1, "max_iter": 3, "alpha": 0.5, "empty": "keep"}
    out = None
    for name, options in (
        ("random", {"init": "random"}), ("spread", {"init": "spread"}), ("first", {"init": "first"}), ("conditional", {"init": "first", "update": "conditional"}),
        ("drop", {"init": "random", "empty": "drop"}), ("seed 1", {"init": "random", "seed": 1}), ("restarts", {"init": "random", "restarts": 2}),
    ):
        found = K.cluster_models(stream, Previous(1), 3, **{**common, **options})
        row = found.assign(stream).groupBy("cluster").agg(F.count("*").alias("reads"), F.round(F.sum("bits"), 4).alias("bits")).select(F.lit(name).alias("variant"), "cluster", "reads", "bits")
        out = row if out is None else out.unionByName(row)
    return out


def _read_blocks(s: SparkSession, d: str) -> DataFrame:
    """block_no, syms: reads of the class stream as blocks of their own."""
    return T.reads(s, d, "class").frame().select(F.lit(0).cast("long").alias("block_no"), "syms")


def adaptive_orders_reads(s: SparkSession, d: str) -> DataFrame:
    """ord, n, adaptive, static bpv for orders 0 to 3 at shift 8, restarting in every read."""
    return A.adaptive_vs_static(_read_blocks(s, d), 4, list(range(4)), 8)


def sparse_updates_reads(s: SparkSession, d: str) -> DataFrame:
    """every, rate, n, bpv of order-1 functions that shift every u symbols of their context, restarting in every read."""
    stream, out = T.reads(s, d, "class"), None
    for every, rate in ((1, 8), (10, 5), (25, 2)):
        row = A.adaptive_context_bits(stream, Previous(1), rate, every).agg(F.sum("n").alias("n"), F.round(F.sum("bits") / F.sum("n"), 6).alias("bpv"))
        row = row.select(F.lit(every).alias("every"), F.lit(rate).alias("rate"), "n", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def fitted_rates_users(s: SparkSession, d: str) -> DataFrame:
    """block_no (user), n, eta, half_life, bpv: the forgetting rate of a grid that codes each user's events best."""
    blocks = T.ev5(s, d).df.select(F.col("user_id").alias("block_no"), "syms")
    found = A.fit_eta(blocks, 5, grid=[0.8, 0.9, 0.95, 0.98, 0.99, 0.995])
    return found.select("block_no", "n", "eta", F.round("half_life", 6).alias("half_life"), F.round("bpv", 6).alias("bpv"))


def soft_objective_ev5(s: SparkSession, d: str) -> DataFrame:
    """objective (nats) and mixture bits of a declared soft machine of two states over the users' events."""
    x, a = np.arange(5)[:, None], np.arange(2)[None, :]
    to_first = (1 + x) / (7.0 + a)
    e = np.stack([np.arange(1, 6) / 15.0, np.arange(5, 0, -1) / 15.0])
    soft = SoftMachine(2, 5, t=np.log(np.stack([to_first, 1 - to_first], axis=2)), d=np.log(e))
    value, _, _, mixed = soft.evaluate(T.ev5(s, d))
    return s.createDataFrame([(round(value, 4), round(mixed, 4))], "objective double, mixture_bits double")


def nestings_class4(s: SparkSession, d: str) -> DataFrame:
    """kind, states, lookups, n, bpv of small nestings of every kind over the windows from place 4 on."""
    stream = T.class4(s, d)
    found = [
        N.pair_binning(stream, 6), N.nest_symmetric(stream, [6, 12]), N.nest_asymmetric(stream, 6, 3), N.far_from_near(stream, 6, 1),
        N.nest_hierarchical(stream, 3, 2), N.nest_with(stream, Previous(1), Position(4, 4), 5), N.Nesting(Previous(4), 256, 4, "complete"),
    ]
    return N.compare_nestings(stream, found, 4)


def prefix_rate_text42(s: SparkSession, d: str) -> DataFrame:
    """n, prefix_bpv, ideal_bpv: a prefix code per order-1 context."""
    return Z.prefix_rate(C.count_windows(T.text42(s, d), Previous(1)), 42)


def _digest(df: DataFrame, *columns) -> DataFrame:
    return df.select(*columns, F.md5(F.concat_ws("", F.transform("syms", lambda x: x.cast("string"))).cast("binary")).alias("digest"))


def decoded_reads(s: SparkSession, d: str) -> DataFrame:
    """doc_id, read_no, n, digest of what the decoder makes of a container of all reads, coded with the cheaper of two models."""
    stream, spec = T.reads(s, d, "class"), Previous(2, "pad")
    counted = C.count_windows(stream.with_df(stream.df.withColumn("fold", (F.length("text") % 2).cast("int"))), spec, ("fold",))
    bits = np.stack([C.Model.from_matrix(spec, 4, *C.matrix(counted.where(f"fold = {k}"), 4), 0.5).bits for k in (0, 1)])
    coded = materialise(Z.encode(stream, spec, bits), "container")
    back = Z.decode(coded, ["doc_id"], 2, 4, bits, digits=True)
    return back.select("doc_id", "read_no", F.length("syms").alias("n"), F.md5(F.col("syms").cast("binary")).alias("digest"))


def decoded_adaptive(s: SparkSession, d: str) -> DataFrame:
    """user_id, digest of events coded under adaptive order-1 functions and decoded again."""
    return _digest(Z.adaptive_round_trip(T.ev5(s, d), Previous(1, "pad"), 1, 5), "user_id")


def position_symbol_rate(s: SparkSession, d: str) -> DataFrame:
    """n, contexts, bpv of a machine that keeps the last value with its coarse place, fed through the symbol."""
    table = np.tile(np.arange(32), (32, 1))
    return R.rate(C.count_windows(T.class4(s, d), H.machine(table, 0, 1, (16, 8))))


def long_machines(s: SparkSession, d: str, block: int = 100_000) -> DataFrame:
    """machine, n, contexts, bpv over all documents end to end as one sequence in chunks: a packed window, which forgets, with
    halos, and run lengths, which may not, by composed maps."""
    chunks = materialise(A.long_blocks(T.class4(s, d), block, tail="keep", digits=True).withColumn("seq", F.lit(0)), "chunks")
    window = H.chain_transition(H.Chain(4, np.arange(4), [np.array([0, 0, 1, 1])], [4, 2]))
    out = None
    for name, table in (("window", window), ("run length", H.run_length_transition(4, 4))):
        row = R.rate(H.count_chunks(chunks, "seq", "block_no", "syms", table, skip=2)).select(F.lit(name).alias("machine"), "n", "contexts", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def consensus_of_hosts(s: SparkSession, d: str) -> DataFrame:
    """n, flag_bpv, replacement_bpv, bpv of pages' first reads coded against their host's consensus, position by position."""
    hosts = load(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]*)", 1).alias("g"))
    reads = T.page101(s, d).frame().join(hosts, "page_id").select("g", "syms")
    return X.diff_rate(reads, X.consensus(reads, "g"), "g", 42)


def entropy_headers(s: SparkSession, d: str) -> DataFrame:
    """cluster, reads, bits when naming a language's model costs lg of its inverse share of the symbols."""
    stream = Stream(load(s, d, "documents"), "text", 4, "class", ("doc_id", "lang"), 101, "keep")
    counted = materialise(C.count_windows(stream, Previous(1), ("lang",)), "counts")
    langs = [r.lang for r in counted.select("lang").distinct().orderBy("lang").collect()]
    tables = np.zeros((len(langs), 4, 4))
    for r in counted.toLocalIterator():
        tables[langs.index(r.lang), r.ctx, r.sym] = r.n
    found = K.Clustering(Previous(1), 4, 0.5, tables, sizes=tables.sum(axis=(1, 2)))
    chosen = found.assign(stream, "entropy").where("n > 0")
    return chosen.groupBy("cluster").agg(F.count("*").alias("reads"), F.round(F.sum("bits"), 4).alias("bits"))


def contingency_langs(s: SparkSession, d: str) -> DataFrame:
    """cluster, label, reads: which of the languages' models codes the reads of each language cheapest."""
    stream = Stream(load(s, d, "documents"), "text", 4, "class", ("doc_id", "lang"), 101, "keep")
    counted = materialise(C.count_windows(stream, Previous(1), ("lang",)), "counts")
    langs = [r.lang for r in counted.select("lang").distinct().orderBy("lang").collect()]
    tables = np.zeros((len(langs), 4, 4))
    for r in counted.toLocalIterator():
        tables[langs.index(r.lang), r.ctx, r.sym] = r.n
    return R.contingency(K.Clustering(Previous(1), 4, 0.5, tables).assign(stream).where("n > 0"), "lang")


def read_file_rates(s: SparkSession, d: str) -> DataFrame:
    """symbols, n, contexts, bpv of a read file: all documents in reads whose bases are the letter classes and whose quality
    scores are the letters, written in the four-line format, read back by the source, and rated as bases, scores and both in
    one symbol, (score << 2) | base."""
    folder = f"{shared_dir(s)}/ctxloom-reads-{uuid.uuid4().hex}"
    Q.write_fastq(T.reads(s, d), folder)
    rows = Q.read_fastq(s, folder).select("read_id", Q.quality_codes(F.col("quality")).alias("q"), Q.base_codes(F.col("bases")).alias("b"))
    rows = materialise(rows.withColumn("both", F.zip_with("q", "b", lambda q, b: F.shiftleft(q, 2).bitwiseOR(b))), "reads")
    out = None
    for name, column, m in (("quality", "q", 42), ("bases", "b", 4), ("packed", "both", 168)):
        row = R.rate(C.count_windows(array_stream(rows, column, m), Previous(1))).select(F.lit(name).alias("symbols"), "n", "contexts", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def model_sizes(s: SparkSession, d: str) -> DataFrame:
    """ord, contexts, cells, bytes of a stationary model's table, and the compression ratio it reaches."""
    rated = B.order_rates(T.class4(s, d), [0, 1, 2, 3])
    sizes = s.createDataFrame([(k, *R.model_size(4**k, 4).values()) for k in range(4)], "ord int, contexts int, cells int, bytes int")
    ratio = R.ratio(F.col("bpv") * F.col("n"), F.col("n"), 4)
    return rated.select("ord", F.round(ratio, 6).alias("ratio")).join(sizes, "ord").select("ord", "contexts", "cells", "bytes", "ratio")


METHODS = {
    f.__name__: f
    for f in (
        merge_steps_text42, merge_steps_heap, cuts_class4_order3, cut_levels_text42, trees_by_language, best_partitions_ev5, cluster_variants_ev5, adaptive_orders_reads,
        sparse_updates_reads, fitted_rates_users, soft_objective_ev5, nestings_class4, prefix_rate_text42, decoded_reads, decoded_adaptive, position_symbol_rate, long_machines,
        consensus_of_hosts, entropy_headers, contingency_langs, read_file_rates, model_sizes,
    )
}
