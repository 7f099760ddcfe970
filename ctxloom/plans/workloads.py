"""The experiments, re-expressed on the given tables. Each returns a small table of what it measures."""

from __future__ import annotations

import math

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
from ctxloom.operators.contexts import Binned, From, LowBits, Position, Previous, Product, handmade
from ctxloom.operators.soft import SoftMachine, harden, sheets
from ctxloom.operators.stream import Stream, array_stream, text_stream
from ctxloom.plans import streams as T
from ctxloom.session import load, materialise

#: Symbols of a block of the concatenated sequence, whatever its length; the last block is shorter.
BLOCK = 1_000_000


def rows_of(spark: SparkSession, schema: str, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def binning(spark: SparkSession, stream: Stream, spec, loss: float = 0.01) -> DataFrame:
    """measure, bins, bpv: no context, the complete one, and the fewest bins within the loss."""
    codes, table = C.matrix(C.count_windows(stream, spec), stream.m)
    tree = M.tree_of(codes, table)
    bins = M.cut(tree, M.MaxLoss(loss))
    none = float(M.excess(table.sum(axis=0)[None]).sum() / tree.total)
    k = int(bins.max()) + 1
    rows = [("none", 1, none), ("complete", tree.leaves, tree.full_rate()), ("binned", k, M.binned_rate(tree, bins))]
    rows += [("range bins", k, M.binned_rate(tree, B.range_bins(tree.leaves, k))), ("random bins", k, M.binned_rate(tree, B.random_bins(tree.leaves, k)))]
    return rows_of(spark, "measure string, bins int, bpv double", [(a, b, round(c, 6)) for a, b, c in rows])


def w1_binning_text42(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning(spark, T.text42(spark, sf_dir), Previous(1))


def w1_loss_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """bins, bpv of the tree, and of dropped low bits where that gives as many bins."""
    stream = T.text42(spark, sf_dir)
    tree = M.build_tree(C.count_windows(stream, Previous(1)), stream.m)
    low = {b: r for b, r in ((42, None), *[(LowBits(1, d).size(42), d) for d in (1, 2, 3, 4)])}
    dropped = {b: M.binned_rate(tree, tree.codes >> d) for b, d in low.items() if d}
    return rows_of(spark, "bins int, bpv double, low_bits_bpv double", [(b, round(x, 6), round(dropped[b], 6) if b in dropped else None) for b, x in M.loss_curve(tree)])


def w2_binning_class4_order3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return binning(spark, T.class4(spark, sf_dir), Previous(3))


def page_streams(spark: SparkSession, sf_dir: str) -> dict[str, Stream]:
    """All reads of the whole pages, tails too; and, beside them, the first reads of the pages that have 101 characters."""
    return {"all": T.page_reads(spark, sf_dir), "first read only": T.page101(spark, sf_dir)}


def w3_position_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """reads, and bin, first, last, members, runs of the positions' bins: runs = 1 where a bin is a range."""
    out = None
    for reads, stream in page_streams(spark, sf_dir).items():
        codes, table = C.matrix(C.count_windows(stream, Position(1, 101)), stream.m)
        bins = M.cut(M.tree_of(codes, table), M.MaxLoss(0.01))
        row = M.bin_ranges(M.bin_frame(spark, codes, bins)).select(F.lit(reads).alias("reads"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def w3_position_previous(spark: SparkSession, sf_dir: str) -> DataFrame:
    """reads, context, contexts, training, held_out on pages: none, position, previous value, both, hand-made."""
    fold = F.col("page_id") % 2
    both = Product((Position(1, 101), Previous(1)))
    out = None
    for reads, stream in page_streams(spark, sf_dir).items():
        specs = {"none": From(Previous(0), 1), "position": From(Position(1, 101), 1), "previous": Previous(1), "both": both, "handmade": handmade(42)}
        for name, spec in specs.items():
            row = R.overfit(stream, spec, fold, 0.1).select(F.lit(reads).alias("reads"), "*", F.lit(name).alias("context"), F.lit(spec.size(stream.m)).alias("contexts"))
            out = row if out is None else out.unionByName(row)
    return out


def w3_position_controls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """stream, context, n, training, held_out: position on streams that should gain little or nothing by it."""
    first = lambda kind: text_stream(load(spark, sf_dir, "documents").where(F.length("text") >= 101).select("doc_id", F.substring("text", 1, 101).alias("head")), "head", kind)
    out = None
    for name, stream, key, places in (("emb16", T.emb16(spark, sf_dir), "vec_id", 64), ("first reads, text42", first("text"), "doc_id", 101), ("first reads, class4", first("class"), "doc_id", 101)):
        for context, spec in (("none", Previous(0)), ("position", Position(1, places))):
            row = R.overfit(stream, spec, F.col(key) % 2, 0.1).select(F.lit(name).alias("stream"), F.lit(context).alias("context"), "n", "training", "held_out")
            out = row if out is None else out.unionByName(row)
    return out


def w3_position_previous_binned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """reads, contexts, bins, training, held_out: position and previous value binned together into 64."""
    both = Product((Position(1, 101), Previous(1)))
    out = None
    for reads, stream in page_streams(spark, sf_dir).items():
        codes, table = C.matrix(C.count_windows(stream, both), stream.m)
        cut = M.cut(M.tree_of(codes, table), M.MaxBins(64))
        binned = Binned(both, M.dense_table(codes, cut, both.size(stream.m)), 64)
        row = R.overfit(stream, binned, F.col("page_id") % 2, 0.1).select(F.lit(reads).alias("reads"), F.lit(len(codes)).alias("contexts"), F.lit(64).alias("bins"), "n", "training", "held_out")
        out = row if out is None else out.unionByName(row)
    return out


def position_rates_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """context, n, contexts, bpv over whole pages: what the SQL-checked page101 queries give for first reads only."""
    out = None
    for name, spec in (("position", Position(1, 101)), ("position, previous", Product((Position(1, 101), Previous(1)))), ("coarse position", Position(10, 8))):
        row = R.rate(C.count_windows(T.page_reads(spark, sf_dir), spec)).select(F.lit(name).alias("context"), "n", "contexts", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def w4_nestings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """kind, states, lookups, n, bpv, held_out of nestings at 64 and 256 states over the windows from place 4 on, beside complete
    and truncated contexts."""
    stream = T.text42(spark, sf_dir)
    found = [
        N.pair_binning(stream, 64), N.pair_binning(stream, 256), N.nest_symmetric(stream, [64, 256]), N.nest_symmetric(stream, [64, 64]),
        N.nest_asymmetric(stream, 64, 4), N.far_from_near(stream, 64, 4), N.nest_hierarchical(stream, 64, 4),
        N.Nesting(LowBits(2, 3), 36, 1, "low bits, order 2"), N.Nesting(Previous(1), 42, 1, "complete, order 1"), N.Nesting(Previous(2), 1764, 1, "complete, order 2"),
    ]
    return N.compare_nestings(stream, found, 4, F.col("doc_id") % 2)


def w4_order8_text42(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The symmetric ladder of the 42 symbols up to order 8: three lookups in place of 42^8 contexts."""
    stream = T.text42(spark, sf_dir)
    found = [N.nest_symmetric(stream, [64, 64, 256]), N.nest_symmetric(stream, [64, 64]), N.pair_binning(stream, 64), N.Nesting(Previous(1), 42, 1, "complete, order 1"), N.Nesting(Previous(0), 1, 0, "none")]
    return N.compare_nestings(stream, found, 8, F.col("doc_id") % 2)


def w4_order8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Symmetric ladder up to order 8 with three lookups, over the windows from place 8 on."""
    stream = T.class4(spark, sf_dir)
    found = [N.nest_symmetric(stream, [16, 64, 256]), N.nest_symmetric(stream, [16, 64]), N.pair_binning(stream, 16), N.Nesting(Previous(8), 4**8, 8, "complete, order 8"), N.Nesting(Previous(0), 1, 0, "none")]
    return N.compare_nestings(stream, found, 8)


def w5_packed_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """machine, states, n, bpv: chained bins packed in one table, against the same bins computed apart."""
    stream = T.text42(spark, sf_dir)
    lags = H.lag_tables(stream, 8)
    plans = (("16-4-2-2", [16, 4, 2, 2], "levels"), ("16-4-2-2 one tree", [16, 4, 2, 2], "one_tree"), ("8-8-4", [8, 8, 4], "levels"), ("2^8", [2] * 8, "levels"))
    chains = [H.bin_chain(stream, sizes, mode, lags) for _, sizes, mode in plans]
    machines = [H.machine(H.chain_transition(c), 0, c.depth) for c in chains]
    rated = R.rate(C.count_many(stream, machines), "spec")
    names = rows_of(spark, "spec int, machine string, states int", [(i, p[0], len(x.table)) for i, (p, x) in enumerate(zip(plans, machines))])
    return names.join(rated, "spec").select("machine", "states", "n", "bpv")


def w6_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """stream, machine, n, states, bpv: counter and run-length machines on the class stream's reads and on word lengths, each
    stream's valued in one pass."""
    out = None
    for name, stream in (("class4", T.reads(spark, sf_dir, "class")), ("wordlen16", T.wordlen16(spark, sf_dir))):
        m = stream.m
        window = H.chain_transition(H.bin_chain(stream, [4, 2]))
        row = H.search_machines(stream, {
            "none": np.zeros((1, m), int), "last value": np.tile(np.arange(m), (m, 1)), "changes": H.counter_transition(m, 16), "run length": H.run_length_transition(m, 4),
            "window": window, "window x changes": H.product_transition(window, H.counter_transition(m, 8)),
        }, skip=2).select(F.lit(name).alias("stream"), "machine", "n", "states", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def w7_soft_machine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """stream, states, soft_bpv, hard_bpv, order0_bpv, order1_bpv: learnt machines on all class reads, a deterministic and a null stream."""
    whole = T.class4(spark, sf_dir)
    cores = spark.sparkContext.defaultParallelism
    if whole.df.rdd.getNumPartitions() < cores:  # a small table may come as one partition: each pass is spread over all cores
        whole = whole.with_df(whole.df.select(whole.payload).repartition(cores))
    whole = whole.cut(101, "keep")
    rows = []
    for name, stream, states in (("class4", whole, 4), ("role3", T.role3(spark, sf_dir), 3), ("ev5", T.ev5(spark, sf_dir), 2)):
        stream = stream.with_df(materialise(stream.df.select(stream.payload), "soft"))
        words = sheets(stream)
        soft = SoftMachine(states, stream.m, seed=1, jitter=0.3).fit(words, 25, 0.3)
        n = R.rate(C.count_windows(stream, Previous(0))).first()
        table = harden(soft, words, refit=1)  # one transition a time
        hard = R.rate(H.count_states(stream, table)).first()["bpv"]
        one = R.rate(C.count_windows(stream, Previous(1, "pad"))).first()["bpv"]
        rows.append((name, states, round(-max(soft.history) / math.log(2) / n["n"], 6), hard, n["bpv"], one))
    return rows_of(spark, "stream string, states int, soft_bpv double, hard_bpv double, order0_bpv double, order1_bpv double", rows)


def clusters(spark: SparkSession, stream: Stream, spec, sizes: tuple[int, ...], label: str, alpha: float = 0.1) -> DataFrame:
    """k, reads, model_bpv, header_flat, header_entropy, total_bpv, purity by label, chance (that of shuffled labels), rounds."""
    out = None
    for k in sizes:
        found = K.cluster_models(stream, spec, k, init="spread", alpha=alpha, max_iter=8, tol=1e-3)
        done = materialise(found.assign(stream).join(stream.df.select(*stream.ids, label), list(stream.ids), "left"), "assigned")
        row = (
            R.total_bpv(done, k).crossJoin(R.header_bpv(done, k)).crossJoin(R.purity(done, label)).crossJoin(R.chance(done, label, [*stream.ids, "read_no"])).crossJoin(done.agg(F.count("*").alias("reads")))
            .select(F.lit(k).alias("k"), "reads", "model_bpv", "flat_bpv", "entropy_bpv", "total_bpv", "purity", "chance", F.lit(len(found.history)).alias("rounds"))
        )
        out = row if out is None else out.unionByName(row)
    return out


def w8_clusters_text42(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = T.reads(spark, sf_dir)
    return clusters(spark, Stream(stream.df, "text", 42, "text", ("doc_id",), 101, "keep"), Previous(1), (1, 2, 4, 8), "lang")


def w9_clusters_class4(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")
    return clusters(spark, Stream(docs, "text", 4, "class", ("doc_id",), 101, "keep"), Previous(1), (1, 2, 4, 8), "quality")


def w9_position_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Position models on the control stream: purity stays at what a shuffled label gives."""
    stream = T.emb16(spark, sf_dir)
    return clusters(spark, stream, Position(1, 64), (10,), "label")


def cluster_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """cluster, bucket, reads: bits a value under each of four order-1 models."""
    stream = T.reads(spark, sf_dir)
    found = K.cluster_models(stream, Previous(1), 4, init="spread", max_iter=5)
    return K.cluster_report(found.assign(stream), 0.1).withColumn("bucket", F.round("bucket", 6))


def selector_context(spark: SparkSession, sf_dir: str) -> DataFrame:
    """models, contexts, bpv: one model, four models, and one four times larger model with the selector in its context."""
    stream = T.reads(spark, sf_dir, "class")
    found = K.cluster_models(stream, Previous(1), 4, init="spread", max_iter=5)
    bits = found.bits().reshape(4, -1)
    spec = K.Selected(Previous(1), 4, tuple(map(tuple, bits.tolist())))
    one = R.rate(C.count_windows(stream, Previous(1))).select(F.lit("one").alias("models"), "contexts", "bpv")
    large = R.rate(C.count_windows(stream, spec)).select(F.lit("selector").alias("models"), "contexts", "bpv")
    four = R.total_bpv(found.assign(stream), 4).select(F.lit("four").alias("models"), F.lit(16).cast("long").alias("contexts"), F.col("model_bpv").alias("bpv"))
    return one.unionByName(large).unionByName(four)


def blocks_of(spark: SparkSession, sf_dir: str, block: int) -> tuple[DataFrame, int]:
    stream = T.class4(spark, sf_dir)
    total = stream.df.agg(F.sum(F.length("text"))).first()[0] or 0
    # a partition per block: the scans are sequential inside a block and independent across blocks
    return A.long_blocks(stream, block, tail="keep").repartitionByRange(max(1, -(-total // block)), "block_no"), stream.m


def w10_half_lives(spark: SparkSession, sf_dir: str, block: int = BLOCK) -> DataFrame:
    """block_no, n, eta, half_life, bpv per pair of neighbouring symbols, of the best forgetting rate in each block. An odd last symbol has no pair."""
    blocks, m = blocks_of(spark, sf_dir, block)
    from ctxloom.functions.symbols import group_symbols

    pairs = blocks.select("block_no", group_symbols(F.col("syms"), 2, m).alias("syms"))
    found = A.fit_eta(pairs, m * m)
    return found.select("block_no", "n", *[F.round(c, 6).alias(c) for c in ("eta", "half_life", "bpv")])


def w11_adaptive_orders(spark: SparkSession, sf_dir: str, block: int = BLOCK) -> DataFrame:
    """ord, n, adaptive, static bpv for orders 0 to 8 at shift 8."""
    blocks, m = blocks_of(spark, sf_dir, block)
    return A.adaptive_vs_static(blocks, m, list(range(9)), 8)


def w12_sparse_updates(spark: SparkSession, sf_dir: str, block: int = BLOCK) -> DataFrame:
    """every, rate, n, bpv of order-1 adaptive functions that shift every u symbols."""
    blocks, m = blocks_of(spark, sf_dir, block)
    stream = array_stream(materialise(blocks, "blocks"), "syms", m, ("block_no",))
    out = None
    for every, rate in ((1, 8), (10, 5), (100, 2)):
        row = A.adaptive_context_bits(stream, Previous(1), rate, every).agg(F.sum("n").alias("n"), F.round(F.sum("bits") / F.sum("n"), 6).alias("bpv"))
        row = row.select(F.lit(every).alias("every"), F.lit(rate).alias("rate"), "n", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def cdf_path(spark: SparkSession, sf_dir: str, block: int = BLOCK) -> DataFrame:
    """block_no, at, ctx, cdf: order-1 functions along the sequence, every 1000 symbols."""
    blocks, m = blocks_of(spark, sf_dir, block)
    return A.cdf_trace(blocks, m, 1, 8, 1000)


def w13_library(spark: SparkSession, sf_dir: str) -> DataFrame:
    """files, reads, model_bpv, total_bpv of 20 models trained on all reads and cut to a menu of four a file, for three kinds of
    file; beside them four models for everything, and four models trained on each language by itself."""
    stream = Stream(load(spark, sf_dir, "documents"), "text", 4, "class", ("doc_id", "lang", "source"), 101, "keep")
    library = K.train_library(stream, Previous(2), 20, init="random", max_iter=4, seed=3)
    costs = materialise(K.read_costs(stream, Previous(2), library.bits()), "library")
    k, out = library.k, None
    every = costs.withColumn("every", F.lit("all"))
    total = lambda df, name: df.agg(F.count("*").alias("reads"), F.round(F.sum("bits") / F.sum("n"), 6).alias("model_bpv"), F.round((F.sum("bits") + 2 * F.count("*")) / F.sum("n"), 6).alias("total_bpv")).select(F.lit(name).alias("files"), "*")
    for file in ("every", "lang", "source"):
        frame = every if file == "every" else costs
        row = total(K.menu_costs(frame, K.choose_menu(frame, file, k, 4), file), file)
        out = row if out is None else out.unionByName(row)
    four = {"init": "random", "max_iter": 4, "seed": 3}
    out = out.unionByName(total(K.cluster_models(stream, Previous(2), 4, **four).assign(stream), "four for all"))
    own = None
    for r in load(spark, sf_dir, "documents").select("lang").distinct().orderBy("lang").collect():  # a file a language
        part = stream.where(F.col("lang").eqNullSafe(F.lit(r.lang)))
        row = K.cluster_models(part, Previous(2), 4, **four).assign(part).select("bits", "n")
        own = row if own is None else own.unionByName(row)
    return out if own is None else out.unionByName(total(own, "four a language"))


def soft_switching(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, bpv: model chosen in the header, switched by past symbols (mixture or best), and one model."""
    stream = T.reads(spark, sf_dir, "class")
    found = K.cluster_models(stream, Previous(1), 4, init="spread", max_iter=5)
    one = K.cluster_models(stream, Previous(1), 1, max_iter=2)
    total = lambda df, name: df.agg(F.round(F.sum("bits") / F.sum("n"), 6).alias("bpv")).select(F.lit(name).alias("method"), "bpv")
    header = R.total_bpv(found.assign(stream), 4).select(F.lit("header").alias("method"), F.col("total_bpv").alias("bpv"))
    out = header.unionByName(total(K.soft_switch(stream, Previous(1), found.bits()), "mixture"))
    out = out.unionByName(total(K.soft_switch(stream, Previous(1), found.bits(), mixture=False), "best so far"))
    return out.unionByName(total(one.assign(stream), "one model"))


def w14_joint_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """pair, n, h_a, h_b, h_ab, gain of coding two streams together."""
    events = X.pack_gain(load(spark, sf_dir, "events"), T.ev_code(), T.val_code()).withColumn("pair", F.lit("event type, value"))
    lines = X.pack_gain(load(spark, sf_dir, "lineitem"), F.col("l_returnflag"), F.col("l_linestatus")).withColumn("pair", F.lit("return flag, line status"))
    return events.unionByName(lines)


def similar_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """g, syms, shift: documents' texts that share a rare stretch with a different one, laid upon one another at that stretch."""
    return materialise(X.similar_groups(T.text42(spark, sf_dir).frame(), 42), "similar")


def _alone(frame: DataFrame, spark: SparkSession) -> DataFrame:
    """method, n, bpv of the same sequences coded without a partner."""
    frame = frame.select("syms")
    none = R.rate(C.count_windows(array_stream(frame, "syms", 42), Previous(0))).select(F.lit("order 0").alias("method"), "n", "bpv")
    return none.unionByName(R.rate(C.count_windows(array_stream(frame, "syms", 42), Previous(1, "pad"))).select(F.lit("order 1").alias("method"), "n", "bpv"))


def w15_consensus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, n, bpv: near copies coded against their group's consensus, beside independent coding. Groups and their layout
    come from shared stretches anywhere in the whole texts; insertions inside a text are not modelled."""
    near = similar_texts(spark, sf_dir)
    cons = materialise(X.consensus(near, "g", shift="shift"), "consensus")
    coded = X.diff_rate(near, cons, "g", 42, shift="shift").select(F.lit("consensus").alias("method"), "n", "bpv")
    return coded.unionByName(_alone(near, spark))


def w15_reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sequences, method, n, bpv: consensus sequences of the groups, and all reads of all documents, that have a near benchmark
    passage, coded against the nearest one as it lies, beside coding without it."""
    passages = Stream(load(spark, sf_dir, "benchmark"), "text", 42, "text", ("item_id",))
    refs = passages.frame().select(F.concat_ws("|", F.col("item_id").cast("string"), F.col("read_no").cast("string")).alias("reference"), "syms")
    refs = materialise(refs, "references")
    cons = materialise(X.consensus(similar_texts(spark, sf_dir), "g", shift="shift").select("g", "syms"), "consensus")
    out = None
    for name, stream in (("consensus", array_stream(cons, "syms", 42, ("g",)).cut(101, "keep")), ("reads", T.text42(spark, sf_dir).cut(101, "keep"))):
        keys = [*stream.ids, "read_no"]
        found = materialise(X.nearest_reference(stream, passages), "nearest")
        frame = stream.frame()
        same = F.lit(True)
        for k in keys:
            same = same & frame[k].eqNullSafe(found[k])
        near = materialise(frame.join(found, same).select(frame["syms"], "reference", "shift"), "near")
        coded = X.diff_rate(near, refs, "reference", 42, shift="shift").select(F.lit("nearest reference").alias("method"), "n", "bpv")
        row = coded.unionByName(_alone(near, spark)).select(F.lit(name).alias("sequences"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def w16_read_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """reads, order_bits, bits_per_read: what a free order of reads is worth."""
    n = load(spark, sf_dir, "documents").agg(F.sum(F.ceil(F.length("text") / 101))).first()[0] or 0
    return rows_of(spark, "reads long, order_bits double, bits_per_read double", [(n, round(R.order_bits(n), 3), round(R.order_bits(n) / max(n, 1), 6))])


def w17_null_controls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """stream, none and order-1 training and held-out rates over the same windows: controls gain nothing held out."""
    out = None
    for name, stream, key in (("ev5", T.ev5(spark, sf_dir), "user_id"), ("val42", T.val42(spark, sf_dir), "user_id"), ("qty50", T.qty50(spark, sf_dir), "l_orderkey"), ("wordlen16", T.wordlen16(spark, sf_dir), "doc_id"), ("text42", T.text42(spark, sf_dir), "doc_id")):
        fold = F.col(key) % 2
        none = R.overfit(stream, From(Previous(0), 1), fold).select("n", F.col("training").alias("none_training"), F.col("held_out").alias("none_held_out"))
        one = R.overfit(stream, Previous(1), fold).select(F.col("training").alias("order1_training"), F.col("held_out").alias("order1_held_out"))
        row = none.crossJoin(one).select(F.lit(name).alias("stream"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def w18_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """reads, wrong, payload_bits, ideal_bits: two models' container over every symbol of every document, decoded and compared.

    Reads are compared as a bag of (doc_id, read_no, syms), so rows without an id or with the same id count, too.
    """
    stream = T.class4(spark, sf_dir).cut(101, "keep")
    spec = Previous(2, "pad")
    found = K.cluster_models(stream, spec, 2, init="spread", max_iter=4)
    coded = materialise(Z.encode(stream, spec, found.bits()), "container")
    back = Z.decode(coded, ["doc_id"], 2, 4, found.bits(), True)
    side = lambda df, sign: df.select("doc_id", "read_no", "syms", F.lit(sign).alias("side"))
    left = side(stream.frame(digits=True), 1).unionByName(side(back, -1)).groupBy("doc_id", "read_no", "syms").agg(F.sum(F.greatest("side", F.lit(0))).alias("reads"), F.sum("side").alias("over"))
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    wrong = left.agg(total("reads").alias("reads"), F.greatest(total(F.greatest("over", F.lit(0))), total(F.greatest(-F.col("over"), F.lit(0)))).alias("wrong"))
    size = coded.agg(F.sum(F.length("payload") * 8).alias("payload_bits"))
    ideal = K.read_costs(stream, spec, found.bits()).agg(F.round(F.sum(F.array_min("bits")), 3).alias("ideal_bits"))
    return wrong.crossJoin(size).crossJoin(ideal)


def baseline_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, n, bpv: raw sizes, prefix code, run lengths, block sorting, order 0."""
    stream = T.reads(spark, sf_dir, "class")
    counted = C.count_windows(stream, Previous(0))
    prefix = Z.prefix_rate(counted, 4)
    n = R.rate(counted)
    out = n.select(F.lit("order 0").alias("method"), "n", "bpv")
    out = out.unionByName(n.select(F.lit("raw").alias("method"), "n", F.lit(2.0).alias("bpv")))
    out = out.unionByName(prefix.select(F.lit("prefix code").alias("method"), "n", F.col("prefix_bpv").alias("bpv")))
    out = out.unionByName(B.run_length_rate(B.run_lengths(stream)).select(F.lit("run lengths").alias("method"), "n", "bpv"))
    sorted_ = array_stream(B.block_sorted(stream), "syms", 4)
    return out.unionByName(R.rate(C.count_windows(sorted_, Previous(1, "pad"))).select(F.lit("block sorting, order 1").alias("method"), "n", "bpv"))


def two_level_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """ctx, bin, coarse: 32 fine bins whose numbers shifted by 3 give a coarser binning."""
    stream = T.text42(spark, sf_dir)
    codes, table = C.matrix(C.count_windows(stream, Previous(1)), stream.m)
    bins, _ = M.two_level(codes, table, 32, 3)
    return M.bin_frame(spark, codes, bins).withColumn("coarse", F.shiftright("bin", 3))


def integer_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """bits, loss_bpv: what power-of-two integer frequencies cost against ideal ones."""
    stream = T.text42(spark, sf_dir)
    _, table = C.matrix(C.count_windows(stream, Previous(1)), stream.m)
    p = table / table.sum(axis=1, keepdims=True)
    return rows_of(spark, "bits int, loss_bpv double", [(b, round(Z.quantization_loss(p, table.sum(axis=1), b), 6)) for b in (8, 10, 12, 14)])


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits per value of none / binned (loss at most 0.01) / complete order-1 contexts, counted again through the bin table."""
    stream = T.text42(spark, sf_dir)
    counted = materialise(C.count_windows(stream, Previous(1)), "counts")
    codes, table = C.matrix(counted, stream.m)
    bins = M.cut(M.tree_of(codes, table), M.MaxLoss(0.01))
    spec = Binned(Previous(1), M.dense_table(codes, bins, stream.m), int(bins.max()) + 1)
    binned = R.rate(C.count_windows(stream, spec))
    none = R.rate(counted.groupBy(F.lit(0).cast("long").alias("ctx"), "sym").agg(F.sum("n").alias("n")))
    name = lambda df, x: df.select(F.lit(x).alias("method"), "n", "contexts", "bpv")
    return name(none, "none").unionByName(name(binned, "binned")).unionByName(name(R.rate(counted), "complete"))


WORKLOADS = {
    f.__name__: f
    for f in (
        flagship, w1_binning_text42, w1_loss_curve, w2_binning_class4_order3, w3_position_bins, w3_position_previous, w3_position_previous_binned, w3_position_controls, position_rates_pages, w4_nestings, w4_order8, w4_order8_text42, w5_packed_windows, w6_counters,
        w7_soft_machine, w8_clusters_text42, w9_clusters_class4, w9_position_clusters, cluster_histogram, selector_context, w10_half_lives, w11_adaptive_orders,
        w12_sparse_updates, cdf_path, w13_library, soft_switching, w14_joint_gain, w15_consensus, w15_reference, w16_read_order, w17_null_controls, w18_round_trip, baseline_codes, two_level_bins, integer_loss,
    )
}
