"""Queries that SQL can express, each with its SQL for another engine (see :mod:`ctxloom.plans.oracles`)."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxloom.functions import symbols as S
from ctxloom.operators import adapt as A
from ctxloom.operators import baselines as B
from ctxloom.operators import cluster as K
from ctxloom.operators import counts as C
from ctxloom.operators import extras as X
from ctxloom.operators import hidden as H
from ctxloom.operators import merge as M
from ctxloom.operators import rates as R
from ctxloom.operators.contexts import Binned, ChangeCount, DelayedBin, From, Position, Previous, Product, RunningSum
from ctxloom.operators.stream import Stream, array_stream
from ctxloom.plans import streams as T
from ctxloom.session import load

# Declared bins for the fixed-bin queries: of four classes into two (letters and the rest).
LETTERS = np.array([0, 0, 1, 1])
ALPHA = 0.5


def rate_order0_text42(s: SparkSession, d: str) -> DataFrame:
    return B.order_rate(T.text42(s, d), 0)


def rate_order1_text42(s: SparkSession, d: str) -> DataFrame:
    return B.order_rate(T.text42(s, d), 1)


def rate_order2_text42(s: SparkSession, d: str) -> DataFrame:
    return B.order_rate(T.text42(s, d), 2)


def rate_order3_class4(s: SparkSession, d: str) -> DataFrame:
    return B.order_rate(T.class4(s, d), 3)


def rate_orders_class4(s: SparkSession, d: str) -> DataFrame:
    return B.order_rates(T.class4(s, d), list(range(9)))


def joint_counts_class4(s: SparkSession, d: str) -> DataFrame:
    return C.count_windows(T.class4(s, d), Previous(2))


def padded_counts_class4(s: SparkSession, d: str) -> DataFrame:
    """First values under a pad symbol of their own."""
    return C.count_windows(T.class4(s, d), Previous(1, "pad"))


def conditional_model_class4(s: SparkSession, d: str) -> DataFrame:
    model = C.conditional(C.count_windows(T.class4(s, d), Previous(1)))
    return model.select("ctx", "sym", "n", F.col("n_ctx").cast("long").alias("n_ctx"), F.round("p", 6).alias("p"), F.round("bits", 6).alias("bits"))


def smoothed_model_class4(s: SparkSession, d: str) -> DataFrame:
    model = C.conditional(C.smooth(C.count_windows(T.class4(s, d), Previous(3)), ALPHA, 64, 4))
    return model.select("ctx", "sym", F.round("p", 6).alias("p"), F.round("bits", 6).alias("bits"))


def entropy_sources(s: SparkSession, d: str) -> DataFrame:
    return R.entropy(load(s, d, "documents").groupBy("source").agg(F.count("*").alias("n")))


def cross_entropy_langs(s: SparkSession, d: str) -> DataFrame:
    """lang, n, bpv of each language's text under the English order-1 model (smoothed)."""
    stream = Stream(load(s, d, "documents"), "text", 42, "text", ("lang",))
    counted = C.count_windows(stream, Previous(1), ("lang",))
    english = C.conditional(C.smooth(counted.where("lang = 'en'").select("ctx", "sym", "n"), ALPHA, 42, 42)).select("ctx", "sym", "bits")
    joined = counted.join(english, ["ctx", "sym"])
    return joined.groupBy("lang").agg(F.sum("n").alias("n"), F.round(F.sum(F.col("n") * F.col("bits")) / F.sum("n"), 6).alias("bpv"))


def low_bits_curve(s: SparkSession, d: str) -> DataFrame:
    return B.low_bits_curve(T.text42(s, d), 1, [0, 1, 2, 3, 4])


def position_rate_page101(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.page101(s, d), Position(1, 101)))


def position_rate_emb16(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.emb16(s, d), Position(1, 64)))


def position_prev_rate(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.page101(s, d), Product((Position(1, 101), Previous(1)))))


def coarse_position_rate(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.page101(s, d), Position(10, 8)))


def change_count_rate(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.ev5(s, d), Product((ChangeCount(8, 4), Previous(1)))))


def running_sum_rate(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.ev5(s, d), RunningSum(8, 16)))


def overfit_text42_order1(s: SparkSession, d: str) -> DataFrame:
    return R.overfit(T.text42(s, d), Previous(1), F.col("doc_id") % 2)


def overfit_val42_order1(s: SparkSession, d: str) -> DataFrame:
    return R.overfit(T.val42(s, d), Previous(1), F.col("user_id") % 2)


def overfit_qty50_order1(s: SparkSession, d: str) -> DataFrame:
    return R.overfit(T.qty50(s, d), Previous(1), F.col("l_orderkey") % 2)


def pair_merge_costs_ev5(s: SparkSession, d: str) -> DataFrame:
    return M.all_pair_costs(C.count_windows(T.ev5(s, d), Previous(1)), 5)


def pair_merge_costs_class4(s: SparkSession, d: str) -> DataFrame:
    return M.all_pair_costs(C.count_windows(T.class4(s, d), Previous(2)), 4)


def _steps(spark: SparkSession, tree: M.MergeTree) -> DataFrame:
    mask = [1 << int(c) for c in tree.codes]
    rows = []
    for i, (a, b, x) in enumerate(zip(tree.left, tree.right, tree.delta), 1):
        mask.append(mask[a] | mask[b])
        rows.append((i, min(mask[a], mask[b]), max(mask[a], mask[b]), round(x + 0.0, 6), round(sum(tree.delta[:i]) + 0.0, 6)))
    return spark.createDataFrame(rows, "step int, a long, b long, delta double, loss double")


def greedy_tree_ev5(s: SparkSession, d: str) -> DataFrame:
    """step, the two merged sets as bit masks, delta, running loss."""
    return _steps(s, M.build_tree(C.count_windows(T.ev5(s, d), Previous(1)), 5))


def greedy_tree_class4(s: SparkSession, d: str) -> DataFrame:
    return _steps(s, M.build_tree(C.count_windows(T.class4(s, d), Previous(1)), 4))


def bins_ev5_k3(s: SparkSession, d: str) -> DataFrame:
    """ctx, bin for three bins, numbered by their least context."""
    tree = M.build_tree(C.count_windows(T.ev5(s, d), Previous(1)), 5)
    return M.bin_frame(s, tree.codes, M.cut(tree, M.MaxBins(3)))


def binned_rate_class4(s: SparkSession, d: str) -> DataFrame:
    """bins, n, bpv: the data counted again through each bin table of the tree."""
    stream = T.class4(s, d)
    tree = M.build_tree(C.count_windows(stream, Previous(1)), 4)
    out = None
    for k in (1, 2, 3, 4):
        bins = M.cut(tree, M.MaxBins(k))
        counted = M.rebin_counts(C.count_windows(stream, Previous(1)), M.bin_frame(s, tree.codes, bins)) if k % 2 else C.count_windows(stream, Binned(Previous(1), tuple(bins.tolist()), k))
        row = R.rate(counted).select(F.lit(k).alias("bins"), "n", "bpv")
        out = row if out is None else out.unionByName(row)
    return out


def applied_bins_ev5(s: SparkSession, d: str) -> DataFrame:
    """bin, n: event types through a literal bin table."""
    rows = load(s, d, "events").select(T.ev_code().alias("ctx"))
    return M.apply_bins(rows, (0, 1, 0, 1, 2)).groupBy("bin").agg(F.count("*").alias("n"))


def pack_pair_counts(s: SparkSession, d: str) -> DataFrame:
    rows = load(s, d, "events").select(S.pack_pair(T.val_code(), T.ev_code(), 3).alias("packed"))
    high, low = S.unpack_pair(F.col("packed"), 3)
    return rows.groupBy("packed").agg(F.count("*").alias("n")).select("packed", high.alias("high"), low.alias("low"), "n")


def pack_gain(s: SparkSession, d: str) -> DataFrame:
    return X.pack_gain(load(s, d, "events"), T.ev_code(), T.val_code())


def grouped_pairs_rate(s: SparkSession, d: str) -> DataFrame:
    return R.rate(C.count_windows(T.class4(s, d).grouped(2), Previous(1)))


def chain_state_rate_class4(s: SparkSession, d: str) -> DataFrame:
    """A packed window of two levels (value, letter or not) run as one machine, rated from place 2 on."""
    chain = H.Chain(4, np.arange(4), [LETTERS], [4, 2])
    return R.rate(H.count_states(T.class4(s, d), H.chain_transition(chain), 0, 2))


def nested_pair_rate_fixed(s: SparkSession, d: str) -> DataFrame:
    """Declared pair bins (letters or not of two values) reused two places earlier: order 4 from two lookups."""
    near = Binned(Previous(2), tuple(int(LETTERS[c % 4] + 2 * LETTERS[c // 4]) for c in range(16)), 4)
    return R.rate(C.count_windows(T.class4(s, d), Product((near, DelayedBin(near, 2)))))


def counter_machine_rate(s: SparkSession, d: str) -> DataFrame:
    """A machine that counts value changes up to 7 and remembers the last value."""
    return R.rate(H.count_states(T.ev5(s, d), H.counter_transition(5, 8), 0, 1))


def _class_reads(s: SparkSession, d: str) -> Stream:
    return Stream(load(s, d, "documents"), "text", 4, "class", ("doc_id", "lang"), 101)


def _lang_models(s: SparkSession, d: str) -> DataFrame:
    counted = C.count_windows(_class_reads(s, d), Previous(1), ("lang",))
    per = F.sum(F.col("n") + ALPHA).over(Window.partitionBy("lang", "ctx"))
    langs = counted.select("lang").distinct().withColumn("cluster", F.dense_rank().over(Window.orderBy("lang")) - 1)
    grid = langs.join(s.range(16).select(F.expr("id div 4").alias("ctx"), (F.col("id") % 4).cast("int").alias("sym")))
    full = grid.join(counted, ["lang", "ctx", "sym"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return full.withColumn("bits", F.log2(per / (F.col("n") + ALPHA))).select("cluster", "ctx", "sym", "bits")


def read_costs_fixed_models(s: SparkSession, d: str) -> DataFrame:
    """lang, cluster, reads: which of the languages' models codes the reads of each language cheapest."""
    counted = K.read_counts(_class_reads(s, d), Previous(1))
    keys = ["doc_id", "lang", "read_no"]
    chosen = K.assign_by_join(K.costs_by_join(counted, _lang_models(s, d), keys), keys)
    return chosen.groupBy("lang", "cluster").agg(F.count("*").alias("reads"), F.round(F.sum("bits"), 3).alias("bits"))


def kmeans_3_rounds(s: SparkSession, d: str) -> DataFrame:
    """cluster, reads, bits after three rounds of k = 3 from the first reads, on the events' sequences."""
    stream = T.ev5(s, d)
    found = K.cluster_models(stream, Previous(1), 3, init="first", tol=-1, max_iter=3, alpha=ALPHA, empty="keep")
    return found.assign(stream).groupBy("cluster").agg(F.count("*").alias("reads"), F.round(F.sum("bits"), 4).alias("bits"))


def header_cost(s: SparkSession, d: str) -> DataFrame:
    """flat_bpv, entropy_bpv of naming the language of each read."""
    reads = load(s, d, "documents").select(F.col("lang").alias("cluster"), F.explode(F.array_repeat(F.lit(101), F.floor(F.length("text") / 101).cast("int"))).alias("n"))
    return R.header_bpv(reads, 4)


def order_bits(s: SparkSession, d: str) -> DataFrame:
    n = load(s, d, "documents").count()
    return s.createDataFrame([(n, round(R.order_bits(n), 4))], "reads long, bits double")


def _emb_costs(s: SparkSession, d: str) -> DataFrame:
    """file, bits (of six fixed order-0 models) per event sequence: model j expects type j half of the time."""
    p = np.full((6, 1, 5), 0.125)
    p[np.arange(5), 0, np.arange(5)] = 0.5
    p[5] = 0.2
    costs = K.read_costs(T.ev5(s, d), Previous(0), -np.log2(p))
    return costs.withColumn("file", F.col("user_id") % 3)


def menu_greedy(s: SparkSession, d: str) -> DataFrame:
    return K.choose_menu(_emb_costs(s, d), "file", 6, 2).withColumn("bits", F.round("bits", 4))


def menu_best_pair(s: SparkSession, d: str) -> DataFrame:
    return K.choose_menu(_emb_costs(s, d), "file", 6, 2, "exhaustive").withColumn("bits", F.round("bits", 4))


def _values(s: SparkSession, d: str) -> DataFrame:
    rows = load(s, d, "events").groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.col("value").alias("v")))).alias("e"))
    return rows.select("user_id", F.transform("e", lambda x: x["v"]).alias("v"))


def ema_events(s: SparkSession, d: str) -> DataFrame:
    return _values(s, d).select("user_id", F.round(A.ema(F.col("v"), 0.9), 6).alias("ema"))


def ema_location_scale(s: SparkSession, d: str) -> DataFrame:
    rows = _values(s, d).select("user_id", A.ema_location_scale(F.col("v"), 0.9).alias("m"))
    return rows.select("user_id", F.round("m.centre", 6).alias("centre"), F.round("m.scale", 6).alias("scale"))


def ema_eta_grid(s: SparkSession, d: str) -> DataFrame:
    """eta, mse: squared error of predicting each value by the average before it."""
    out, rows = None, _values(s, d)
    for eta in (0.5, 0.8, 0.9, 0.95, 0.99):
        trail = F.arrays_zip(A.ema_trail(F.col("v"), eta).alias("p"), F.col("v").alias("x"))
        err = rows.select(F.explode(trail).alias("t")).agg(F.round(F.avg(F.pow(F.col("t.x") - F.col("t.p"), 2)), 4).alias("mse")).select(F.lit(eta).alias("eta"), "mse")
        out = err if out is None else out.unionByName(err)
    return out


def cdf_shift_events(s: SparkSession, d: str) -> DataFrame:
    """user_id, c1 .. c4: the adaptive distribution function after each user's events, in integers."""
    rows = T.ev5(s, d).df.select("user_id", A.cdf_after(F.col("syms"), 5, 4).alias("c"))
    return rows.select("user_id", *[F.get("c", F.lit(i)).alias(f"c{i}") for i in range(1, 5)])


def adaptive_order0_ev5(s: SparkSession, d: str) -> DataFrame:
    rows = T.ev5(s, d).df.select("user_id", F.round(A.cdf_bits(F.col("syms"), 5, 4), 6).alias("bits"))
    return rows


def adaptive_order1_ev5(s: SparkSession, d: str) -> DataFrame:
    """user_id, n, bits with one function per previous type."""
    return A.adaptive_context_bits(T.ev5(s, d), Previous(1), 4).select("user_id", "n", F.round("bits", 6).alias("bits"))


def half_life_table(s: SparkSession, d: str) -> DataFrame:
    """rate, docs, eta, half_life of the shifts that forget over about as many symbols as a document has: the rate is the place of
    the leading bit of its length (texts of one character or none have no such shift)."""
    n = F.length("text")
    rows = load(s, d, "documents").where(n >= 2).select((F.length(F.bin(n)) - 1).alias("rate")).groupBy("rate").agg(F.count("*").alias("docs"))
    return rows.withColumn("eta", A.eta_from_rate(F.col("rate"))).select("rate", "docs", F.round("eta", 9).alias("eta"), F.round(A.half_life(F.col("eta")), 6).alias("half_life"))


def rle_runs_role(s: SparkSession, d: str) -> DataFrame:
    """sym, length, n of the roles' runs (rows form)."""
    rows = load(s, d, "conversations")
    return B.runs(rows, "conv_id", ["turn"], S.encode_category(F.col("role"), S.ROLES)).groupBy("sym", "length").agg(F.count("*").alias("n"))


def rle_runs_class4(s: SparkSession, d: str) -> DataFrame:
    return B.run_lengths(T.class4(s, d))


def rle_rate_class4(s: SparkSession, d: str) -> DataFrame:
    return B.run_length_rate(B.run_lengths(T.class4(s, d)))


def _read_bits(s: SparkSession, d: str) -> DataFrame:
    """doc_id, lang, source, n, bits of each document under the pooled order-1 class model (smoothed)."""
    stream = Stream(load(s, d, "documents"), "text", 4, "class", ("doc_id", "lang", "source"))
    model = C.Model.fit(stream, Previous(1), ALPHA)
    return K.assign(K.read_costs(stream, Previous(1), model.bits[None])).select("doc_id", "lang", "source", "n", "bits")


def cube_bits(s: SparkSession, d: str) -> DataFrame:
    rows = _read_bits(s, d).cube("lang", "source").agg(F.sum("n").alias("n"), F.round(F.sum("bits") / F.sum("n"), 6).alias("bpv"))
    return rows


def rollup_bits(s: SparkSession, d: str) -> DataFrame:
    return _read_bits(s, d).rollup("lang", "source").agg(F.count("*").alias("docs"), F.round(F.sum("bits") / F.sum("n"), 6).alias("bpv"))


def topk_reads(s: SparkSession, d: str) -> DataFrame:
    """The three worst-coded documents of each language (a top-k report)."""
    w = Window.partitionBy("lang").orderBy(F.round(F.col("bits") / F.col("n"), 6).desc(), "doc_id")
    rows = _read_bits(s, d).where("n > 0").withColumn("place", F.row_number().over(w)).where("place <= 3")
    return rows.select("lang", "place", "doc_id", F.round(F.col("bits") / F.col("n"), 6).alias("bpv"))


def unseen_contexts_anti(s: SparkSession, d: str) -> DataFrame:
    """ctx, n: order-2 contexts of odd documents that even ones never show."""
    split = T.text42(s, d)
    counted = C.count_windows(split.with_df(split.df.withColumn("fold", (F.col("doc_id") % 2).cast("int"))), Previous(2), ("fold",))
    return counted.where("fold = 1").join(counted.where("fold = 0").select("ctx").distinct(), "ctx", "left_anti").groupBy("ctx").agg(F.sum("n").alias("n"))


def hourly_rate(s: SparkSession, d: str) -> DataFrame:
    """hour, n, bpv: entropy of event types by hour of day (hour as context)."""
    counted = load(s, d, "events").groupBy(F.hour("ts").alias("hour"), T.ev_code().alias("sym")).agg(F.count("*").alias("n"))
    return R.rate(counted.withColumn("ctx", F.lit(0)), "hour").select("hour", "n", "bpv")


def asof_model(s: SparkSession, d: str) -> DataFrame:
    """user_id, version, n: the latest model version at each event's time (as-of join by union and last value).

    Versions are the first event of each user's every tenth; models are only their ids here.
    """
    events = load(s, d, "events").select("user_id", "ts", "event_id")
    versions = events.where(F.col("event_id") % 10 == 0).select("user_id", "ts", F.col("event_id").alias("version"))
    both = events.withColumn("version", F.lit(None).cast("long")).unionByName(versions.withColumn("event_id", F.lit(None).cast("long")), allowMissingColumns=True)
    w = Window.partitionBy("user_id").orderBy("ts", F.col("version").isNull().cast("int")).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("v", F.last("version", True).over(w)).where("event_id is not null")
    return found.groupBy("user_id", F.col("v").alias("version")).agg(F.count("*").alias("n"))


def block_of_events(s: SparkSession, d: str) -> DataFrame:
    """block, n: range join of events with declared value blocks, bucketed by the blocks' width."""
    blocks = s.createDataFrame([(i, float(i * 60), float((i + 1) * 60)) for i in range(12)], "block int, low double, high double")
    events = load(s, d, "events").select("value", F.floor(F.col("value") / 60).alias("bucket"))
    keyed = blocks.withColumn("bucket", F.floor(F.col("low") / 60))
    return events.join(keyed, "bucket").where("value >= low and value < high").groupBy("block").agg(F.count("*").alias("n"))


def quality_by_rate(s: SparkSession, d: str) -> DataFrame:
    """quality, docs, bpv: labels joined with documents' bits."""
    return _read_bits(s, d).join(load(s, d, "labels"), "doc_id").groupBy("quality").agg(F.count("*").alias("docs"), F.round(F.sum("bits") / F.sum("n"), 6).alias("bpv"))


def event_props_rate(s: SparkSession, d: str) -> DataFrame:
    """n, contexts, bpv of event types given the JSON property k modulo 8."""
    k = (F.get_json_object("props", "$.k").cast("long") % 8).alias("ctx")
    return R.rate(load(s, d, "events").groupBy(k, T.ev_code().alias("sym")).agg(F.count("*").alias("n")))


def star_revenue_top(s: SparkSession, d: str) -> DataFrame:
    """segment, status pair counts of the star join: symbols (return flag, line status) by customer segment."""
    li = load(s, d, "lineitem").select("l_orderkey", "l_returnflag", "l_linestatus")
    orders = load(s, d, "orders").select("o_orderkey", "o_custkey")
    cust = load(s, d, "customer").select("c_custkey", "c_mktsegment")
    j = li.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(cust, F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("c_mktsegment", "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


def context_overlap(s: SparkSession, d: str) -> DataFrame:
    """kind, n: order-2 contexts that both folds show, and those only one does (set operations)."""
    split = T.class4(s, d)
    counted = C.count_windows(split.with_df(split.df.withColumn("fold", (F.col("doc_id") % 2).cast("int"))), Previous(3), ("fold",))
    a, b = (counted.where(f"fold = {k}").select("ctx") for k in (0, 1))
    size = lambda df, kind: df.agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
    return size(a.intersect(b), "both").unionByName(size(a.subtract(b), "even only")).unionByName(size(b.subtract(a), "odd only"))


def pivot_types_by_hour(s: SparkSession, d: str) -> DataFrame:
    """hour and a column of counts for each event type."""
    rows = load(s, d, "events").groupBy(F.hour("ts").alias("hour")).pivot("event_type", list(S.EVENT_TYPES)).count()
    return rows.fillna(0)


def bits_percentiles(s: SparkSession, d: str) -> DataFrame:
    """lang, p10, p50, p90 of bits per value over documents (exact percentiles)."""
    rows = _read_bits(s, d).where("n > 0").withColumn("bpv", F.col("bits") / F.col("n"))
    return rows.groupBy("lang").agg(*[F.round(F.percentile("bpv", p), 6).alias(f"p{int(p * 100)}") for p in (0.1, 0.5, 0.9)])


def session_lengths(s: SparkSession, d: str) -> DataFrame:
    """sessions, events: runs of a user's events with gaps of at most 30 days (gaps and islands), by number of events."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = load(s, d, "events").select("user_id", "ts", "event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))).alias("gap"))
    marked = rows.withColumn("session", F.sum((F.coalesce(F.col("gap"), F.lit(1 << 60)) > 30 * 86_400_000_000).cast("int")).over(w))
    return marked.groupBy("user_id", "session").agg(F.count("*").alias("events")).groupBy("events").agg(F.count("*").alias("sessions"))


def added_counts_class4(s: SparkSession, d: str) -> DataFrame:
    """ctx, sym, n: folds counted apart, added, and one fold subtracted again."""
    stream = T.class4(s, d)
    even = C.count_windows(stream.where("doc_id % 2 = 0"), Previous(1))
    odd = C.count_windows(stream.where("doc_id % 2 = 1"), Previous(1))
    return C.subtract_counts(C.add_counts(even, odd), odd)


RELATIONAL = {
    f.__name__: f
    for f in (
        rate_order0_text42, rate_order1_text42, rate_order2_text42, rate_order3_class4, rate_orders_class4, joint_counts_class4, padded_counts_class4, conditional_model_class4,
        smoothed_model_class4, entropy_sources, cross_entropy_langs, low_bits_curve, position_rate_page101, position_rate_emb16, position_prev_rate, coarse_position_rate,
        change_count_rate, running_sum_rate, overfit_text42_order1, overfit_val42_order1, overfit_qty50_order1, pair_merge_costs_ev5, pair_merge_costs_class4, greedy_tree_ev5,
        greedy_tree_class4, bins_ev5_k3, binned_rate_class4, applied_bins_ev5, pack_pair_counts, pack_gain, grouped_pairs_rate, chain_state_rate_class4, nested_pair_rate_fixed,
        counter_machine_rate, read_costs_fixed_models, kmeans_3_rounds, header_cost, order_bits, menu_greedy, menu_best_pair, ema_events, ema_location_scale, ema_eta_grid,
        cdf_shift_events, adaptive_order0_ev5, adaptive_order1_ev5, half_life_table, rle_runs_role, rle_runs_class4, rle_rate_class4, cube_bits, rollup_bits, topk_reads,
        unseen_contexts_anti, hourly_rate, asof_model, block_of_events, quality_by_rate, event_props_rate, star_revenue_top, context_overlap, pivot_types_by_hour, bits_percentiles, session_lengths, added_counts_class4,
    )
}
