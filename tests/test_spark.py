"""Operators on Spark against brute force, over edge cases and partitionings."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ctxloom.functions import registry, symbols as S
from ctxloom.operators import adapt as A
from ctxloom.operators import baselines as B
from ctxloom.operators import cluster as K
from ctxloom.operators import coder as Z
from ctxloom.operators import counts as C
from ctxloom.operators import extras as E
from ctxloom.operators import hidden as H
from ctxloom.operators import merge as M
from ctxloom.operators import nested as N
from ctxloom.operators import rates as R
from ctxloom.operators import contexts as X
from ctxloom.operators.soft import SoftMachine, harden, sheets
from ctxloom.operators.stream import array_stream, text_stream
from ctxloom.plans import streams as T
from tests.helpers import flat, markov, stream_of


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def test_symbols(spark):
    df = spark.createDataFrame([("Ab é.\n!ß",), ("",), (None,)], "text string")
    native = df.select(S.encode_text(F.col("text")).alias("c")).collect()
    kernel = text_stream(df, ids=()).frame().collect()
    assert native[0].c == kernel[0].syms == [2, 3, 0, 28, 40, 1, 41, 36] or native[0].c == kernel[0].syms
    assert kernel[1].syms == kernel[2].syms == []
    assert text_stream(df, kind="class", ids=()).frame().first().syms == [0, 1, 2, 0, 3, 2, 3, 1]
    x = spark.createDataFrame([(3, 5, [0, 1, 2, 3, 1], 12.5, "b")], "h int, l int, a array<int>, v double, t string")
    r = x.select(S.pack_pair(F.col("h"), F.col("l"), 3).alias("p"), S.group_symbols(F.col("a"), 2, 4).alias("g"), S.group_symbols(F.col("a"), 2, 4, True).alias("o"),
                 S.quantize(F.col("v"), 12, 41).alias("q"), S.quantize(F.col("v"), edges=[1, 10, 20]).alias("e"), S.encode_category(F.col("t"), ("a", "b")).alias("c")).first()
    assert (r.p, r.g, r.o, r.q, r.e, r.c) == (29, [1, 11], [1, 6, 11, 13], 1, 2, 1)
    assert [b.x for b in x.select(*[c.alias("x") for c in S.unpack_pair(F.lit(29), 3)][:1]).collect()] == [3]
    assert S.raw_bits(42) == 6


@pytest.mark.parametrize("parts", [1, 4, 16])
def test_counts_do_not_depend_on_partitions(spark, sf, parts):
    stream = T.class4(spark, sf)
    a = rows(C.count_windows(stream, X.Previous(2)), "ctx", "sym", "n")
    b = rows(C.count_windows(stream.with_df(stream.df.repartition(parts)), X.Previous(2)), "ctx", "sym", "n")
    assert a == b


def test_counts_edges(spark):
    s = stream_of(spark, [[0, 1, 1], [], None, [1]], 2)
    assert rows(C.count_windows(s, X.Previous(1)), "ctx", "sym", "n") == [(0, 1, 1), (1, 1, 1)]
    assert rows(C.count_windows(s, X.Previous(3)), "ctx", "sym", "n") == []
    empty = stream_of(spark, [], 2)
    assert C.count_windows(empty, X.Previous(1)).count() == 0 and R.rate(C.count_windows(empty, X.Previous(1))).count() == 1
    one = stream_of(spark, [[0, 0, 0]], 1)
    assert R.rate(C.count_windows(one, X.Previous(0))).first().bpv == 0
    by = C.count_windows(s, X.Previous(0), ("id",))
    assert rows(by, "id", "ctx", "sym", "n") == [(0, 0, 0, 1), (0, 0, 1, 2), (3, 0, 1, 1)]
    assert rows(s.cut(2).frame(), "id", "read_no", "syms") == [(0, 0, [0, 1])]
    assert rows(s.cut(2, "keep").frame(), "id", "read_no", "syms") == [(0, 0, [0, 1]), (0, 1, [1]), (3, 0, [1])]


def test_count_algebra(spark, sf):
    a = C.count_windows(T.class4(spark, sf), X.Previous(2))
    assert rows(C.subtract_counts(C.add_counts(a, a), a), "ctx", "sym", "n") == rows(a, "ctx", "sym", "n")
    lower = C.marginal(a, 4).groupBy("ctx").agg(F.sum("n").alias("n")).agg(F.sum("n")).first()[0]
    assert lower == a.agg(F.sum("n")).first()[0]
    sm = C.conditional(C.smooth(a, 0.1, 16, 4))
    assert sm.count() == 64 and abs(sm.agg(F.sum("p")).first()[0] - 16) < 1e-9
    assert abs(R.bpv(a, C.conditional(a)).first().bpv - R.rate(a).first().bpv) < 1e-6
    doubled = C.scale_counts(a, 2.0)
    assert R.rate(doubled.withColumn("n", F.col("n"))).first().bpv == R.rate(a).first().bpv


def test_model_save_and_cost(spark, sf, tmp_path):
    s = T.class4(spark, sf)
    model = C.Model.fit(s, X.Previous(1), 0.5)
    model.save(spark, str(tmp_path / "m"))
    again = C.Model.load(spark, str(tmp_path / "m"), X.Previous(1))
    assert np.allclose(model.bits, again.bits) and model.size() == 16
    total = model.cost(s).agg(F.sum("bits"), F.sum("n")).first()
    assert abs(total[0] / total[1] - R.rate(C.count_windows(s, X.Previous(1))).first().bpv) < 1e-3


def test_backends_agree(spark, sf):
    counts = C.count_windows(T.text42(spark, sf), X.Previous(1))
    heap, near = M.build_tree(counts, 42, "heap"), M.build_tree(counts, 42)
    assert heap.left == near.left and heap.right == near.right
    rounds = M.build_tree(counts, 42, backend="rounds")
    assert len(rounds.left) == len(near.left)
    assert M.binned_rate(rounds, M.cut(rounds, M.MaxBins(8))) < M.binned_rate(near, M.cut(near, M.MaxBins(8))) + 0.1
    tree = near.frame(spark)
    assert tree.count() == len(near.left) and tree.agg(F.max("loss")).first()[0] == pytest.approx(sum(near.delta))


def test_grouped_trees_and_apply(spark, sf):
    counts = C.count_windows(T.class4(spark, sf), X.Previous(2))
    per = counts.select((F.col("ctx") % 4).alias("near"), F.expr("ctx div 4").alias("ctx"), "sym", "n")
    got = M.build_trees(per, "near", 4, max_bins=2)
    assert got.groupBy("near").agg(F.countDistinct("bin").alias("b")).agg(F.max("b")).first()[0] == 2
    bins = M.bin_frame(spark, np.arange(4), np.array([0, 0, 1, 1]))
    df = spark.range(5).withColumnRenamed("id", "ctx")
    assert rows(M.apply_bins(df, bins, fallback=7), "ctx", "bin") == [(0, 0), (1, 0), (2, 1), (3, 1), (4, 7)]
    assert rows(M.apply_bins(df, (0, 0, 1, 1), fallback=7), "ctx", "bin") == [(0, 0), (1, 0), (2, 1), (3, 1), (4, 7)]
    ranges = rows(M.bin_ranges(bins), "bin", "first", "last", "members", "runs")
    assert ranges == [(0, 0, 1, 2, 1), (1, 2, 3, 2, 1)]


def test_identity_nesting_is_the_full_order(spark, sf):
    s = T.class4(spark, sf)
    near = X.Binned(X.Previous(2), tuple(range(16)), 16)
    both = R.rate(C.count_windows(s, X.Product((near, X.DelayedBin(near, 2))))).first()
    full = R.rate(C.count_windows(s, X.Previous(4))).first()
    assert (both.n, both.bpv) == (full.n, full.bpv)
    h = N.nest_hierarchical(s, 16, 16)
    assert abs(R.rate(C.count_windows(s, X.From(h.spec, 4))).first().bpv - full.bpv) < 1e-6
    shifted = N.far_from_near(s, 12, 2)
    assert R.rate(C.count_windows(s, X.From(shifted.spec, 4))).first().bpv >= full.bpv - 1e-9


def test_clusters_recover_a_planted_mixture(spark):
    r = np.random.default_rng(7)
    a, b = [[0.9, 0.1], [0.1, 0.9]], [[0.1, 0.9], [0.9, 0.1]]
    truth = [i % 2 for i in range(60)]
    s = stream_of(spark, [markov(r, (a, b)[t], 80) for t in truth], 2)
    found = K.cluster_models(s, X.Previous(1), 2, init="spread", alpha=0.5, max_iter=10, tol=0)
    got = {x.id: x.cluster for x in found.assign(s).collect()}
    agree = sum(got[i] == t for i, t in enumerate(truth))
    assert agree in (0, 60)
    assert all(x >= y - 1e-6 for x, y in zip(found.penalised, found.penalised[1:]))
    one = K.cluster_models(s, X.Previous(1), 1, init="first", alpha=1e-9, max_iter=3, tol=-1)
    assert abs(one.history[-1] / (60 * 79) - R.rate(C.count_windows(s, X.Previous(1))).first().bpv) < 1e-4
    drop = K.cluster_models(s, X.Previous(1), 5, init="random", empty="drop", update="conditional", max_iter=4)
    assert 1 <= drop.k <= 5
    costs = np.array([x.bits for x in K.read_costs(s, X.Previous(1), found.bits()).orderBy("id").collect()])
    assert costs.argmin(axis=1).tolist() == [got[i] for i in range(60)]
    switched = K.soft_switch(s, X.Previous(1), found.bits()).agg(F.sum("bits")).first()[0]
    assert switched < one.history[-1]


def test_relational_twin(spark, sf):
    s = T.ev5(spark, sf)
    found = K.cluster_models(s, X.Previous(1), 3, init="first", alpha=0.5, max_iter=1, tol=-1)
    bits = found.bits()
    models = spark.createDataFrame([(j, c, x, float(bits[j, c, x])) for j in range(3) for c in range(5) for x in range(5)], "cluster int, ctx long, sym int, bits double")
    keys = ["user_id", "read_no"]
    counted = K.read_counts(s, X.Previous(1))
    twin = K.assign_by_join(K.costs_by_join(counted, models, keys), keys)
    kernel = found.assign(s).where("n > 0")
    assert rows(twin, "user_id", "cluster") == rows(kernel, "user_id", "cluster")
    again = K.refit(counted, twin, keys, 0.5, 5, 5).orderBy("cluster", "ctx", "sym").collect()
    pooled, _, _ = K.assign_and_pool(s, X.Previous(1), bits)
    assert np.allclose([x.bits for x in again], K.model_bits(pooled, 0.5).ravel()[: len(again)])


def test_menus(spark):
    r = np.random.default_rng(9)
    data = [(i % 3, [float(x) for x in r.uniform(0, 10, 5)]) for i in range(60)]
    costs = spark.createDataFrame(data, "file long, bits array<double>")
    best = {x.file: x for x in K.choose_menu(costs, "file", 5, 2, "exhaustive").collect()}
    greedy = {x.file: x for x in K.choose_menu(costs, "file", 5, 2).collect()}
    from itertools import combinations

    for f in range(3):
        own = np.array([b for k, b in data if k == f])
        want = min((round(own[:, list(c)].min(axis=1).sum(), 6), c) for c in combinations(range(5), 2))
        assert abs(best[f].bits - want[0]) < 1e-5 and tuple(best[f].menu) == want[1]
        assert greedy[f].bits >= best[f].bits - 1e-9


def test_headers(spark):
    a = spark.createDataFrame([(0, 101, 10.0)] * 3 + [(1, 101, 20.0)], "cluster int, n int, bits double")
    h = R.header_bpv(a, 2).first()
    assert h.flat_bpv == round(1 / 101, 6) and h.entropy_bpv <= h.flat_bpv
    assert R.total_bpv(a, 2).first().total_bpv == round(54 / 404, 6)
    assert abs(R.order_bits(5) - math.log2(120)) < 1e-9


def test_states_by_expression(spark):
    table = H.counter_transition(3, 4)
    s = stream_of(spark, [[0, 1, 1, 2], [2, 2]], 3)
    got = s.df.select("id", H.run_states(F.col("syms"), table).alias("st")).orderBy("id").collect()
    from tests.helpers import flat

    assert got[0].st + got[1].st == H.run_machine(flat([0, 1, 1, 2], [2, 2]), table).tolist()
    p = spark.createDataFrame([(1, 2, 0)], "a int, b int, c int").select(H.pack([F.col("a"), F.col("b"), F.col("c")], [2, 3, 2]).alias("s"))
    assert p.first().s == 5
    assert [p.select(c.alias("x")).first().x for c in H.unpack(F.col("s"), [2, 3, 2])] == [1, 2, 0]


def test_soft_machine_learns_a_deterministic_successor(spark):
    s = stream_of(spark, [[0, 1, 2] * 8 for _ in range(6)], 3)
    soft = SoftMachine(3, 3, seed=2, jitter=0.5).fit(s, 60, 0.3)
    assert max(soft.history) > soft.history[0]
    table = harden(soft, s, refit=2, per_round=2)
    assert table.shape == (3, 3) and R.rate(H.count_states(s, table)).first().bpv < 0.75
    assert SoftMachine(2, 3, emission="estimated", start="uniform").fit(s, 3).history[-1] <= 0


def test_soft_machine_over_words(spark):
    r = np.random.default_rng(9)
    for m, states in ((4, 4), (3, 1), (42, 2)):
        s = stream_of(spark, [r.integers(0, m, n).tolist() for n in (0, 101, 7, 8, 9, 1, 300, 16)] + [None], m).cut(101, "keep")
        words = sheets(s)
        for emission in ("free", "estimated"):
            new = lambda: SoftMachine(states, m, emission, seed=3, jitter=0.7)
            for got, want in zip(new().evaluate(words)[:3], new().evaluate(s)[:3]):
                assert np.allclose(got, want, atol=1e-8)
            assert np.isclose(new().evaluate(words, False)[0], new().evaluate(s)[0])
            assert np.allclose(new().fit(words, 3).history, new().fit(s, 3).history)
    assert sheets(s.where("id < 0")).df.count() == 0 and SoftMachine(2, 42).evaluate(sheets(s.where("id < 0")))[0] == 0


def test_long_blocks(spark):
    s = stream_of(spark, [[0, 1, 2], [], [3, 3], [1, 1, 1, 1, 2]], 4)
    got = rows(A.long_blocks(s, 4, "id", 2), "block_no", "syms")
    assert got == [(0, [0, 1, 2, 3]), (1, [3, 1, 1, 1])]
    fit = A.fit_eta(spark.createDataFrame([(0, [0, 1] * 50)], "block_no long, syms array<int>"), 2, grid=[0.5, 0.9]).first()
    assert fit.eta in (0.5, 0.9) and fit.n == 100


def test_ema_expressions(spark):
    x = spark.createDataFrame([([1.0, 3.0, 2.0],)], "v array<double>")
    r = x.select(A.ema(F.col("v"), 0.5).alias("e"), A.ema_trail(F.col("v"), 0.5).alias("t")).first()
    assert r.e == 0.5 * (0.5 * (0.5 * 0 + 0.5 * 1) + 0.5 * 3) + 0.5 * 2 and r.t == [0.0, 0.5, 1.75]
    cov = A.ema_cov(spark.createDataFrame([(0, i, [float(i), 2.0 * i]) for i in range(5)], "k int, o int, v array<double>"), "k", "o", "v", 0.9).first()
    assert cov.n == 5 and abs(cov.cov[0][1] - 2 * cov.cov[0][0]) < 1e-9


def test_container(spark, tmp_path):
    r = np.random.default_rng(11)
    s = stream_of(spark, [markov(r, [[0.8, 0.2], [0.2, 0.8]], 90) for _ in range(20)] + [[]], 2)
    spec = X.Previous(2, "pad")
    found = K.cluster_models(s, spec, 2, max_iter=3)
    coded = Z.encode(s, spec, found.bits())
    Z.write_container(coded, spark.createDataFrame([(0, "a"), (1, "b")], "model_id int, name string"), str(tmp_path / "c"))
    back, menu = Z.read_container(spark, str(tmp_path / "c"))
    assert menu.count() == 2
    assert rows(Z.decode(back, ["id"], 2, 2, found.bits()), "id", "syms") == rows(s.frame(), "id", "syms")


def test_consensus(spark):
    df = spark.createDataFrame([("g", [1, 2, 3]), ("g", [1, 2, 4]), ("g", [1, 0, 4, 5])], "g string, syms array<int>")
    cons = E.consensus(df, "g")
    assert cons.first().syms == [1, 2, 4, 5]
    d = E.diff_rate(df, cons, "g", 6).first()
    assert d.n == 10 and d.bpv == pytest.approx(d.flag_bpv + d.replacement_bpv, abs=1e-5)


def test_minimizers_by_hand():
    r = np.random.default_rng(3)
    f = flat(*[r.integers(0, 42, n) for n in (5, 24, 30, 39, 40, 100, 0, 300)])
    h, inside = E.window_hashes(f, 24)
    names = {}
    for i in np.flatnonzero(inside):
        w = tuple(f.codes[i : i + 24])
        assert names.setdefault(w, h[i]) == h[i]
    want = set()
    for a, b in zip(f.starts[:-1], f.starts[1:]):
        begins = list(range(a, b - 23))
        for i in range(max(1, len(begins) - 15) if begins else 0):
            part = begins[i : i + 16]
            want.add(min(part, key=lambda j: (h[j], j)))
    assert set(E._minimizers(f, 24, 16)[0].tolist()) == want


def test_similar_groups_and_nearest_references(spark):
    r = np.random.default_rng(4)
    base, other, line = r.integers(0, 42, 400), [r.integers(0, 42, 300) for _ in range(3)], r.integers(0, 42, 30)
    edited = base.copy()
    edited[[50, 200]] += 1
    edited %= 42
    rows = [base, np.r_[r.integers(0, 42, 60), edited], np.r_[edited[30:], r.integers(0, 42, 5)], base, *[np.r_[line, o] for o in other]]
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(rows)], "id long, syms array<int>")
    got = E.similar_groups(df, 42).collect()
    assert sorted(len(x.syms) for x in got) == [375, 400, 400, 460]
    stream = array_stream(df, "syms", 42, ("id",))
    refs = array_stream(spark.createDataFrame([(7, edited.tolist()), (8, other[0].tolist()), (9, line.tolist())], "item long, syms array<int>"), "syms", 42, ("item",))
    near = {x.id: (x.reference, x.shift) for x in E.nearest_reference(stream, refs).collect()}
    assert near[0] == near[3] == ("7|0", 0) and near[1] == ("7|0", 60) and near[2] == ("7|0", -30) and near[4] == ("8|0", 30)
    frame = stream.frame().join(E.nearest_reference(stream, refs), ["id", "read_no"]).where("id = 1 or id = 2")
    table = refs.frame().select(F.concat_ws("|", "item", "read_no").alias("reference"), "syms")
    assert E.diff_rate(frame, table, "reference", 42, shift="shift").first().n == 460 + 375
    lone = [x for x in got if len(x.syms) == 460]
    cons = E.consensus(spark.createDataFrame(got), "g", shift="shift")
    assert sum(len(x.syms) for x in cons.collect()) >= 400 and lone[0].shift >= 60


def test_runs(spark):
    s = stream_of(spark, [[0, 0, 1], [1, 1], []], 2)
    assert rows(B.run_lengths(s), "sym", "length", "n") == [(0, 2, 1), (1, 1, 1), (1, 2, 1)]
    got = {x.id: x.syms for x in B.block_sorted(s).collect()}
    assert sorted(got[0]) == [0, 0, 1] and got[2] == []


def test_sql_functions(spark):
    registry.register(spark)
    assert spark.sql("SELECT round(half_life(0.5), 6) AS h").first().h == 1
    assert rows(spark.sql("SELECT * FROM windows_of(array(0, 1, 2), 1, 3)"), "ctx", "sym") == [(0, 1), (1, 2)]
    assert rows(spark.sql("SELECT * FROM runs_of(array(0, 0, 1))"), "sym", "length") == [(0, 2), (1, 1)]
    assert spark.sql("SELECT entropy_of(n) AS e FROM VALUES (1.0D), (1.0D) AS t(n)").first().e == 1
    assert spark.sql("SELECT read_bits(array(0, 1), array(1.0D, 2.5D)) AS b").first().b == 3.5
    assert spark.sql("SELECT ctx_code(1, 2, 4) AS c, bits_of(1, 4) AS b").first().c == 9


def test_scan_reads_only_what_it_needs(spark, sf):
    plan = C.count_windows(T.class4(spark, sf).where("lang = 'en'"), X.Previous(1))._jdf.queryExecution().toString()
    scan = [x for x in plan.splitlines() if "ReadSchema" in x][-1]
    assert "n_chars" not in scan.split("ReadSchema")[1] and "lang" in scan.split("PushedFilters")[1]


def test_moving_scale_and_regression(spark):
    r = np.random.default_rng(12)
    v = r.laplace(0, 3, 4000)
    x = spark.createDataFrame([(v.tolist(),)], "v array<double>")
    assert 2.2 < x.select(A.power_scale(F.col("v"), 0.999, 1.0).alias("s")).first().s < 3.8
    X = r.normal(size=(200, 2))
    rows_ = [(0, i, a.tolist(), float(a @ [2.0, -1.0])) for i, a in enumerate(X)]
    got = A.adaptive_regression(spark.createDataFrame(rows_, "k int, o int, x array<double>, y double"), "k", "o", "x", "y", 0.95).first()
    assert got.n == 200 and np.allclose(got.weights, [2, -1], atol=0.01)


def test_chunks_of_long_sequences(spark):
    r = np.random.default_rng(5)
    seqs = {"a": r.integers(0, 4, 700), None: r.integers(0, 4, 95), "b": r.integers(0, 4, 3)}
    window = H.chain_transition(H.Chain(4, np.array([0, 1, 2, 2]), [np.array([0, 0, 1])], [3, 2]))
    for size in (100, 7, 1):
        chunks = [(k, i // size, x[i : i + size].tolist()) for k, x in seqs.items() for i in range(0, len(x), size)]
        df = spark.createDataFrame(chunks, "k string, no int, x array<int>").repartition(5)
        for table in (window, H.counter_transition(4, 3), H.counter_transition(4, 40)):
            got = {}
            for row in H.run_chunks(df, "k", "no", "x", table, 1).collect():
                got.setdefault(row.seq, []).append((row.chunk_no, row.states, row.syms))
            for k, x in seqs.items():
                state, want = 1, []
                for v in x:
                    want.append(state)
                    state = int(table[state, v])
                parts = sorted(got[k])
                assert [s for _, states, _ in parts for s in states] == want and [s for *_, syms in parts for s in syms] == x.tolist()
    run = H.run_chunks(df, "k", "no", "x", window)
    assert H.rate_states(run, 2).first().n == sum(len(x) for x in seqs.values()) - 3  # heads of one symbol


def test_chunks_as_digits_are_counted_where_they_are(spark):
    x = np.random.default_rng(8).integers(0, 4, 9000)
    window = H.chain_transition(H.Chain(4, np.arange(4), [np.array([0, 0, 1, 1])], [4, 2]))
    for size in (5000, 9000, 1):
        part = x[:200] if size == 1 else x
        rows_ = [(0, i // size, part[i : i + size].tolist()) for i in range(0, len(part), size)]
        df = spark.createDataFrame(rows_, "k int, no int, x array<int>").repartition(3)
        digits = df.withColumn("x", F.array_join(F.col("x").cast("array<string>"), ""))
        for table in (window, H.run_length_transition(4, 4), H.counter_transition(4, 40)):
            want = H.rate_states(H.run_chunks(df, "k", "no", "x", table), 2 if size > 1 else 0).collect()
            assert R.rate(H.count_chunks(digits, "k", "no", "x", table, skip=2 if size > 1 else 0)).collect() == want
    s = stream_of(spark, [[0, 1, 2], [], [3, 3], [1, 1, 1, 1, 2]], 4)
    assert rows(A.long_blocks(s, 4, "id", 2, "keep", True), "block_no", "syms") == [(0, "0123"), (1, "3111"), (2, "12")]
    # a machine that forgets moves ends of chunks through its one window, not the chunks
    long = spark.createDataFrame([(0, i, x.tolist()) for i in range(3)], "k int, no int, x array<int>")
    plan = H.run_chunks(long, "k", "no", "x", window)._jdf.queryExecution().optimizedPlan().toString()
    assert "lag(end#" in next(line for line in plan.splitlines() if "Window [" in line)


def test_blocks_of_rows_with_one_id(spark):
    texts = [(1, "ab c1."), (1, "ab c1."), (1, "zz  99"), (None, "aeiou "), (5000, "bcdfg1")]
    s = text_stream(spark.createDataFrame(texts, "doc_id long, text string"), kind="class")
    blocks = {r.block_no: r.syms for r in A.long_blocks(s, 12, tail="keep").collect()}
    assert {k: len(v) for k, v in blocks.items()} == {0: 12, 1: 12, 2: 6} and blocks[0][:6] == [0, 0, 0, 0, 0, 2] and blocks[2] == [1, 1, 1, 1, 1, 3]


def test_chance_is_what_shuffled_labels_give(spark):
    rows = [(i, i % 10, i % 5, 101) for i in range(5000)]
    df = spark.createDataFrame(rows, "id long, cluster int, label int, n int")
    assert R.purity(df, "label").first().purity == 1.0
    drawn = R.shuffled(df, "label", ["id"])
    shares = {r.label: r["count"] / 5000 for r in drawn.groupBy("label").count().collect()}
    assert set(shares) == set(range(5)) and all(abs(v - 0.2) < 0.03 for v in shares.values())
    few = df.where("id < 500")
    assert R.chance(few, "label", ["id"]).first().chance > 0.22  # more than the largest label's share, by luck alone
    nulls = df.withColumn("label", F.when(F.col("label") > 0, F.col("label")))
    assert abs(R.shuffled(nulls, "label", ["id"]).where("label is null").count() / 5000 - 0.2) < 0.03


def test_seeds_do_not_depend_on_partitions(spark):
    r = np.random.default_rng(6)
    rows = [(i % 40, r.integers(0, 3, 30).tolist()) for i in range(60)]  # some ids twice
    for how in ("random", "first"):
        picks = []
        for parts in (1, 7):
            s = array_stream(spark.createDataFrame(rows, "id long, syms array<int>").repartition(parts), "syms", 3, ("id",)).cut(8, "keep")
            picks.append(K.pick_reads(s, X.Previous(1), 5, how, 3))
            assert K.worst_read(s, X.Previous(1), np.full((1, 9), 1.5)).sum() > 0
        assert picks[0].shape == (5, 3, 3) and (picks[0] == picks[1]).all()


def test_count_tables_are_bounded(spark):
    counts = spark.createDataFrame([(i, i % 3, 1) for i in range(50)], "ctx long, sym int, n long")
    assert C.matrix(counts, 3)[1].sum() == 50
    with pytest.raises(ValueError):
        C.matrix(counts, 3, most=49)


def test_adaptive_round_trip(spark):
    r = np.random.default_rng(7)
    seqs = [r.integers(0, 5, n).tolist() for n in (0, 1, 300)] + [None]
    s = stream_of(spark, seqs, 5)
    got = {x.id: x.syms for x in Z.adaptive_round_trip(s, X.Previous(1, "pad"), 1, 4).collect()}
    assert got == {i: q or [] for i, q in enumerate(seqs)}


def test_steps_are_dropped(spark):
    from ctxloom import session

    path = session.materialise(spark.range(3), "drop").inputFiles()[0]
    assert session.drop_steps(spark) >= 1 and not session._steps
    import os

    assert not os.path.exists(path.removeprefix("file://"))
