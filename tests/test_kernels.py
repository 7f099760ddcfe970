"""Contexts, trees, machines, coder and adaptive functions without Spark: brute force and invariants."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ctxloom.operators import adapt as A
from ctxloom.operators import baselines as B
from ctxloom.operators import coder as Z
from ctxloom.operators import contexts as X
from ctxloom.operators import hidden as H
from ctxloom.operators import merge as M
from ctxloom.operators.soft import SoftMachine, batch_gradient, softmax
from tests.helpers import flat, markov

seqs = st.lists(st.lists(st.integers(0, 3), max_size=12), min_size=1, max_size=5)


@given(seqs, st.integers(0, 3))
@settings(max_examples=60, deadline=None)
def test_previous_values(sequences, order):
    f = flat(*sequences)
    ctx, valid = X.Previous(order).codes(f, 4)
    pad, all_ = X.Previous(order, "pad").codes(f, 4)
    i = 0
    assert all_.all()
    for s in sequences:
        for t in range(len(s)):
            assert valid[i] == (t >= order)
            if t >= order:
                assert ctx[i] == sum(s[t - k] * 4 ** (k - 1) for k in range(1, order + 1))
            assert pad[i] == sum((s[t - k] if t >= k else 4) * 5 ** (k - 1) for k in range(1, order + 1))
            i += 1


@given(seqs)
@settings(max_examples=60, deadline=None)
def test_running_contexts(sequences):
    f = flat(*sequences)
    changes, _ = X.ChangeCount(5, 2).codes(f, 4)
    sums, _ = X.RunningSum(6, 3).codes(f, 4)
    back, _ = X.Previous(2, "backoff").codes(f, 4)
    low, _ = X.LowBits(1, 1).codes(f, 4)
    i = 0
    for s in sequences:
        for t in range(len(s)):
            assert changes[i] == min(sum(s[k] != s[k - 1] for k in range(1, t)) // 2, 4)
            assert sums[i] == min(sum(s[:t]) // 3, 5)
            assert back[i] == (s[t - 1] + 4 * s[t - 2] if t > 1 else 16 + s[0] if t == 1 else 20)
            if t:
                assert low[i] == s[t - 1] >> 1
            i += 1


def test_product_and_delay():
    f = flat([0, 1, 2, 3, 1, 0, 2])
    near = X.Binned(X.Previous(2), tuple(range(16)), 16)
    ctx, valid = X.Product((near, X.DelayedBin(near, 2))).codes(f, 4)
    full, ok = X.Previous(4).codes(f, 4)
    assert (valid == ok).all() and (ctx[ok] == full[ok]).all()


def tables(n, m, seed):
    r = np.random.default_rng(seed)
    return r.integers(1, 50, (n, m))


@pytest.mark.parametrize("seed", range(6))
def test_tree(seed):
    t = tables(9, 4, seed)
    heap, near = (M.tree_of(np.arange(9), t, q) for q in ("heap", "nearest"))
    assert heap.left == near.left and heap.right == near.right and np.allclose(heap.delta, near.delta)
    assert len(heap.left) == 8 and min(heap.delta) >= 0
    none = M.excess(t.sum(axis=0)[None]).sum() / t.sum()
    assert math.isclose(sum(heap.delta), none - heap.full_rate(), abs_tol=1e-9)
    rates = [M.binned_rate(heap, M.cut(heap, M.MaxBins(k))) for k in range(1, 10)]
    assert all(a >= b - 1e-12 for a, b in zip(rates, rates[1:]))
    assert [round(x, 9) for _, x in M.loss_curve(heap)] == [round(x, 9) for x in rates]
    for order in ("reverse", "largest_gain"):
        for k in range(1, 10):
            bins = M.cut(heap, M.MaxBins(k), order)
            assert sorted(set(bins)) == list(range(k))
    for a, b in zip(*[M.cut_many(heap, [M.MaxBins(k) for k in r]) for r in ((5, 3), (3, 2))]):
        assert len({(x, y) for x, y in zip(a, b)}) == a.max() + 1  # nested
    loss = M.cut(heap, M.MaxLoss(0.01))
    assert M.binned_rate(heap, loss) - heap.full_rate() <= 0.01 + 1e-9
    assert M.cut(heap, M.MinGain(1e9)).max() == 0


def test_greedy_against_all_partitions():
    for seed in range(3):
        t = tables(6, 3, seed)
        tree = M.tree_of(np.arange(6), t)
        for k in (2, 3, 4):
            assert M.binned_rate(tree, M.cut(tree, M.MaxBins(k))) >= B.best_partition(t, k) - 1e-12


def test_equal_distributions_merge_free():
    t = np.array([[10, 30], [20, 60], [40, 8], [5, 1]])
    tree = M.tree_of(np.arange(4), t)
    assert abs(M.binned_rate(tree, M.cut(tree, M.MaxBins(2))) - tree.full_rate()) < 1e-12
    assert M.tree_of(np.arange(1), t[:1]).left == [] and M.cut(M.tree_of(np.arange(1), t[:1]), M.MaxBins(3)).tolist() == [0]


def test_two_level_numbers():
    t = tables(20, 4, 3)
    bins, rows = M.two_level(np.arange(20), t, 12, 2)
    assert len(set(bins.tolist())) == len(rows) == 12
    assert np.bincount(bins >> 2).max() <= 20 and max(len({b for b in bins if b >> 2 == g}) for g in set((bins >> 2).tolist())) <= 4


def test_chain_is_the_window():
    r = np.random.default_rng(0)
    chain = H.Chain(5, np.array([0, 1, 2, 3, 3]), [np.array([0, 1, 1, 2]), np.array([0, 1, 1])], [4, 3, 2])
    for pow2 in (False, True):
        radices = chain.radices(pow2)
        table = H.chain_transition(chain, pow2)
        packed = np.arange(int(np.prod(radices)))
        assert (H.pack_codes(H.unpack_codes(packed, radices), radices) == packed).all()
        s = r.integers(0, 5, 60)
        state = H.run_machine(flat(s.tolist()), table)
        for i in range(3, 60):
            window = [chain.level_table(j)[s[i - 1 - j]] for j in range(3)]
            assert state[i] == H.pack_codes(np.array(window), radices)


WINDOW = H.chain_transition(H.Chain(4, np.array([0, 0, 1, 2]), [np.array([0, 1, 1])], [3, 2]))


def states_by_hand(sequences, table):
    out = []
    for s in sequences:
        state = 0
        for x in s:
            out.append(state)
            state = int(table[state, x])
    return out


@pytest.mark.parametrize("piece", [2, 5, 2048])
@pytest.mark.parametrize("table", [H.counter_transition(4, 3), WINDOW, np.zeros((1, 4), int), H.counter_transition(4, 20)], ids=["counter", "window", "none", "many"])
@given(seqs)
@settings(max_examples=20, deadline=None)
def test_machines_and_pieces(table, piece, sequences):
    before, H.PIECE = H.PIECE, piece
    try:
        assert H.run_machine(flat(*sequences), table).tolist() == states_by_hand(sequences, table)
    finally:
        H.PIECE = before


def test_memory():
    assert H.memory(WINDOW) == 2 and H.memory(np.zeros((1, 4), int)) == 0 and H.memory(H.counter_transition(4, 3)) is None


@pytest.mark.parametrize("rate, contexts", [(4, 1), (8, 1), (8, 5), (5, 400)])
def test_lanes_are_the_scan(rate, contexts):
    r = np.random.default_rng(rate + contexts)
    for codes in (r.choice(4, 30000, p=[0.6, 0.3, 0.09, 0.01]), np.repeat(r.integers(0, 4, 30), 1000)):
        ctx = r.integers(0, contexts, len(codes))
        want, _ = A.scan_cdfs(codes, ctx, 4, rate)
        assert (A.lane_gaps(codes, ctx, 4, rate) == want).all()
        assert (A.lane_gaps(codes, ctx, 4, rate, piece=300, halo=20) == want).all()  # most pieces are run again


def test_product_transition():
    a, b = H.run_length_transition(3, 2), H.counter_transition(3, 2)
    s = [0, 0, 1, 2, 2, 0]
    both = H.run_machine(flat(s), H.product_transition(a, b))
    assert (both % len(a) == H.run_machine(flat(s), a)).all() and (both // len(a) == H.run_machine(flat(s), b)).all()


def test_ema_and_half_life():
    eta, x = 0.93, np.random.default_rng(1).integers(0, 3, 500)
    p, want = np.full(3, 1 / 3), []
    for s in x:
        want.append(p[s])
        p = eta * p
        p[s] += 1 - eta
    assert np.allclose(A._frequencies(x, 3, eta), want)
    assert abs(A._frequencies(x, 3, 0.51) - A._frequencies(x, 3, 0.51)).max() == 0
    mu = -1 / math.log2(1 - 2**-8)
    assert 177 < mu < 178 and abs((1 - 2**-8) ** mu - 0.5) < 1e-12


@pytest.mark.parametrize("rate", [1, 4, 8])
def test_cdf_gaps_stay(rate):
    m = 5
    cdf = A.uniform_cdf(m)
    for x in [0] * 400 + [4] * 400 + [2] * 400:
        cdf = [a + ((b - a) >> rate) for a, b in zip(cdf, A.step_target(m, x))]
        assert cdf[0] == 0 and cdf[-1] == 1 << A.CDF_BITS and min(np.diff(cdf)) >= 1


def test_adaptive_on_switching_and_stationary_sources():
    r = np.random.default_rng(2)
    switching = np.concatenate([r.choice(2, 3000, p=[0.95, 0.05]), r.choice(2, 3000, p=[0.05, 0.95])])
    still = r.choice(2, 6000, p=[0.7, 0.3])
    for x, better in ((switching, True), (still, False)):
        gaps, _ = A.scan_cdfs(x, np.zeros(len(x), int), 2, 6)
        adaptive = A.CDF_BITS - np.log2(gaps).mean()
        n = np.bincount(x)
        static = M.excess(n[None])[0] / n.sum()
        assert (adaptive < static) == better
    dense, _ = A.scan_cdfs(still, np.zeros(6000, int), 2, 6, every=1)
    sparse, trail = A.scan_cdfs(still, np.zeros(6000, int), 2, 2, every=100, trace=1000)
    assert len(dense) == len(sparse) == 6000 and len(trail) == 6 and sparse.min() >= 1


def test_written_out_loop_is_the_general_one():
    r = np.random.default_rng(6)
    x, c = r.integers(0, 4, 3000), r.integers(0, 9, 3000)
    fast, _ = A.scan_cdfs(x, c, 4, 5)
    slow, _ = A.scan_cdfs(x, c, 4, 5, trace=10)
    assert (fast == slow).all()


def test_coder_round_trip_and_size():
    r = np.random.default_rng(3)
    p = np.array([0.7, 0.2, 0.05, 0.05])
    q = Z.quantize_freqs(p)[0]
    assert q.sum() == 1 << Z.TOTAL_BITS and q.min() >= 1
    start = np.concatenate([[0], np.cumsum(q)])
    x = r.choice(4, 20000, p=p)
    data = Z.encode_read([(int(start[s]), int(q[s])) for s in x])
    d, out = Z.Decoder(data), []
    for _ in x:
        s = int(np.searchsorted(start, d.slot(Z.TOTAL_BITS), "right")) - 1
        d.advance(int(start[s]), int(q[s]), Z.TOTAL_BITS)
        out.append(s)
    assert out == x.tolist()
    ideal = -np.log2(p[x]).sum()
    assert len(data) * 8 < ideal * 1.01 + 64
    assert Z.quantization_loss(p, np.ones(1)) < 0.001


def test_reads_coded_in_step_give_the_same_bytes():
    r = np.random.default_rng(6)
    for m, order, models in ((4, 2, 2), (42, 1, 3), (5, 0, 2), (1, 1, 1)):
        freqs = np.stack([Z.quantize_freqs(r.dirichlet(np.full(m, 0.3), (m + 1) ** order)) for _ in range(models)])
        starts = np.concatenate([np.zeros((*freqs.shape[:2], 1), np.int64), np.cumsum(freqs, axis=2)], axis=2)
        f, model = flat(*[r.integers(0, m, n).tolist() for n in (0, 101, 3, 101, 1, 700, 0)]), r.integers(0, models, 7)
        ctx, _ = X.Previous(order, "pad").codes(f, m)
        cell = np.repeat(model, f.size), ctx, f.codes
        got = Z.encode_reads(starts[cell], freqs[cell], f.starts)
        assert got.to_pylist() == [Z.encode_read(list(zip(starts[cell][a:b].tolist(), freqs[cell][a:b].tolist()))) for a, b in zip(f.starts, f.starts[1:])]
        assert (Z.decode_reads(got, model, f.size, order, m, freqs, starts) == f.codes).all()
        assert (Z.decode_reads(got.slice(2), model[2:], f.size[2:], order, m, freqs, starts) == f.codes[101:]).all()


def test_many_reads_are_coded_faster_than_one_by_one():
    import time

    r = np.random.default_rng(7)
    q = Z.quantize_freqs(r.dirichlet(np.full(4, 0.5), 5))
    start, codes, offsets = np.cumsum(q, axis=1) - q, r.integers(0, 4, 404_000), np.arange(0, 404_001, 101)
    began = time.perf_counter()
    data = Z.encode_reads(start[0, codes], q[0, codes], offsets)
    took = time.perf_counter() - began
    one = [(int(start[0, x]), int(q[0, x])) for x in codes[:40_400]]
    began = time.perf_counter()
    assert [Z.encode_read(one[a : a + 101]) for a in range(0, 40_400, 101)] == data[:400].to_pylist()
    assert took < 2 * (time.perf_counter() - began)  # ten times as many


def test_adaptive_coder_mirrors():
    x = markov(np.random.default_rng(4), [[0.9, 0.1], [0.3, 0.7]], 2000)
    ctx, _ = X.Previous(1, "pad").codes(flat(x), 2)
    data = Z.encode_adaptive(x, ctx.tolist(), 2, 5)
    assert Z.decode_adaptive(data, len(x), 1, 2, 5) == x


def test_prefix_lengths():
    assert sorted(Z.huffman_lengths([8, 4, 2, 2])) == [1, 2, 3, 3]
    assert Z.huffman_lengths([0, 5, 0]) == [0, 1, 0] and Z.huffman_lengths([0, 0]) == [0, 0]


@given(st.lists(st.integers(0, 3), max_size=40))
@settings(max_examples=60, deadline=None)
def test_block_sorting_round_trip(x):
    x = np.array(x, np.int64)
    last, row = B.block_sort(x, 4)
    if len(set(np.roll(x, i).tobytes() for i in range(len(x)))) == len(x):  # periodic sequences have equal rotations
        assert B.block_unsort(last, row).tolist() == x.tolist()
    assert sorted(last) == sorted(x)


def test_soft_gradient_by_differences():
    r = np.random.default_rng(5)
    f = flat(r.integers(0, 3, 7).tolist(), r.integers(0, 3, 4).tolist(), [])
    T, d = softmax(r.normal(size=(3, 2, 2))), np.log(softmax(r.normal(size=(2, 3)))).T
    start = np.array([1.0, 0.0])
    value, gT, gd, mixed = batch_gradient(f, T, d, start)
    for grad, array in ((gT, T), (gd, d)):
        for i in np.ndindex(array.shape):
            array[i] += 1e-6
            up = batch_gradient(f, T, d, start)[0]
            array[i] -= 2e-6
            down = batch_gradient(f, T, d, start)[0]
            array[i] += 1e-6
            assert abs((up - down) / 2e-6 - grad[i]) < 1e-4
    assert value <= mixed * math.log(2) + 1e-9  # Jensen


def test_soft_machine_rows():
    s = SoftMachine(3, 4, seed=1)
    assert np.allclose(s.transitions().sum(axis=-1), 1) and np.allclose(np.exp(s.emissions()).sum(axis=0), 1)
    s.fixed[0, 1] = 2
    assert s.transitions()[0, 1].tolist() == [0, 0, 1] and s.table().shape == (3, 4)
