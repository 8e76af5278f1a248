"""The tree of one cell against brute force; worked examples; invariants."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pivotgrove.operators import tree
from pivotgrove.operators.tree import MODES, STRATEGIES, Params
from pivotgrove.plans import cdf, fanout


def cloud(n, d, seed=0, digits=2):
    x = np.random.default_rng(seed).normal(size=(n, d)).round(digits)
    return x, np.arange(n)


def brute(x, ids, q, k):
    return sorted(zip(tree.distances(x, q).tolist(), ids.tolist(), strict=True))[:k]


@pytest.mark.parametrize("mode", MODES)
@pytest.mark.parametrize("n,d", [(0, 2), (1, 2), (700, 2), (900, 3), (300, 1), (200, 16)])
def test_every_strategy_equals_brute_force(mode, n, d):
    x, ids = cloud(n, d)
    root, x, ids = tree.unpack(tree.pack(tree.build(x, ids, Params(mode=mode, c=10, small=0)), x, ids))
    assert sorted(np.concatenate([leaf.idx for leaf in tree.leaves(root)]).tolist()) == list(range(n))
    for seed in range(3):
        q = np.random.default_rng(seed).normal(size=d)
        for s in STRATEGIES:
            for order in ("nearest", "pivot"):
                assert tree.knn(root, x, ids, q, 7, s, order)[0] == brute(x, ids, q, 7)
            for inside in (False, True):
                got = tree.radius_search(root, x, ids, q, 0.5, s, inside)[0]
                assert sorted(got.tolist()) == ids[tree.distances(x, q) <= 0.5].tolist()


def test_equal_points_and_a_constant_coordinate():
    x = np.ones((40, 2))
    assert len(tree.leaves(tree.build(x, np.arange(40), Params()))) == 1
    x[:, 1] = np.arange(40)
    root = tree.build(x, np.arange(40), Params(c=5, t=3))
    assert max(leaf.n for leaf in tree.leaves(root)) <= 6
    assert tree.knn(root, x, np.arange(40), x[0], 100)[0] == brute(x, np.arange(40), x[0], 100)


@given(st.integers(1, 400), st.integers(2, 6), st.integers(0, 5))
@settings(max_examples=25, deadline=None)
def test_volumes_hold_their_points_and_counts_add_up(n, t, seed):
    x, ids = cloud(n, 2, seed)
    for node, _, _ in tree.preorder(tree.build(x, ids, Params(c=8, t=t))):
        mine = np.concatenate([leaf.idx for leaf in tree.leaves(node)])
        assert len(mine) == node.n and len(node.kids) in (0, t)
        if node.n:
            assert (x[mine] >= node.lo).all() and (x[mine] <= node.hi).all()
            assert (tree.distances(x[mine], node.center) <= node.radius + 1e-9).all()
        if node.pivots is not None:
            assert (np.diff(node.pivots) >= 0).all()


@given(st.integers(0, 1000), st.floats(0, 3))
@settings(max_examples=50, deadline=None)
def test_pruning_is_sound(seed, r):
    x, ids = cloud(50, 2, seed)
    q = np.random.default_rng(seed + 1).normal(size=2) * 3
    root = tree.volume(x, 0)
    root.kids = [tree.volume(x, 1)]
    least = tree.distances(x, q).min()
    assert tree.lower_bounds(root, q, False)[0] <= least + 1e-9 and tree.lower_bounds(root, q, True)[0] <= least + 1e-9


@pytest.mark.parametrize("mode", MODES)
@pytest.mark.parametrize("rebuild", ["selective", "full", "none"])
def test_insertion_keeps_answers_exact(mode, rebuild):
    x, ids = cloud(3000, 2)
    x[1500:] = x[1500:] * 0.1 + 3
    p = Params(mode=mode, t=4, small=0)
    root, log = tree.build(x, ids, p, np.arange(1500)), []
    for a in range(1500, 3000, 300):
        log += tree.insert(root, x, ids, np.arange(a, a + 300), p, rebuild)
    assert sorted(np.concatenate([leaf.idx for leaf in tree.leaves(root)]).tolist()) == list(range(3000))
    for s in STRATEGIES:
        assert tree.knn(root, x, ids, np.array([3.0, 3.0]), 20, s)[0] == brute(x, ids, np.array([3.0, 3.0]), 20)
    assert all(r["points_rebuilt"] <= r["points_full"] for r in log) and (log == []) == (rebuild == "none")


def test_rebuild_example_takes_twelve_of_eighteen():
    for omega in (0.7, 0.8, 0.9):
        assert tree.rebuild_range([6, 3, 9], omega) == (1, 2)
    assert tree.rebuild_range([6, 6, 6], 0.9) is None
    assert tree.allowed_omega(0.8, 8) > 7 / 8 and tree.allowed_omega(0.9, 8) == 0.9


@given(st.lists(st.integers(0, 50), min_size=2, max_size=8), st.sampled_from([0.88, 0.95]))
@settings(max_examples=100, deadline=None)
def test_the_range_of_fewest_points_is_taken(sizes, omega):
    found = tree.rebuild_range(sizes, omega)
    if found is None:
        return
    a, b = found
    good = [sum(sizes[i : j + 1]) for i in range(a, -1, -1) for j in range(b, len(sizes)) if tree.range_balanced(sizes, i, j, omega)]
    assert sum(sizes[a : b + 1]) <= min([*good, sum(sizes)])


def test_fanout_examples():
    x = np.arange(8.0)[:, None]
    paths = {t: tree.aepl(tree.build(x, np.arange(8), Params(c=3, t=t, mode="sort")))[0] / 8 for t in (2, 3, 4)}
    assert paths[2] == 2 and paths[4] == 2.25 and paths[3] < paths[2]
    assert [fanout.aepl_printed_per_point(8, 3, t) for t in (2, 3, 4)] == [2, 1.875, 2.25]
    assert fanout.optimal_fanout(10**6, 30, 2, 11) == 8


@given(st.integers(50, 10**7), st.integers(5, 100))
@settings(max_examples=60, deadline=None)
def test_annealing_finds_the_scan_result(n, c):
    a, b = (fanout.optimal_fanout(n, c, method=m) for m in ("anneal", "scan"))
    assert a == b or fanout.aepl_printed(n, c, a) == fanout.aepl_printed(n, c, b)


def test_cdf_of_a_ramp_a_constant_and_an_outlier():
    x = np.arange(100.0)
    m = cdf.fit(x, 1)
    assert abs(m.alpha - 0.01) < 1e-12 and abs(m.beta) < 1e-9
    assert np.abs(cdf.fit(x, 10).predict(x) - x / 100).max() < 0.02
    assert cdf.fit(np.ones(10), 5).alpha == 0
    p = cdf.fit(np.append(x, 1e6), 20).predict(np.append(x, 1e6))
    assert (np.diff(p) >= 0).all() and 0 <= p.min() and p.max() <= 1


def test_rank_corrected_cuts_are_the_order_statistics():
    x = np.random.default_rng(3).exponential(size=5000)
    cuts = tree.find_pivots(x, 5, Params(kappa=0.05), np.random.default_rng(0))
    assert cuts.tolist() == [np.sort(x)[int(np.ceil(i / 5 * 5000)) - 1] for i in range(1, 5)]


def test_router_equals_the_tree():
    x, ids = cloud(4000, 3, 4, 1)
    from pivotgrove.operators.index import cell_ids, upper_tree

    for cells in (1, 2, 9, 150, 700):
        root = upper_tree(x, ids, cells, Params(mode="rank_corrected", t=8))
        assert len(tree.leaves(root)) <= max(1.5 * cells, 2)
        want = np.empty(len(x), dtype=np.int64)
        for i, leaf in enumerate(tree.leaves(root)):
            want[leaf.idx] = i
        assert tree.Router.of(root).cells(x).tolist() == want.tolist()
        dealt = cell_ids(tree.Router.of(root), {0: 3, 1: [4, 0, -1.0, 1.0, 1, -1.0, 1.0]}, x, ids)
        assert (dealt >> 20 == want).all() and len(set(dealt[want == 0].tolist())) > 1


def test_quantile_sketch_is_near_the_quantiles():
    x = np.random.default_rng(8).exponential(size=50_000)
    values, weights = tree.quantile_sketch(x, np.random.default_rng(0))
    assert weights.sum() == len(x) and len(values) < 5000
    cuts = tree.find_pivots(x, 8, Params(mode="sketch"), np.random.default_rng(0))
    assert max(abs(float((x <= c).mean()) - (i + 1) / 8) for i, c in enumerate(cuts)) < 0.02
