"""Trees of one partition: exact answers, invariants, special cases."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ballspark.config import BuildConfig
from ballspark.operators import kernel
from ballspark.operators.kernel import Trace, Tree, build, canonical, count_kernel, nearest_kernel, range_kernel, squared
from ballspark.operators.pca import balanced_bound

CONFIGS = [
    BuildConfig(leaf_capacity=4),
    BuildConfig(kind="fpb", leaf_capacity=4),
    BuildConfig(kind="kdt", leaf_capacity=4),
    BuildConfig(kind="kdt", kd_axis="cycle", kd_cut="midpoint", leaf_capacity=1),
    BuildConfig(kind="kdt", kd_bounds="cells", leaf_capacity=2),
    BuildConfig(kind="kdt", kd_bounds="plane", leaf_capacity=1),
    BuildConfig(axis="gram", leaf_capacity=2),
    BuildConfig(axis_solver="power"),
    BuildConfig(offset="printed", alpha=3.0, leaf_capacity=2),
    BuildConfig(candidate="data_mean", leaf_capacity=1),
    BuildConfig(cut="exhaustive", leaf_capacity=1),
    BuildConfig(ball="enclosing", leaf_capacity=2),
]


def check_sound(t: Tree, cfg: BuildConfig, n: int):
    leaf = t.lo < 0
    assert (t.end - t.begin)[leaf].sum() == n
    assert sorted(t.pid) == list(range(n))
    for i in range(len(t.lo)):
        x = t.x[t.begin[i] : t.end[i]]
        assert np.sqrt(squared(x, t.center[i])).max() <= t.radius[i] * (1 + 1e-9) + 1e-12
        if leaf[i]:
            assert len(x) <= cfg.leaf_capacity or (x == x[0]).all()
        else:
            a, b = t.lo[i], t.hi[i]
            assert t.begin[a] == t.begin[i] and t.end[a] == t.begin[b] and t.end[b] == t.end[i]
            assert t.end[a] > t.begin[a] and t.end[b] > t.begin[b]


points = st.lists(st.tuples(st.floats(-5, 5, width=16), st.floats(-5, 5, width=16)), min_size=1, max_size=60)


@settings(max_examples=40, deadline=None)
@given(points, st.sampled_from(CONFIGS), st.integers(1, 70), st.sampled_from([0.0, 0.5, 2.0, math.inf]))
def test_searches_are_exact(rows, cfg, k, r):
    x = np.array(rows)
    t = build(x, np.arange(len(x)), cfg)
    check_sound(t, cfg, len(x))
    for q in (x[0], x.mean(axis=0), np.array([9.0, -9.0])):
        truth = [a for a in sorted(zip(squared(x, q).tolist(), range(len(x)))) if a[0] <= r * r]
        assert sorted(range_kernel(t, q.tolist(), r, Trace())) == truth
        assert count_kernel(t, q.tolist(), r, Trace()) == len(truth)
        for options in ({}, {"order": "right_first"}, {"order": "best_first"}, {"prune": "conjunction"}, {"carry_bound": False}, {"child_test": False}):
            assert nearest_kernel(t, q.tolist(), k, r, Trace(), **options) == truth[:k]


def test_worked_range_query():
    """Four pairs of points, far apart: a query near one pair opens that pair only."""
    pairs = np.array([(0, 0), (0.1, 0), (10, 0), (10.1, 0), (0, 10), (0.1, 10), (10, 10), (10.1, 10)], float)
    t = build(pairs, np.arange(8), BuildConfig(leaf_capacity=2))
    trace = Trace()
    assert sorted(p for _, p in range_kernel(t, [0.05, 0.0], 1.0, trace)) == [0, 1]
    assert trace.leaves_scanned == 1 and trace.points_compared == 2
    assert trace.nodes_entered < len(t.lo)


def test_special_inputs():
    assert len(build(np.empty((0, 2)), np.empty(0, int), BuildConfig()).lo) == 0
    assert range_kernel(build(np.empty((0, 2)), np.empty(0, int), BuildConfig()), [0.0, 0.0], 1.0, Trace()) == []
    one = build(np.array([[1.0, 2.0]]), np.array([7]), BuildConfig())
    assert nearest_kernel(one, [0.0, 0.0], 3, math.inf, Trace()) == [(5.0, 7)]
    same = build(np.ones((100, 2)), np.arange(100), BuildConfig(leaf_capacity=10))
    assert len(same.lo) == 1  # points that are equal cannot be parted, whatever the capacity
    line = build(np.stack([np.arange(64.0)] * 2, axis=1), np.arange(64), BuildConfig(leaf_capacity=1, alpha=0.0))
    assert line.depth[line.lo < 0].max() == 6 and np.allclose(line.axis[0], math.sqrt(0.5))


def test_gram_axis_falls_back_on_the_covariance():
    x = np.array([[1, -0.1], [1, 0.1]] * 8)
    t = build(x, np.arange(16), BuildConfig(axis="gram", leaf_capacity=8))
    assert np.allclose(np.abs(t.axis[0]), [0, 1]) and len(t.lo) == 3


def test_outlier_unbalances_the_pivot_tree_only():
    x = np.random.default_rng(1).random((1000, 2))
    x = np.concatenate([x, [[10.0, 10.0]]])
    lop = {}
    for kind in ("pab", "fpb"):
        t = build(x, np.arange(len(x)), BuildConfig(kind=kind, alpha=0.0, sections=512))
        a, b = (t.end[c] - t.begin[c] for c in (t.lo[0], t.hi[0]))
        lop[kind] = abs(int(a) - int(b)) / len(x)
    assert lop["fpb"] > 0.99 and lop["pab"] < 0.2


def test_ties_are_answered_by_pid():
    angle = np.linspace(0, 2 * np.pi, 13)[:-1]
    x = np.round(np.stack([np.cos(angle), np.sin(angle)], axis=1), 3)
    d = squared(x, np.zeros(2))
    t = build(x, np.arange(12), BuildConfig(leaf_capacity=1))
    assert nearest_kernel(t, [0.0, 0.0], 5, math.inf, Trace()) == sorted(zip(d.tolist(), range(12)))[:5]


def test_border_is_inside():
    t = build(np.array([[3.0, 4.0], [6.0, 8.0]]), np.arange(2), BuildConfig())
    assert [p for _, p in range_kernel(t, [0.0, 0.0], 5.0, Trace())] == [0]


def test_constrained_search_visits_no_more():
    rng = np.random.default_rng(5)
    x = rng.random((3000, 2)) ** 2
    t = build(x, np.arange(3000), BuildConfig(leaf_capacity=4))
    for q in rng.random((40, 2)).tolist():
        for r in (0.01, 0.05, 0.2):
            c, n, g = Trace(), Trace(), Trace()
            nearest_kernel(t, q, 10, r, c, order="right_first")
            nearest_kernel(t, q, 10, math.inf, n, order="right_first")
            range_kernel(t, q, r, g)
            assert c.nodes_entered <= n.nodes_entered and c.nodes_entered <= g.nodes_entered


def test_depth_keeps_to_the_bound_and_the_known_order():
    x = np.random.default_rng(2).random((4096, 2)) ** 3
    depth = {}
    for kind in ("pab", "fpb", "kdt"):
        t = build(x, np.arange(4096), BuildConfig(kind=kind, leaf_capacity=1))
        depth[kind] = t.depth[t.lo < 0].mean()
        assert depth[kind] >= balanced_bound(4096) - 1e-9
    assert depth["pab"] < depth["fpb"]


def test_round_trip_and_config():
    t = build(np.random.default_rng(0).random((50, 3)), np.arange(50), BuildConfig(leaf_capacity=5))
    u = Tree.from_bytes(t.to_bytes())
    assert all(np.array_equal(getattr(t, n), getattr(u, n), equal_nan=True) for n in Tree.ARRAYS)
    assert (canonical(np.array([[-0.8, 0.6], [0.6, -0.8]])) == [[0.8, -0.6], [-0.6, 0.8]]).all()
    with pytest.raises(ValueError):
        BuildConfig(kind="metric")
    with pytest.raises(ValueError):
        BuildConfig(leaf_capacity=0)


@settings(max_examples=40, deadline=None)
@given(rows=st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9)), max_size=60), kind=st.sampled_from(["pab", "fpb", "kdt"]), capacity=st.integers(1, 9), seed=st.integers(0, 99))
def test_many_queries_together_answer_as_each_alone(rows, kind, capacity, seed):
    kernel.OPEN, kernel.COMPARED = (7, 5) if seed % 2 else (1_000_000, 2_000_000)
    tree = kernel.build(np.array(rows, float).reshape(-1, 2), np.arange(len(rows))[::-1], BuildConfig(kind=kind, leaf_capacity=capacity))
    rng = np.random.default_rng(seed)
    q, k, r = rng.integers(0, 10, (12, 2)).astype(float), rng.integers(1, 20, 12), np.where(rng.random(12) < 0.4, np.inf, rng.integers(0, 6, 12))
    of, pid, d2 = kernel.nearest_together(tree, q, k, r)
    for i in range(12):
        assert list(zip(d2[of == i], pid[of == i])) == kernel.nearest_kernel(tree, q[i].tolist(), int(k[i]), float(r[i]), kernel.Trace())
    near = np.minimum(r, 3.0)
    found, counted = list(kernel.range_together(tree, q, near)), kernel.range_traces(tree, q, near)
    for i in range(12):
        trace = kernel.Trace()
        alone = sorted(kernel.range_kernel(tree, q[i].tolist(), float(near[i]), trace))
        assert sorted(x for of, pid, d2 in found for x in zip(d2[of == i], pid[of == i])) == alone
        assert counted[i].tolist() == [len(alone), trace.nodes_entered, trace.nodes_expanded, trace.leaves_scanned, trace.points_compared]


@pytest.mark.parametrize("kind", ["pab", "fpb", "kdt"])
@pytest.mark.parametrize("order", ["near_first", "right_first"])
def test_traces_together_are_those_of_each_query(kind, order):
    rng = np.random.default_rng(3)
    x, q = rng.random((1500, 2)), rng.random((40, 2))
    x[:500] = np.round(x[:500], 1)  # leaves above capacity, and ties
    t = kernel.build(x, np.arange(1500), BuildConfig(kind=kind, leaf_capacity=8))
    for k, r in ((1, np.inf), (10, np.inf), (10, 0.05), (50, 0.2)):
        want = []
        for v in q.tolist():
            trace = kernel.Trace()
            found = kernel.nearest_kernel(t, v, k, r, trace, order=order)
            want.append((len(found), trace.nodes_entered, trace.nodes_expanded, trace.leaves_scanned, trace.points_compared))
        assert kernel.nearest_traces(t, q, np.full(40, k), np.full(40, r), order).tolist() == [list(w) for w in want]


def test_large_trees_are_files(tmp_path, monkeypatch):
    """Their bytes only say where they are; those of a small tree hold it."""
    t = kernel.build(np.random.default_rng(5).random((300, 3)), np.arange(300), BuildConfig(leaf_capacity=8))
    assert t.stored(f"file://{tmp_path}", "a") == t.to_bytes()
    monkeypatch.setattr(kernel, "FILED", 0)
    place = t.stored(f"file://{tmp_path}", "b")
    assert len(place) < 1000
    u, some = kernel.Tree.from_bytes(place), kernel.Tree.from_bytes(place, ("lo", "depth"))
    assert all(np.array_equal(getattr(u, n), getattr(t, n), equal_nan=True) for n in kernel.Tree.ARRAYS)
    assert np.array_equal(some.lo, t.lo) and not len(some.x)


def test_nodes_split_in_runs_make_the_same_tree(monkeypatch):
    """Nodes of a level go in runs of at most SPLIT points, which bounds what is held beside the points."""
    rng = np.random.default_rng(5)
    x, pid = np.round(rng.random((3000, 2)), 2), np.arange(3000)
    for options in ({}, {"kind": "fpb"}, {"kind": "kdt", "kd_bounds": "cells"}):
        whole = build(x, pid, BuildConfig(leaf_capacity=4, **options))
        with monkeypatch.context() as m:
            m.setattr(kernel, "SPLIT", 100)
            most, level = [], kernel._Level.__init__
            m.setattr(kernel._Level, "__init__", lambda self, *a: (level(self, *a), most.append((len(self.n), len(self.x))))[0])
            runs = build(x, pid, BuildConfig(leaf_capacity=4, **options))
        assert all(np.array_equal(getattr(whole, n), getattr(runs, n), equal_nan=True) for n in whole.ARRAYS)
        assert all(points <= 100 for nodes, points in most if nodes > 1)


def test_traces_count_whole_nodes_without_going_down(monkeypatch):
    """A node wholly within reach is counted by what is below it, so few points are compared, with the counters of the procedure."""
    rng = np.random.default_rng(5)
    x = np.repeat(rng.random((1500, 2)), 2, axis=0)
    q, r, seen, real = rng.random((30, 2)), np.repeat([0.0, 0.05, 0.3, 0.9, 3.0, math.inf], 5), [], kernel.compared

    def watched(*args):
        for of, at, d2 in real(*args):
            seen.append(len(of))
            yield of, at, d2

    monkeypatch.setattr(kernel, "compared", watched)
    for options in ({}, {"kind": "fpb"}, {"kind": "kdt"}, {"kind": "kdt", "kd_bounds": "cells"}, {"kind": "kdt", "kd_bounds": "plane"}):
        t = kernel.build(x, np.arange(len(x)), BuildConfig(leaf_capacity=8, **options))
        want = []
        for v, limit in zip(q, r):
            trace = kernel.Trace()
            found = kernel.range_kernel(t, v.tolist(), limit, trace)
            want.append([len(found), trace.nodes_entered, trace.nodes_expanded, trace.leaves_scanned, trace.points_compared])
        seen.clear()
        assert kernel.range_traces(t, q, r).tolist() == want
        assert sum(seen) < sum(w[4] for w in want) / 10


def test_traces_merge_only_leaves_that_are_closer(monkeypatch):
    """Distances are merged for queries that a leaf comes nearer to, not at every leaf that is scanned, and mixed k and r have the procedure's counters."""
    rng = np.random.default_rng(6)
    x, q = np.repeat(rng.random((1500, 2)), 2, axis=0), rng.random((40, 2))
    k, r, rows, real = rng.integers(1, 20, 40), np.tile([0.02, 0.2, math.inf, 0.0], 10), [], np.sort
    t = kernel.build(x, np.arange(len(x)), BuildConfig(leaf_capacity=8))
    want = []
    for v, n, limit in zip(q, k, r):
        trace = kernel.Trace()
        found = kernel.nearest_kernel(t, v.tolist(), int(n), limit, trace, order="right_first")
        want.append([len(found), trace.nodes_entered, trace.nodes_expanded, trace.leaves_scanned, trace.points_compared])
    monkeypatch.setattr(np, "sort", lambda a, **o: rows.append(len(a)) or real(a, **o))
    assert kernel.nearest_traces(t, q, k, r, "right_first").tolist() == want
    assert 0 < sum(rows) < sum(w[3] for w in want) * 0.9


def test_only_some_arrays_are_kept():
    x = np.random.default_rng(7).random((500, 2))
    whole, some = (kernel.build(x, np.arange(500), BuildConfig(kind="fpb"), only=only) for only in (None, ("lo", "depth")))
    assert (whole.lo == some.lo).all() and (whole.depth == some.depth).all() and not some.center.size and not some.axis.size and whole.center.size
