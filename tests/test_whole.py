"""One tree of several parts is the tree that one task builds: the same depths, counters and measures."""

import os

import pytest

from ballspark.config import BuildConfig
from ballspark.operators import whole
from ballspark.operators.index import build_tree
from ballspark.operators.search import SEARCHED, nearest, range_search
from ballspark.operators.stats import avg_depth, tree_quality
from ballspark.plans import workloads
from ballspark.sources.queries import data_queries, uniform_queries
from ballspark.sources.views import points


@pytest.fixture
def small(monkeypatch):
    """Parts and blocks of a few points, so that the smallest tables have many."""
    monkeypatch.setattr(whole, "PART", 150)
    monkeypatch.setattr(whole, "BINS", 8)


@pytest.mark.parametrize("view", ["orders2", "dup4", "events4"])
def test_depths_do_not_depend_on_parts(spark, sf_dir, monkeypatch, view):
    p = points(spark, sf_dir, view)
    want = workloads.depth_rows(view, p)
    for part in (1000, 150):
        monkeypatch.setattr(whole, "PART", part)
        assert workloads.depth_rows(view, p) == [pytest.approx(row) for row in want]


TREES = {**workloads.COMPARED, "fpb 1": {"kind": "fpb", "leaf_capacity": 1}, "printed": {"offset": "printed", "alpha": 1.0, "sections": 8}}


@pytest.mark.parametrize("name", sorted(TREES))
def test_counters_are_those_of_one_task(spark, sf_dir, small, name):
    p, cfg = points(spark, sf_dir, "orders2"), BuildConfig(**({"leaf_capacity": 8} | TREES[name]))
    one, many = build_tree(p, cfg), whole.whole_tree(whole.blocked(p), cfg, only=SEARCHED)
    assert one.n_parts == 1 and many.n_parts > 8 and many.top.depth.max() > 2
    qs = uniform_queries(spark, [(0.0, 1.0)] * 2, 40).unionByName(data_queries(p.df, 10).selectExpr("qid + 1000000 AS qid", "q", "k", "r")).drop("k", "r")
    counted = lambda df: sorted(map(tuple, df.select("qid", "answers", "nodes_entered", "nodes_expanded", "leaves_scanned", "points_compared").collect()))
    for r in (0.0, 0.03, 0.3, 5.0):
        assert counted(range_search(one, qs, r, trace=True)) == counted(range_search(many, qs, r, trace=True))
    for order in ("near_first", "right_first"):
        for k, r in ((1, None), (10, None), (10, 0.02), (400, 0.5)):
            assert counted(nearest(one, qs, k, r, trace=True, order=order)) == counted(nearest(many, qs, k, r, trace=True, order=order))
    found = lambda index: sorted((row.qid, row["rank"], row.pid) for row in nearest(index, qs, 5).collect())
    assert found(one) == found(many)


@pytest.mark.parametrize("kind", workloads.KINDS)
def test_quality_is_that_of_one_task(spark, sf_dir, small, kind):
    p, cfg = points(spark, sf_dir, "events_uv2"), BuildConfig(kind=kind, leaf_capacity=1)
    one, many = build_tree(p, cfg), whole.whole_tree(whole.blocked(p), cfg, only=workloads.QUALITY)
    assert many.n_parts > 3
    assert tuple(tree_quality(many).first()) == pytest.approx(tuple(tree_quality(one).first()), nan_ok=True)
    assert tuple(avg_depth(many).first()) == pytest.approx(tuple(avg_depth(one).first()))


def test_reports_count_over_parts(spark, sf_dir, monkeypatch):
    """Reports whose trees have several parts used to raise."""
    args = {"queries": 12, "ks": (5,), "generated": 0}
    counted = lambda: [tuple(row)[:11] for f, rs in ((workloads.visit_report, (0.1,)), (workloads.cvisit_report, (0.05,))) for row in f(spark, sf_dir, ("orders2",), rs=rs, **args).collect()]
    want = counted()
    monkeypatch.setattr(whole, "PART", 300)
    assert counted() == [pytest.approx(row) for row in want] and len(want) == 14
    study = [tuple(row) for row in workloads.outlier_study(spark, sf_dir).collect()]
    monkeypatch.undo()
    assert study == [pytest.approx(tuple(row)) for row in workloads.outlier_study(spark, sf_dir).collect()]


def test_sweep_over_parts_drops_its_trees(spark, sf_dir, monkeypatch):
    """The sweep's trees used to stay, and were made from the table each."""
    small, made, real, wrote = {"queries": 10, "alphas": (0.0, 4.0), "sections": (8,)}, [], workloads.one_tree, []
    want = workloads.alpha_sweep(spark, sf_dir, **small).collect()
    monkeypatch.setattr(whole, "PART", 400)
    monkeypatch.setattr(workloads, "one_tree", lambda *a, **k: (made.append(real(*a, **k)), made[-1])[1])
    monkeypatch.setattr(whole, "blocked", lambda p, f=whole.blocked: (wrote.append(f(p)), wrote[-1])[1])
    got = workloads.alpha_sweep(spark, sf_dir, **small).collect()
    assert got == [pytest.approx(tuple(row)) for row in want] and len(got) == 8
    assert len(made) == 4 and all(index.n_parts > 1 for index in made) and len(wrote) == 1
    assert not any(os.path.exists(place.removeprefix("file:")) for index in made for place in index.places)
