"""The registered experiments take whole tables; small arguments against brute force."""

import inspect
import os

import pytest

from ballspark.operators.kernel import Tree
from ballspark.operators.search import brute
from ballspark.operators.stats import avg_depth
from ballspark.plans import workloads
from ballspark.sources.queries import uniform_queries

SF001 = "/root/testdata/sf0.01"


def test_depth_report_takes_all_rows(spark):
    rows = workloads.depth_report(spark, SF001, ("dup4", "events4"), 0).collect()
    lines, events = (spark.read.parquet(f"{SF001}/{t}.parquet").count() for t in ("lineitem", "events"))
    assert {(r.view, r.n) for r in rows} == {("dup4", lines), ("events4", events)} and lines > 10_000
    assert len(rows) == 2 * len(workloads.KINDS)


def test_defaults_are_whole():
    """inv_dominance is not among these: its SQL says 200 queries."""
    default = lambda f, name: inspect.signature(f).parameters[name].default
    for f in (workloads.visit_report, workloads.cvisit_report, workloads.alpha_sweep, workloads.scale_report, workloads.high_dimension):
        assert default(f, "queries") == 5300
    for f in (workloads.depth_report, workloads.visit_report, workloads.cvisit_report):
        assert default(f, "generated") == 500_000
    assert default(workloads.alpha_sweep, "sections") == (8, 16, 64, 256)
    assert default(workloads.scale_report, "sizes")[-2:] == (10**6, 10**7)


def test_visits_answer_as_brute_force(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(workloads, "COMPARED", {"pab": {}})
    one = {"generated": 300, "families": ("lithuanian",)}
    got = {(r.view, r.search, r.r): r for r in workloads.visit_report(spark, sf_dir, ("orders2",), queries=12, rs=(0.1,), ks=(5,), **one).collect()}
    near = {(r.view, r.search): r for r in workloads.cvisit_report(spark, sf_dir, ("orders2",), queries=12, rs=(0.05,), ks=(5,), orders=("near_first",), **one).collect()}
    for v, p in workloads._sets(spark, sf_dir, ("orders2",), 300, ("lithuanian",)):
        qs = uniform_queries(spark, [(0.0, 1.0)] * 2, 12)
        assert got[v, "range", 0.1].queries == 12 == near[v, "knn near_first"].queries
        assert got[v, "range", 0.1].avg_answers == pytest.approx(brute(p.df, qs, 2, None, 0.1).count() / 12)
        assert near[v, "constrained near_first"].avg_answers == pytest.approx(brute(p.df, qs, 2, 5, 0.05).count() / 12)
    assert len(got) == 4 and len(near) == 4


def test_reductions(spark, sf_dir):
    rows = workloads.reduction_report(spark, sf_dir, ("orders2",), queries=20, rs=(0.01, 0.05)).collect()
    assert {(r.order, r.r) for r in rows} == {(o, r) for o in ("right_first", "near_first") for r in (0.01, 0.05)}
    for r in rows:
        assert r.queries == 20 and r.visits_saved == pytest.approx((r.base_entered - r.ours_entered) / r.base_entered) and 0 <= r.visits_saved < 1


def test_small_reports(spark, sf_dir):
    """The reports that are not run at their defaults, on small grids: all combinations, and the order of depths that the trees are known for."""
    depth = workloads.depth_report(spark, sf_dir, ("events4",), 2000, ("highleyman",)).collect()
    by = {(r.view, r.kind): r for r in depth}
    assert len(depth) == 6 and all(r.bound - 1e-9 <= r.avg_depth <= r.max_depth for r in depth)
    assert by["generated highleyman", "pab"].avg_depth < by["generated highleyman", "fpb"].avg_depth
    sweep = workloads.alpha_sweep(spark, sf_dir, queries=10, alphas=(0.0, 4.0), sections=(8, 64)).collect()
    assert len(sweep) == 16 and all(r.avg_entered > 0 for r in sweep)
    quality = workloads.quality_report(spark, sf_dir, ("orders2",)).collect()
    assert {r.kind for r in quality} == set(workloads.KINDS) and all(0 <= r.imbalance <= 1 for r in quality)


def test_reductions_are_searched_one_after_another(spark, sf_dir):
    """What is returned reads the searches' averages and searches nothing itself: its tasks would hold trees of different views at once."""
    report = workloads.reduction_report(spark, sf_dir, ("orders2",), queries=20, rs=(0.01,), orders=("right_first",))
    assert "MapIn" not in report._jdf.queryExecution().toString() and report.count() == 1


def test_visited_trees_are_dropped(spark, sf_dir, monkeypatch):
    """Trees of a report are built from points that are written once, and each goes after its searches: together they take many times the points' disk."""
    made, real, there = [], workloads.build_tree, lambda place: os.path.exists(place.removeprefix("file:"))

    def built(p, *args, **options):
        index = real(p, *args, **options)
        tree = Tree.from_bytes(index.parts.first().tree)
        assert tree.center.size and not tree.axis.size and not tree.pivot_lo.size and not tree.parent.size  # what searches don't read is not written
        made.append((p.filed, index.places, [there(place) for place in index.places][-1]))
        return index

    monkeypatch.setattr(workloads, "build_tree", built)
    visits = workloads.visit_report(spark, sf_dir, ("orders2",), queries=5, rs=(0.1,), ks=(1,), generated=0).collect()
    near = workloads.cvisit_report(spark, sf_dir, ("orders2",), queries=5, rs=(0.1,), ks=(5,), orders=("near_first",), generated=0).collect()
    assert [r.kind for r in visits] == [k for k in workloads.COMPARED for _ in range(2)] and len(near) == 2
    assert len(made) == len(workloads.COMPARED) + 1 and all(filed and was for filed, _, was in made)
    assert not any(there(place) for _, places, _ in made for place in places)


def test_depths_need_no_written_tree(spark, sf_dir, monkeypatch):
    """Depths are counted in the task that builds a tree, and are those of the tree that is written otherwise."""
    p = workloads.points(spark, sf_dir, "events4")
    want = [avg_depth(workloads.one_tree(p, kind=kind, leaf_capacity=1)).first() for kind in workloads.KINDS]

    def written(*args, **options):
        raise AssertionError("a tree is written")

    monkeypatch.setattr(workloads, "build_tree", written)
    got = workloads.depth_rows("events4", p)
    assert [row[3:8] for row in got] == [tuple(r) for r in want] and [row[1] for row in got] == list(workloads.KINDS)
