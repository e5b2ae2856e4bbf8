"""The experiments: depth of trees, nodes visited by tree and by search, scaling, ablations."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ballspark.config import BuildConfig
from ballspark.operators import whole
from ballspark.operators.index import SpatialIndex, build_tree, saved
from ballspark.operators.pca import balanced_bound
from ballspark.operators.search import SEARCHED, nearest, range_search
from ballspark.operators.stats import QUALITY, average_cost, avg_depth, reduction, tree_quality
from ballspark.sources.generators import generate, with_outliers
from ballspark.sources.points import Points, to_points
from ballspark.sources.queries import data_queries, uniform_queries
from ballspark.sources.views import hash_cut, points

KINDS = ("pab", "fpb", "kdt")
#: Trees whose visits are compared; a KD-tree that tests the last cut alone prunes least.
COMPARED = {"pab": {}, "fpb": {"kind": "fpb"}, "kdt": {"kind": "kdt"}, "kdt cells": {"kind": "kdt", "kd_bounds": "cells"}, "kdt plane": {"kind": "kdt", "kd_bounds": "plane"}}
SYNTHETIC = ("latin", "highleyman", "niederreiter", "lithuanian", "sobol")
STANDINS = ("latin2", "events_uv2", "ship2", "events_tv2", "lattice2")
REAL4 = ("dup4", "events4")
QUERIES = 5300
#: Points of a generated set.
GENERATED = 500_000
#: Points of the trees that are built beside one another, or of one tree.
AT_ONCE = 2_000_000
#: The same where only depths are kept of a tree, and where trees of one set are searched one after another and dropped.
DEPTHS_AT_ONCE, SEARCHED_AT_ONCE = 12_000_000, 8_000_000
#: The same for trees of several parts, whose tasks are bounded: what counts is their disk.
PARTS_AT_ONCE = 24_000_000


def one_tree(p: Points | whole.Blocks, n: int | None = None, only: tuple[str, ...] | None = None, **options) -> SpatialIndex:
    """One tree over all the points, however many: beyond a part's points a top with subtrees, so that counters and depths are those of a single tree."""
    if isinstance(p, whole.Blocks):
        return whole.whole_tree(p, BuildConfig(**options), only=only)
    n = p.df.count() if n is None else n
    if n <= whole.PART:
        return build_tree(p, BuildConfig(local_rows=max(1, whole.PART), **options), n, only=only)
    blocks = whole.blocked(p)
    index = whole.whole_tree(blocks, BuildConfig(**options), p.scale, only)
    blocks.drop()
    return index


def _width(spark: SparkSession, n: int, most: int) -> int:
    """How many trees of n points are made beside one another, each being one task."""
    return max(1, min(spark.sparkContext.defaultParallelism, most // max(1, n)))


def _beside(spark: SparkSession, n: int, each: Callable[[tuple], list[tuple]], choices: Iterable[tuple], most: int = AT_ONCE) -> list[tuple]:
    """``each`` of the choices, in their order: a tree of n points is one task, so several are made at once, as ``most`` points allow."""
    with ThreadPoolExecutor(_width(spark, n, most)) as pool:
        return [row for rows in pool.map(each, choices) for row in rows]


def _filed(p: Points) -> tuple[Points | whole.Blocks, int]:
    """The points as files, blocks where they are more than a part, which trees are built from without making the points again for each, and how many they are."""
    n = p.df.count()
    if n > whole.PART:
        return whole.blocked(p), n
    return replace(p, df=saved(p.df.select("pid", "x")), filed=True), n


def _searched(spark: SparkSession, p: Points, each: Callable[[str, SpatialIndex], list[tuple]], trees: dict[str, dict], capacity: int) -> list[tuple]:
    """``each`` of the trees over the points: some are built beside one another, then searched one after another, as searches are timed, and dropped, as together they take many times the points' disk."""
    p, n = _filed(p)
    rows, names, width = [], list(trees), _width(spark, n, SEARCHED_AT_ONCE)
    with ThreadPoolExecutor(width) as pool:
        for a in range(0, len(names), width):
            some = names[a : a + width]
            for name, index in zip(some, list(pool.map(lambda name: one_tree(p, n, SEARCHED, leaf_capacity=capacity, **trees[name]), some))):
                rows += each(name, index)
                index.drop()
    if isinstance(p, whole.Blocks):
        p.drop()
    return rows


def _bounds(p: Points) -> list[tuple[float, float]]:
    r = p.df.agg(*[f(F.col("x")[j]).alias(f"{n}{j}") for j in range(p.dim) for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return [(r[f"lo{j}"], r[f"hi{j}"]) for j in range(p.dim)]


def _rows(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


DEPTHS = "view string, kind string, leaf_capacity int, n long, leaves long, avg_depth double, weighted_depth double, max_depth int, bound double"


def depth_rows(name: str, p: Points, capacity: int = 1) -> list[tuple]:
    blocks = whole.blocked(p)

    def measured(choice: tuple[str]) -> list[tuple]:
        r = whole.whole_depth(blocks, BuildConfig(kind=choice[0], leaf_capacity=capacity))
        return [(name, *choice, capacity, r.n, r.leaves, r.avg_depth, r.weighted_depth, r.max_depth, balanced_bound(r.leaves))]

    rows = _beside(p.df.sparkSession, blocks.n, measured, product(KINDS), DEPTHS_AT_ONCE)
    blocks.drop()
    return rows


def depth_report(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = (*STANDINS, *REAL4), generated: int = GENERATED, families: tuple[str, ...] = SYNTHETIC) -> DataFrame:
    """Average leaf depth of each tree with one point a leaf, on all rows of the stand-ins and on generated sets."""
    rows = []
    for v in views:
        rows += depth_rows(v, points(spark, sf_dir, v))
    for kind in families if generated else ():
        rows += depth_rows(f"generated {kind}", Points(generate(spark, kind, generated), 2))
    return _rows(spark, rows, DEPTHS)


def real_depths(spark: SparkSession, sf_dir: str, n: int, views: tuple[str, ...] = REAL4) -> DataFrame:
    """Average leaf depths of the trees over n points of each view, those of the smallest hash: the size of a published set."""
    rows = []
    for v in views:
        p = points(spark, sf_dir, v)
        rows += depth_rows(v, Points(hash_cut(p.df, n), p.dim, p.scale))
    return _rows(spark, rows, DEPTHS)


def quality_report(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("orders2", "events_uv2", "events4")) -> DataFrame:
    rows = []
    for v, kind in product(views, KINDS):
        r = tree_quality(one_tree(points(spark, sf_dir, v), kind=kind)).first()
        rows.append((v, kind, r.inner, r.imbalance, r.weighted_imbalance, r.child_radius, r.overlap, r.objective))
    return _rows(spark, rows, "view string, kind string, inner long, imbalance double, weighted_imbalance double, child_radius double, overlap double, objective double")


def _sets(spark: SparkSession, sf_dir: str, views: tuple[str, ...], generated: int, families: tuple[str, ...] = SYNTHETIC) -> list[tuple[str, Points]]:
    """The views, and the generated sets scaled to the unit square as they are."""
    sets = [(v, points(spark, sf_dir, v)) for v in views]
    for kind in families if generated else ():
        rows = generate(spark, kind, generated).select("pid", *[F.col("x")[j].alias(f"x{j}") for j in (0, 1)])
        sets.append((f"generated {kind}", to_points(rows, "pid", ["x0", "x1"], scale="minmax")))
    return sets


VISITS = "view string, kind string, search string, k int, r double, queries long, avg_entered double, avg_expanded double, avg_leaves double, avg_points double, avg_answers double, seconds double"


def _cost(view: str, kind: str, search: str, k: int | None, r: float | None, trace: DataFrame) -> tuple:
    began = time.monotonic()
    c = average_cost(trace).first()
    return (view, kind, search, k, r, c.queries, c.avg_entered, c.avg_expanded, c.avg_leaves, c.avg_points, c.avg_answers, time.monotonic() - began)


def visit_report(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("orders2", "events_uv2", "ship2"), queries: int = QUERIES, capacity: int = 8, rs: tuple = (0.02, 0.05, 0.1), ks: tuple = (1, 10, 50), generated: int = GENERATED, families: tuple[str, ...] = SYNTHETIC) -> DataFrame:
    """Nodes visited by one and the same search on the trees, uniform queries, on views and generated sets."""
    rows = []
    for v, p in _sets(spark, sf_dir, views, generated, families):
        qs = uniform_queries(spark, [(0.0, 1.0)] * p.dim, queries)

        def visits(kind: str, index: SpatialIndex) -> list[tuple]:
            ranges = [_cost(v, kind, "range", None, r, range_search(index, qs, r, trace=True)) for r in rs]
            return ranges + [_cost(v, kind, "knn", k, None, nearest(index, qs.drop("r"), k, trace=True)) for k in ks]

        rows += _searched(spark, p, visits, COMPARED, capacity)
    return _rows(spark, rows, VISITS)


def cvisit_report(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("orders2", "events_uv2", "ship2"), queries: int = QUERIES, capacity: int = 8, rs: tuple = (0.01, 0.02, 0.05), ks: tuple = (10, 50), orders: tuple = ("right_first", "near_first"), generated: int = GENERATED, families: tuple[str, ...] = SYNTHETIC) -> DataFrame:
    """Nodes visited and time of nearest neighbours with and without the range constraint, on the principal-axis tree, in equal visiting orders, on views and generated sets."""
    rows = []
    for v, p in _sets(spark, sf_dir, views, generated, families):
        qs = uniform_queries(spark, [(0.0, 1.0)] * p.dim, queries)

        def visits(kind: str, index: SpatialIndex) -> list[tuple]:
            found = []
            for order, k in product(orders, ks):
                found.append(_cost(v, kind, f"knn {order}", k, None, nearest(index, qs.drop("r"), k, trace=True, order=order)))
                found += [_cost(v, kind, f"constrained {order}", k, r, nearest(index, qs, k, r, trace=True, order=order)) for r in rs]
            return found

        rows += _searched(spark, p, visits, {"pab": {}}, capacity)
    return _rows(spark, rows, VISITS)


def reduction_report(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("orders2", "events_uv2"), queries: int = QUERIES, k: int = 10, rs: tuple = (0.01, 0.02, 0.05), orders: tuple = ("right_first", "near_first")) -> DataFrame:
    """By how much the range constraint lessens the nodes visited and points compared of nearest-neighbour searches.

    One search runs at a time: tasks of several would hold trees of different views beside one another.
    """
    out = None
    for v in views:
        p = points(spark, sf_dir, v)
        index, qs = one_tree(p, leaf_capacity=8), uniform_queries(spark, [(0.0, 1.0)] * p.dim, queries)
        for order in orders:
            base = saved(average_cost(nearest(index, qs.drop("r"), k, trace=True, order=order)))
            for r in rs:
                row = reduction(base, saved(average_cost(nearest(index, qs, k, r, trace=True, order=order)))).select(F.lit(v).alias("view"), F.lit(order).alias("order"), F.lit(k).alias("k"), F.lit(r).alias("r"), "queries", "base_entered", "ours_entered", "visits_saved", "comparisons_saved")
                out = row if out is None else out.unionByName(row)
    return out


def dominance(spark: SparkSession, sf_dir: str, view: str, k: int, r: float, queries: int = 200) -> DataFrame:
    """(queries, above_knn, above_range): queries whose constrained search entered more nodes than either search alone; none."""
    p = points(spark, sf_dir, view)
    index, qs = one_tree(p, leaf_capacity=8), uniform_queries(spark, [(0.0, 1.0)] * p.dim, queries)
    c, n = (nearest(index, qs, k, limit, trace=True, order="right_first").select("qid", F.col("nodes_entered").alias(name)) for limit, name in ((r, "c"), (math.inf, "n")))
    g = range_search(index, qs, r, trace=True).select("qid", F.col("nodes_entered").alias("g"))
    return c.join(n, "qid").join(g, "qid").agg(F.count("*").alias("queries"), F.count_if(F.col("c") > F.col("n")).alias("above_knn"), F.count_if(F.col("c") > F.col("g")).alias("above_range"))


def alpha_sweep(spark: SparkSession, sf_dir: str, view: str = "events_uv2", queries: int = QUERIES, alphas: tuple = (0.0, 0.25, 0.5, 1.0, 2.0, 4.0), sections: tuple = (8, 16, 64, 256), offsets: tuple = ("centred", "printed"), r: float = 0.05, k: int = 10) -> DataFrame:
    """Depth and nodes visited by the weight and the number of sections, for uniform queries and for queries from the data."""
    p = points(spark, sf_dir, view)
    sets = {name: saved(qs) for name, qs in (("uniform", uniform_queries(spark, _bounds(p), queries)), ("data", data_queries(p.df, queries)))}
    p, n = _filed(p)

    def swept(choice: tuple[str, int, float]) -> list[tuple]:
        offset, s, a = choice
        index = one_tree(p, n, SEARCHED, alpha=a, sections=s, offset=offset, leaf_capacity=8)
        depth = avg_depth(index).first()
        costs = {name: average_cost(nearest(index, qs, k, r, trace=True, order="right_first")).first() for name, qs in sets.items()}
        index.drop()
        return [(view, offset, s, a, name, depth.avg_depth, depth.max_depth, c.avg_entered, c.avg_points) for name, c in costs.items()]

    rows = _beside(spark, n, swept, product(offsets, sections, alphas), PARTS_AT_ONCE if isinstance(p, whole.Blocks) else AT_ONCE)
    if isinstance(p, whole.Blocks):
        p.drop()
    return _rows(spark, rows, "view string, offset string, sections int, alpha double, queries string, avg_depth double, max_depth int, avg_entered double, avg_points double")


def outlier_study(spark: SparkSession, sf_dir: str, view: str = "orders2") -> DataFrame:
    """Depth and imbalance with and without one point in a thousand ten times as far out."""
    rows, p = [], points(spark, sf_dir, view)
    for kind, far in product(("pab", "fpb"), (False, True)):
        q = Points(with_outliers(p.df, p.dim), p.dim) if far else p
        index = one_tree(q, only=QUALITY, kind=kind, leaf_capacity=1, alpha=0.0 if kind == "pab" else 0.5)
        d, t = avg_depth(index).first(), tree_quality(index).first()
        index.drop()
        rows.append((view, kind, far, d.avg_depth, d.max_depth, t.imbalance, t.weighted_imbalance))
    return _rows(spark, rows, "view string, kind string, outliers boolean, avg_depth double, max_depth int, imbalance double, weighted_imbalance double")


def scale_report(spark: SparkSession, sf_dir: str, sizes: tuple = (1_000, 10_000, 100_000, 1_000_000, 10_000_000), queries: int = QUERIES, k: int = 10, r: float = 0.05, generated: str = "uniform", view: str | None = "ship2") -> DataFrame:
    """Build and search seconds by the number of points, with the growth to the next size."""
    rows = []
    sets = [(f"generated {generated}", Points(generate(spark, generated, n), 2)) for n in sizes]
    if view:
        sets.append((view, points(spark, sf_dir, view)))
    for name, p in sets:
        began = time.monotonic()
        index = build_tree(p, BuildConfig())
        built = time.monotonic()
        qs = uniform_queries(spark, [(0.0, 1.0)] * p.dim, queries)
        answers = nearest(index, qs, k, r, order="right_first").count()
        rows.append((name, index.n, index.n_parts, built - began, time.monotonic() - built, answers))
    return _rows(spark, rows, "view string, n long, parts int, build_seconds double, search_seconds double, answers long")


def high_dimension(spark: SparkSession, sf_dir: str, queries: int = QUERIES, k: int = 10) -> DataFrame:
    """Unit vectors in 64 dimensions, nearly isotropic: pruning is expected to fail, answers to stay exact."""
    p = points(spark, sf_dir, "emb64")
    rows = []
    for kind in KINDS:
        index = one_tree(p, kind=kind, leaf_capacity=8)
        rows.append(_cost("emb64", kind, "knn", k, None, nearest(index, data_queries(p.df, queries).drop("r"), k, trace=True)))
    return _rows(spark, rows, VISITS)
