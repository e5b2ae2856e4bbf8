"""Queries whose indexes come to have several parts, as they do on larger tables, against their SQL."""

from functools import partial

import pytest
from pyspark.sql import functions as F

from ballspark import catalogue
from ballspark.config import BuildConfig
from ballspark.operators import pca
from ballspark.operators.index import build_tree
from ballspark.operators.joins import knn_join
from ballspark.operators.search import brute
from ballspark.operators.stats import avg_depth
from ballspark.plans import workloads
from ballspark.sources.generators import generate
from ballspark.sources.points import Points
from ballspark.sources.queries import data_queries, uniform_queries

from .test_queries import SQL, _rows, duck  # noqa: F401


@pytest.fixture
def small_parts(monkeypatch):
    """Parts of 400 rows, where the smallest tables have 1,000 events and 1,500 orders."""
    monkeypatch.setattr(catalogue, "BuildConfig", partial(BuildConfig, local_rows=400))
    monkeypatch.setattr(catalogue, "_built", {})
    yield
    assert all(index.n_parts > 1 for index, _ in catalogue._built.values())


@pytest.mark.parametrize("name", ["ball_enclosing", "inv_measures", "inv_visits", "sql_knn_of"])
def test_over_several_parts(spark, duck, sf_dir, small_parts, name):  # noqa: F811
    assert _rows(catalogue.QUERIES[name](spark, sf_dir).toPandas()) == _rows(duck.sql(SQL[name]).df())


def test_uniform_queries_are_of_a_table(spark, sf_dir):
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    rows = catalogue.QUERIES["uniform_queries"](spark, sf_dir)
    assert rows.select("qid").exceptAll(events.selectExpr("cast(event_id as bigint)")).isEmpty() and rows.count() == events.count()
    assert any(f.endswith("events.parquet") for f in rows.inputFiles())


def test_one_large_tree_is_no_row(spark):
    """Its row says where it is; depths are those of all points."""
    index = workloads.one_tree(Points(generate(spark, "highleyman", 120_000), 2), leaf_capacity=1)
    assert index.n_parts == 1 and index.parts.selectExpr("length(tree) AS bytes").first().bytes < 1000
    depth = avg_depth(index).first()
    assert (depth.n, depth.leaves) == (120_000, 120_000)


def test_projected_filter_sends_few_rows(spark, monkeypatch):
    """Of each task's points only the first few of each query leave it; equal points go by pid."""
    points, sent, least = generate(spark, "uniform", 6000).withColumn("x", F.transform("x", lambda v: F.round(v, 2))).repartition(2), [], pca._least
    queries = uniform_queries(spark, [(0.0, 1.0)] * 2, 5)
    monkeypatch.setattr(pca, "_least", lambda *a: (sent.append(rows := least(*a)), rows)[1])
    found = pca.pca_filter_knn(points, queries, 2, pca.fit_pca(points, 2), 1, 30)
    key = lambda df: sorted((r.qid, r.rank, r.pid, round(r.dist, 9)) for r in df.collect())
    assert key(found) == key(brute(points, queries.drop("k"), 2, 30))
    assert [rows.count() <= 2 * 5 * 30 for rows in sent] == [True, True]


def test_generated_sets_read_events(spark, sf_dir, monkeypatch):
    """Their points are those of a given table's ids."""
    from ballspark.sources import generators

    asked, made = [], generators.generate
    monkeypatch.setattr(generators, "generate", lambda *a, ids=None, **k: (asked.append(ids), made(*a, ids=ids, **k))[1])
    rows = catalogue.generated_sets(spark, sf_dir).collect()
    assert len(rows) == 3 and all(any(f.endswith("events.parquet") for f in ids.inputFiles()) for ids in asked)


def test_parts_stay_bounded(spark):
    """Parts asked for are a least number: each has its bound of points all the same, and no large tree is a row of the table."""
    p = Points(generate(spark, "uniform", 60_000), 2)
    index = build_tree(p, BuildConfig(parts=2, local_rows=20_000, leaf_capacity=4))
    rows = index.parts.selectExpr("n", "length(tree) AS bytes", "part_id").collect()
    assert len(rows) >= 3 and max(r.n for r in rows) <= 4 * 20_000 and all(r.bytes < 1000 for r in rows if r.n > 10_000)
    asks = uniform_queries(spark, [(0.0, 1.0)] * 2, 40)
    key = lambda df: sorted((r.qid, r.rank, r.pid) for r in df.collect())
    assert key(knn_join(index, asks, 3)) == key(brute(p.df, asks.drop("k"), 2, 3))


def test_sweep_builds_trees_beside_one_another(spark, sf_dir, monkeypatch):
    """Rows are those of trees made one after the other; queries from the data go to as many tasks as the session has."""
    small = {"queries": 10, "alphas": (0.0, 4.0), "sections": (8,)}
    at_once, most, made = [0], [0], workloads.one_tree

    def counted(*a, **k):
        at_once[0] += 1
        most[0] = max(most)
        most.append(at_once[0])
        try:
            return made(*a, **k)
        finally:
            at_once[0] -= 1

    monkeypatch.setattr(workloads, "one_tree", counted)
    beside = workloads.alpha_sweep(spark, sf_dir, **small).collect()
    assert max(most) > 1
    monkeypatch.setattr(workloads, "AT_ONCE", 1)
    assert workloads.alpha_sweep(spark, sf_dir, **small).collect() == beside
    asks = data_queries(Points(generate(spark, "uniform", 500), 2).df, 100)
    assert asks.rdd.getNumPartitions() == spark.sparkContext.defaultParallelism and asks.count() == 100
