"""Points, files, indexes in parts, streams: what the queries don't show."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from ballspark.config import BuildConfig
from ballspark.operators import levels, routing, search
from ballspark.operators.index import SpatialIndex, build_tree, saved
from ballspark.operators.joins import grid_range_join, interval_join
from ballspark.operators.stats import compare_exact, depth_histogram, invariants
from ballspark.plans.choose import choose_engine, parts_for, suggest_alpha
from ballspark.sources.generators import KINDS, generate, with_outliers
from ballspark.sources.points import Points, read_points, to_points, write_results
from ballspark.sources.queries import uniform_queries
from ballspark.streaming.search import marked_late, run_to_end, standing_nearest, stream_append


def test_bad_rows_are_left_out_and_counted(spark):
    rows = spark.createDataFrame([(1, 1.0, 2.0), (2, None, 1.0), (3, float("nan"), 1.0), (4, 3.0, 5.0)], "id long, a double, b double")
    p = to_points(rows, "id", ["a", "b"], scale="minmax")
    assert p.rejected == 2 and [tuple(r.x) for r in p.df.orderBy("pid").collect()] == [(0.0, 0.0), (1.0, 1.0)]
    with pytest.raises(ValueError):
        to_points(rows, "id", ["a", "b"], nulls="error")
    arrays = spark.createDataFrame([(1, [1.0, 2.0]), (2, [1.0]), (3, None), (4, [2.0, 2.0])], "id long, v array<double>")
    assert to_points(arrays, "id", array_col="v").rejected == 2
    assert to_points(rows.where("false"), "id", ["a", "b"], scale="zscore").df.count() == 0


def test_coordinates_of_every_type(spark):
    rows = spark.sql("SELECT 1L AS id, true AS b, DATE'1970-01-03' AS d, TIMESTAMP_NTZ'1970-01-01 00:01:30' AS t, CAST(2.5 AS DECIMAL(8,2)) AS m, INTERVAL '1 00:00:10' DAY TO SECOND AS i")
    assert list(to_points(rows, "id", ["b", "d", "t", "m", "i"]).df.first().x) == [1.0, 2.0, 90.0, 2.5, 86410.0]


def test_files_round_trip(spark, tmp_path):
    rows = spark.createDataFrame([(1, 0.5, 1.5), (2, 2.5, 3.5)], "id long, a double, b double")
    for fmt in ("parquet", "orc", "json", "csv"):
        write_results(rows, f"{tmp_path}/{fmt}", fmt)
        assert read_points(spark, f"{tmp_path}/{fmt}", fmt, "id long, a double, b double").select("id", "a", "b").orderBy("id").collect() == rows.collect()
    (tmp_path / "bad.csv").write_text("1,0.5,1.5\nx,y\n")
    got = read_points(spark, f"{tmp_path}/bad.csv", "csv", "id long, a double, b double").orderBy("id").collect()
    assert got[0]._rejected == "x,y" and got[1].id == 1


@pytest.mark.parametrize("options", [{"top": "sample"}, {"top": "exact"}, {"top": "sample", "kind": "fpb"}, {"top": "sample", "kind": "kdt"}, {"top": "exact", "kind": "kdt"}, {"top": "exact", "kind": "fpb"}])
def test_parts_answer_like_one_tree(spark, options):
    p = Points(saved(generate(spark, "highleyman", 3000)), 2)
    qs = saved(uniform_queries(spark, [(-1.0, 4.0)] * 2, 20))
    index = build_tree(p, BuildConfig(parts=6, local_rows=500, leaf_capacity=8, **options))
    assert index.n == 3000 and index.n_parts > 1
    v = invariants(index).first()
    assert (v.points, v.cover, v.partition_gap, v.over_capacity, v.parent_gap, v.unsplit) == (3000, 0, 0, 0, 0, 0)
    truth = search.brute(p.df, qs, 2, 10, 0.7)
    for found in (search.constrained_knn(index, qs, 10, 0.7), search.nearest(index, qs, 10, 0.7, bound="metadata")):
        assert compare_exact(found, truth).first() == (0, 0, 0.0)
    every = search.brute(p.df, qs, 2, None, 0.7)
    for engine in ("routed", "frontier", "flat"):
        assert compare_exact(search.range_search(index, qs, 0.7, engine), every).first()[:2] == (0, 0)
    assert compare_exact(grid_range_join(p.df, qs, 0.7, 2), every).first()[:2] == (0, 0)


def test_equal_points_beyond_a_part(spark):
    p = Points(saved(spark.range(900).select(F.col("id").alias("pid"), F.array(F.lit(1.0), F.lit(2.0)).alias("x"))), 2)
    index = build_tree(p, BuildConfig(parts=4, local_rows=100))
    asks = spark.createDataFrame([(0, [1.0, 2.0])], "qid long, q array<double>")
    assert [r.pid for r in search.knn_search(index, asks, 5).orderBy("rank").collect()] == [0, 1, 2, 3, 4]
    assert search.range_count(index, asks, 0.0).first().n == 900


def test_empty_index_and_bad_arguments(spark, tmp_path):
    none = build_tree(Points(generate(spark, "uniform", 0), 2))
    asks = uniform_queries(spark, [(0.0, 1.0)] * 2, 3)
    assert search.range_search(none, asks, 1.0).count() == 0 and search.knn_search(none, asks, 3).count() == 0
    assert search.range_count(none, asks, 1.0).agg(F.sum("n")).first()[0] == 0
    for k, r in ((0, 1.0), (1, -1.0)):
        with pytest.raises(ValueError):
            search.nearest(none if k else build_tree(Points(generate(spark, "uniform", 5), 2)), asks, k, r).count()
    full = build_tree(Points(generate(spark, "uniform", 50), 2))
    assert search.knn_search(full, asks, 51).count() == 150
    full.save(f"{tmp_path}/index")
    again = SpatialIndex.load(spark, f"{tmp_path}/index")
    assert (again.n, again.dim, again.config) == (50, 2, full.config) and depth_histogram(again).count() >= 1
    assert choose_engine(full, 10) == "brute" and parts_for(10**9, 2) == 90 and suggest_alpha(1.0) == 0.0


def test_generators_are_sound(spark):
    for kind in KINDS:
        rows = generate(spark, kind, 256).select("pid", F.col("x")[0].alias("a"), F.col("x")[1].alias("b")).toPandas()
        assert len(rows) == 256 and rows.notna().all().all() and rows[["a", "b"]].drop_duplicates().shape[0] == 256
    assert with_outliers(generate(spark, "uniform", 5000), 2).where(F.col("x")[0] > 1).count() > 0


def test_interval_join_by_buckets(spark):
    a = spark.createDataFrame([(1, 0), (1, 59), (1, 125), (2, 10)], "u long, t long")
    b = spark.createDataFrame([(1, 60), (1, 66), (2, 200)], "u long, s long")
    got = sorted((r.t, r.s) for r in interval_join(a, b, ["u"], "t", "s", 60).collect())
    assert got == [(0, 60), (59, 60), (59, 66), (125, 66)]


def test_streams_of_points(spark, tmp_path):
    pts = generate(spark, "uniform", 300)
    pts.where("pid < 150").coalesce(1).write.parquet(f"{tmp_path}/in/a")
    pts.where("pid >= 150").coalesce(1).write.parquet(f"{tmp_path}/in/b")
    stream = spark.readStream.schema("pid long, x array<double>").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    start = build_tree(Points(generate(spark, "uniform", 0), 2))
    asks = uniform_queries(spark, [(0.0, 1.0)] * 2, 5)
    index = stream_append(stream, start)
    truth = search.brute(pts, asks, 2, 4)
    assert index.n == 300 and compare_exact(search.knn_search(index, asks, 4), truth).first()[:2] == (0, 0)


def test_standing_queries_over_several_batches(spark, tmp_path):
    """Three batches, the last of which holds nothing that any query takes; then a stream without rows."""
    pts = generate(spark, "uniform", 300)
    asks = uniform_queries(spark, [(0.0, 1.0)] * 2, 5)
    truth = search.brute(pts, asks, 2, 4).collect()
    best = {r.pid for r in truth}
    one, two = sorted(best)[::2], sorted(best)[1::2]
    for name, some in (("a", F.col("pid").isin(one)), ("b", F.col("pid").isin(two)), ("c", ~F.col("pid").isin(sorted(best)))):
        pts.where(some).coalesce(1).write.parquet(f"{tmp_path}/in/{name}")
    stream = spark.readStream.schema("pid long, x array<double>").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    last = run_to_end(standing_nearest(stream, asks, 4, 2), mode="update", key=["qid"])
    assert {(r.qid, r["rank"], r.pid) for r in last.collect()} == {(r.qid, r["rank"], r.pid) for r in truth} and last.count() == len(truth)
    few = spark.readStream.schema("pid long, x array<double>").parquet(f"{tmp_path}/in/c")
    none = run_to_end(standing_nearest(few.where("pid < 0"), asks, 4, 2), mode="update", key=["qid"])
    assert none.count() == 0
    with pytest.raises(ValueError):
        run_to_end(standing_nearest(few, asks, 4, 2), mode="update")


def test_late_rows_are_marked(spark, tmp_path):
    times = [["2024-01-01 10:00:00", None, "2024-01-01 12:00:00"], ["2024-01-01 10:59:59", "2024-01-01 11:00:00", "2024-01-01 09:00:00"], ["2024-01-01 15:00:00", "2024-01-01 11:30:00"]]
    for i, some in enumerate(times):
        spark.createDataFrame([(10 * i + j, t) for j, t in enumerate(some)], "id long, ts string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema("id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    got = {r.id: r.late for r in marked_late(stream, "ts", "1 hour").collect()}
    assert got == {0: False, 1: False, 2: False, 10: True, 11: False, 12: True, 20: False, 21: False}


@pytest.mark.parametrize("kind", ["pab", "kdt"])
def test_branches_of_scale_answer_alike(spark, monkeypatch, kind):
    """Routers over blocks of parts, queries that are too many to be broadcast, and groups of few queries."""
    p = Points(saved(generate(spark, "lithuanian", 3000)), 2)
    qs = saved(uniform_queries(spark, [(-8.0, 12.0)] * 2, 150))
    index = build_tree(p, BuildConfig(parts=40, top="sample", sample_rows=50, local_rows=200, leaf_capacity=8, kind=kind))
    truth, every = search.brute(p.df, qs, 2, 7), search.brute(p.df, qs, 2, None, 1.0)
    want = [search.range_count(index, qs, 1.0).orderBy("qid").collect(), index.append(generate(spark, "uniform", 40).withColumn("pid", F.col("pid") + 10_000)).n]
    monkeypatch.setattr(routing, "ROUTED_PARTS", 12)
    monkeypatch.setattr(search, "BROADCAST_QUERIES", 10)
    monkeypatch.setattr(search, "CHUNK", 16)
    index.made = None
    assert index.routing().blocks.count() > 1
    assert compare_exact(search.knn_search(index, qs, 7), truth).first()[:2] == (0, 0)
    assert compare_exact(search.nearest(index, qs, 7, bound="metadata"), truth).first()[:2] == (0, 0)
    assert compare_exact(search.range_search(index, qs, 1.0), every).first()[:2] == (0, 0)
    more = index.append(generate(spark, "uniform", 40).withColumn("pid", F.col("pid") + 10_000))
    assert [search.range_count(index, qs, 1.0).orderBy("qid").collect(), more.n] == want


def test_a_part_that_outgrows_its_size_is_cut(spark):
    index = build_tree(Points(generate(spark, "uniform", 200), 2), BuildConfig(parts=2, top="sample", local_rows=100, leaf_capacity=8))
    more = index.append(generate(spark, "uniform", 1500).withColumns({"pid": F.col("pid") + 1000, "x": F.transform("x", lambda v: v / 100)}))
    assert more.n == 1700 and more.n_parts > 3 and more.parts.agg(F.max("n")).first()[0] <= 400
    asks = uniform_queries(spark, [(0.0, 0.02)] * 2, 10)
    assert compare_exact(search.knn_search(more, asks, 5), search.brute(more.leaf_points().select("pid", "x"), asks, 2, 5)).first()[:2] == (0, 0)


def test_routers_are_right():
    rng = np.random.default_rng(4)
    regions = pd.DataFrame({"part_id": np.arange(200)[::-1], "n": rng.integers(1, 9, 200), "center": list(rng.random((200, 2))), "radius": rng.random(200) * 0.1})
    center = np.array(regions["center"].tolist())
    regions["box_lo"], regions["box_hi"] = list(center - regions["radius"].to_numpy()[:, None] / 2), list(center + regions["radius"].to_numpy()[:, None] / 2)
    q, reach, k = rng.random((50, 2)), rng.random(50) * 0.2, rng.integers(1, 40, 50)
    for kind in ("pab", "kdt"):
        r = routing.Router.over(regions, kind)
        far = np.sqrt(((q[:, None] - center[None]) ** 2).sum(axis=2))
        gap = np.maximum(0, far - regions["radius"].to_numpy()) if kind == "pab" else np.sqrt((np.maximum(0, np.abs(q[:, None] - center[None]) - regions["radius"].to_numpy()[None, :, None] / 2) ** 2).sum(axis=2))
        who, ids = r.meets(q, reach)
        assert sorted(zip(who, ids)) == sorted((i, regions["part_id"][j]) for i, j in zip(*np.nonzero(gap <= reach[:, None])))
        assert (r.nearest_center(q) == regions["part_id"].to_numpy()[far.argmin(axis=1)]).all()
        assert set(r.home(q)) <= set(regions["part_id"])
        order = np.argsort(far + regions["radius"].to_numpy(), axis=1)
        least = [np.take(far[i] + regions["radius"].to_numpy(), order[i])[np.searchsorted(np.cumsum(regions["n"].to_numpy()[order[i]]), k[i])] for i in range(50)]
        assert (r.bound(q, k) >= np.array(least) - 1e-9).all() and np.isfinite(r.bound(q, k)).all()


def test_medians_are_exact(spark, monkeypatch):
    """By histograms: spread, tied, single and two values, in passes of a few bins."""
    rng = np.random.default_rng(6)
    sets = [rng.random(501), rng.integers(0, 3, 400).astype(float), np.array([2.5]), np.array([1.0, 4.0]), np.full(300, 7.0), np.concatenate([np.zeros(50), np.ones(50)]), rng.lognormal(0, 9, 800)]
    values = spark.createDataFrame([(i, float(v)) for i, s in enumerate(sets) for v in s], "code long, v double")
    ranges = values.groupBy("code").agg(F.count("*").alias("n"), F.min("v").alias("low"), F.max("v").alias("high"))
    for bins, gathered in ((1024, 4096), (8, 5)):
        monkeypatch.setattr(levels, "BINS", bins)
        monkeypatch.setattr(levels, "GATHERED", gathered)
        got = {r.code: r.cut for r in levels.medians(values, ranges).collect()}
        assert all(got[i] == (np.sort(s)[(len(s) - 1) // 2] + np.sort(s)[len(s) // 2]) / 2 for i, s in enumerate(sets))


def test_levels_in_turns(spark, monkeypatch):
    p = Points(saved(generate(spark, "lithuanian", 2000)), 2)
    want = levels.assign_levels(p.df, 2, BuildConfig(), 300).groupBy("part_id").count()
    monkeypatch.setattr(levels, "AT_ONCE", 2)
    got = levels.assign_levels(p.df, 2, BuildConfig(), 300).groupBy("part_id").count()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and got.agg(F.max("count")).first()[0] <= 300
