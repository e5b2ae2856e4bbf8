"""The queries that the driver runs, by name, with the SQL that each is held against."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ballspark.config import BuildConfig
from ballspark.functions.geometry import bounding_box_predicate, project, register_sql, sq_dist
from ballspark.functions.udtf import register_knn_of
from ballspark.operators import joins, levels, search, stats
from ballspark.operators.index import SpatialIndex, build_tree, shared_dir
from ballspark.operators.pca import balanced_depth, fit_pca, pca_filter_knn, pca_transform
from ballspark.plans import oracle, workloads
from ballspark.sources import queries as query_sets
from ballspark.sources.points import Points, load, read_points, write_results
from ballspark.sources.views import VIEWS, points
from ballspark.streaming.search import deduplicated, event_stream, marked_late, nearby_events, run_to_end, standing_nearest, stream_append, stream_constrained, window_counts

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Indexes of this session, by where their points come from: several queries search one.
_built: dict[tuple, tuple[SpatialIndex, Points]] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def indexed(spark: SparkSession, sf_dir: str, view: str, **options) -> tuple[SpatialIndex, Points]:
    key = (spark.sparkContext.applicationId, sf_dir, view, tuple(sorted(options.items())))
    if key not in _built:
        p = points(spark, sf_dir, view)
        _built[key] = build_tree(p, BuildConfig(**options)), p
    return _built[key]


def _rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns or ("dist",)})


def _uniform(spark: SparkSession, dim: int, m: int = 50, k: int | None = None, r: float | None = None) -> DataFrame:
    return query_sets.uniform_queries(spark, [(0.0, 1.0)] * dim, m, k, r)


# --- range searches ---------------------------------------------------------------------------------


def _range(view: str, r: float, engine: str = "routed", **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index, p = indexed(spark, sf_dir, view, **options)
        return _rounded(search.range_search(index, _uniform(spark, p.dim), r, engine))

    return run


def _range_sql(view: str, r: float) -> str:
    return oracle.in_range(view, oracle.uniform(VIEWS[view].dim, 50), r)


for _name, _view, _r, _engine, _options in (
    ("range_orders2", "orders2", 0.05, "routed", {}),
    ("range_ship2", "ship2", 0.02, "routed", {}),
    ("range_events_uv2", "events_uv2", 0.05, "routed", {}),
    ("range_line4", "line4", 0.1, "routed", {}),
    ("range_frontier", "ship2", 0.02, "frontier", {}),
    ("range_flat", "ship2", 0.02, "flat", {}),
    ("range_fpb", "orders2", 0.05, "routed", {"kind": "fpb"}),
    ("range_kdt", "orders2", 0.05, "routed", {"kind": "kdt"}),
    ("range_enclosing", "orders2", 0.05, "routed", {"ball": "enclosing"}),
):
    query(_name, _range_sql(_view, _r))(_range(_view, _r, _engine, **_options))


@query("range_point_lookup", oracle.in_range("orders2", oracle.sampled(2, 50), 0.0))
def range_point_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, p = indexed(spark, sf_dir, "orders2")
    return _rounded(search.range_search(index, query_sets.data_queries(p.df, 50), 0.0))


@query("range_count", f"WITH {oracle.points('events_uv2')}, {oracle.uniform(2, 50)}, {oracle.pairs(2, 0.1)} SELECT qid, count(pid) AS n FROM qs LEFT JOIN pairs USING (qid) GROUP BY qid")
def range_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, p = indexed(spark, sf_dir, "events_uv2")
    return search.range_count(index, _uniform(spark, 2), 0.1)


_FAR = oracle.uniform(2, 50, -1.0, 2.0)


@query("range_exists", f"WITH {oracle.points('events_uv2')}, {_FAR}, {oracle.pairs(2, 0.05)} SELECT qid, count(pid) > 0 AS found FROM qs LEFT JOIN pairs USING (qid) GROUP BY qid")
def range_exists(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "events_uv2")
    return search.range_exists(index, query_sets.far_queries(spark, 2, 50), 0.05)


@query("left_outer_answers", f"WITH {oracle.points('orders2')}, {_FAR}, {oracle.pairs(2, 0.05)} SELECT qs.qid, pid, round(sqrt(d2), 6) AS dist FROM qs LEFT JOIN pairs USING (qid)")
def left_outer_answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "orders2")
    far = query_sets.far_queries(spark, 2, 50)
    return _rounded(joins.left_outer(far, search.range_search(index, far, 0.05)))


# --- nearest neighbours -----------------------------------------------------------------------------


def _nearest(view: str, k: int, r: float | None = None, how: str = "nearest", build: dict | None = None, m: int = 50, data: bool = False, **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index, p = indexed(spark, sf_dir, view, **(build or {}))
        qs = query_sets.data_queries(p.df, m) if data else _uniform(spark, p.dim, m)
        if how == "nearest":
            found = search.nearest(index, qs.drop("r"), k, r, **options)
        elif how == "constrained":
            found = search.constrained_knn(index, qs, k, r, **options)
        elif how == "knn_then_range":
            found = search.knn_then_range(index, qs, k, r)
        elif how == "range_then_topk":
            found = search.range_then_topk(index, qs, k, r)
        else:
            found = search.brute(p.df, qs, p.dim, k, r)
        return _rounded(found)

    return run


def _nearest_sql(view: str, k: int, r: float | None = None, m: int = 50, data: bool = False) -> str:
    dim = VIEWS[view].dim
    return oracle.k_nearest(view, oracle.sampled(dim, m) if data else oracle.uniform(dim, m), k, r)


for _name, _view, _k, _r, _how, _build, _options in (
    ("knn_orders2", "orders2", 10, None, "nearest", {}, {}),
    ("knn_ship2", "ship2", 10, None, "nearest", {}, {}),
    ("knn_events_uv2", "events_uv2", 10, None, "nearest", {}, {}),
    ("knn_dup4", "dup4", 50, None, "nearest", {}, {}),
    ("knn_right_first", "orders2", 10, None, "nearest", {}, {"order": "right_first"}),
    ("knn_no_carry", "orders2", 10, None, "nearest", {}, {"carry_bound": False}),
    ("knn_best_first", "orders2", 10, None, "nearest", {}, {"order": "best_first"}),
    ("knn_fpb", "orders2", 10, None, "nearest", {"kind": "fpb"}, {}),
    ("knn_kdt", "orders2", 10, None, "nearest", {"kind": "kdt"}, {}),
    ("cnn_orders2", "orders2", 10, 0.02, "constrained", {}, {}),
    ("cnn_ship2", "ship2", 10, 0.01, "constrained", {}, {}),
    ("cnn_events_tv2", "events_tv2", 10, 0.05, "constrained", {}, {}),
    ("cnn_events4", "events4", 10, 0.3, "constrained", {}, {}),
    ("cnn_line4", "line4", 10, 0.1, "constrained", {}, {}),
    ("cnn_conjunction", "orders2", 10, 0.02, "constrained", {}, {"prune": "conjunction"}),
    ("cnn_no_child_test", "orders2", 10, 0.02, "constrained", {}, {"child_test": False}),
    ("cnn_fpb", "orders2", 10, 0.02, "constrained", {"kind": "fpb"}, {}),
    ("cnn_kdt", "orders2", 10, 0.02, "constrained", {"kind": "kdt"}, {}),
    ("cnn_gram", "orders2", 10, 0.02, "constrained", {"axis": "gram"}, {}),
    ("cnn_power", "orders2", 10, 0.02, "constrained", {"axis_solver": "power"}, {}),
    ("cnn_printed", "orders2", 10, 0.02, "constrained", {"offset": "printed"}, {}),
    ("cnn_data_mean", "orders2", 10, 0.02, "constrained", {"candidate": "data_mean"}, {}),
    ("cnn_exhaustive", "orders2", 10, 0.02, "constrained", {"cut": "exhaustive"}, {}),
    ("knn_then_range", "orders2", 10, 0.02, "knn_then_range", {}, {}),
    ("range_then_topk", "orders2", 10, 0.02, "range_then_topk", {}, {}),
    ("brute_constrained", "orders2", 10, 0.02, "brute", {}, {}),
    ("brute_knn", "orders2", 10, None, "brute", {}, {}),
    ("filtered_knn", "open_orders2", 10, None, "nearest", {}, {}),
    ("two_tier_knn", "orders2", 10, None, "nearest", {"parts": 16, "top": "sample"}, {}),
    ("two_tier_cnn", "orders2", 10, 0.02, "constrained", {"parts": 16, "top": "sample"}, {}),
    ("two_tier_fpb", "orders2", 10, 0.02, "constrained", {"parts": 16, "top": "sample", "kind": "fpb"}, {}),
    ("two_tier_kdt", "orders2", 10, 0.02, "constrained", {"parts": 16, "top": "sample", "kind": "kdt"}, {}),
    ("cnn_kdt_cycle", "orders2", 10, 0.02, "constrained", {"kind": "kdt", "kd_axis": "cycle"}, {}),
    ("cnn_kdt_variance", "orders2", 10, 0.02, "constrained", {"kind": "kdt", "kd_axis": "variance"}, {}),
    ("cnn_kdt_midpoint", "orders2", 10, 0.02, "constrained", {"kind": "kdt", "kd_cut": "midpoint"}, {}),
    ("cnn_kdt_cells", "orders2", 10, 0.02, "constrained", {"kind": "kdt", "kd_bounds": "cells"}, {}),
    ("cnn_kdt_plane", "orders2", 10, 0.02, "constrained", {"kind": "kdt", "kd_bounds": "plane"}, {}),
    ("cnn_one_by_one", "orders2", 10, 0.02, "constrained", {}, {"order": "near_first"}),
    ("exact_top_kdt", "events_uv2", 10, 0.05, "constrained", {"parts": 8, "top": "exact", "kind": "kdt"}, {}),
    ("exact_top_fpb", "events_uv2", 10, 0.05, "constrained", {"parts": 8, "top": "exact", "kind": "fpb"}, {}),
    ("exact_top_cnn", "events_uv2", 10, 0.05, "constrained", {"parts": 8, "top": "exact"}, {}),
):
    query(_name, _nearest_sql(_view, _k, _r))(_nearest(_view, _k, _r, _how, _build, **_options))

query("knn_emb64", _nearest_sql("emb64", 10, None, 20, True))(_nearest("emb64", 10, m=20, data=True))


@query(
    "cnn_per_query_kr",
    f"WITH {oracle.points('orders2')}, {oracle.uniform(2, 50)}, all_pairs AS (SELECT *, {oracle.d2(2)} AS d2, qid % 7 + 1 AS k, 0.01e0 + (qid % 5) * 0.01e0 AS r FROM qs, pts), "
    f"pairs AS (SELECT * FROM all_pairs WHERE d2 <= r * r), {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked WHERE rank <= k",
)
def cnn_per_query_kr(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "orders2")
    qs = _uniform(spark, 2).withColumns({"k": (F.col("qid") % 7 + 1).cast("int"), "r": F.lit(0.01) + (F.col("qid") % 5) * F.lit(0.01)})
    return _rounded(search.constrained_knn(index, qs))


_ATTACHED = "qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist, o_orderstatus, o_orderpriority, c_mktsegment"


@query("attach_orders", oracle.k_nearest("orders2", oracle.uniform(2, 50), 10, 0.02, _ATTACHED, "JOIN orders ON o_orderkey = pid JOIN customer ON c_custkey = o_custkey"))
def attach_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "orders2")
    found = _rounded(search.constrained_knn(index, _uniform(spark, 2), 10, 0.02))
    orders = load(spark, sf_dir, "orders").join(load(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return search.attach(found, orders, "o_orderkey", ["o_orderstatus", "o_orderpriority", "c_mktsegment"]).select("qid", "rank", "pid", "dist", "o_orderstatus", "o_orderpriority", "c_mktsegment")


@query(
    "post_filtered_knn",
    f"WITH {oracle.points('orders2')}, {oracle.uniform(2, 50)}, {oracle.pairs(2)}, {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked JOIN orders ON o_orderkey = pid WHERE rank <= 10 AND o_orderstatus = 'O'",
)
def post_filtered_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The open ones among the ten nearest orders of any kind: the filter comes after the search, so some queries have fewer than ten."""
    index, _ = indexed(spark, sf_dir, "orders2")
    found = search.attach(search.knn_search(index, _uniform(spark, 2), 10), load(spark, sf_dir, "orders"), "o_orderkey", ["o_orderstatus"])
    return _rounded(found.where("o_orderstatus = 'O'").select("qid", "rank", "pid", "dist"))


@query(
    "answer_cardinality",
    f"WITH {oracle.points('orders2')}, {_FAR}, {oracle.pairs(2, 0.02)}, c AS (SELECT qid, least(10, count(pid)) AS n FROM qs LEFT JOIN pairs USING (qid) GROUP BY qid) "
    "SELECT count(*) AS queries, CAST(sum(n) AS BIGINT) AS answers, count(*) FILTER (n < 10) AS fewer, count(*) FILTER (n = 0) AS none, round(count(*) FILTER (n < 10) / count(*), 6) AS share_fewer FROM c",
)
def answer_cardinality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many answers constrained searches have, and the share of queries with fewer than K."""
    index, _ = indexed(spark, sf_dir, "orders2")
    far = query_sets.far_queries(spark, 2, 50)
    return stats.cardinality(search.constrained_knn(index, far, 10, 0.02), far, 10).withColumn("share_fewer", F.round("share_fewer", 6))


_BOTH = f"WITH {oracle.points('orders2')}, {oracle.uniform(2, 50)}, {oracle.pairs(2, 0.05)}, {oracle.RANKED} SELECT qid, pid FROM ranked WHERE rank <= 10 INTERSECT SELECT qid, pid FROM pairs WHERE d2 <= 0.03e0 * 0.03e0"


@query("knn_intersect_range", _BOTH)
def knn_intersect_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The set intersection of two searches' answers: the ten nearest within a range, and a smaller range."""
    index, _ = indexed(spark, sf_dir, "orders2")
    near, inside = search.constrained_knn(index, _uniform(spark, 2), 10, 0.05), search.range_search(index, _uniform(spark, 2), 0.03)
    return near.select("qid", "pid").intersect(inside.select("qid", "pid"))


@query("approximate_measures", "SELECT true AS count_near, true AS median_near, true AS tail_near")
def approximate_measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Approximate distinct points among answers and percentiles of their distances, against the exact ones."""
    index, _ = indexed(spark, sf_dir, "orders2")
    found = search.range_search(index, _uniform(spark, 2), 0.05)
    close = lambda a, b, share: F.abs(a - b) <= share * b + F.lit(1e-9)
    return found.agg(
        close(F.approx_count_distinct("pid", 0.01), F.count_distinct("pid"), 0.05).alias("count_near"),
        close(F.percentile_approx("dist", 0.5, 10_000), F.percentile("dist", F.lit(0.5)), 0.02).alias("median_near"),
        close(F.percentile_approx("dist", 0.99, 10_000), F.percentile("dist", F.lit(0.99)), 0.02).alias("tail_near"),
    )


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return attach_orders(spark, sf_dir)


# --- joins ------------------------------------------------------------------------------------------


def _knn_join(r: float | None, bound: str = "data") -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index, _ = indexed(spark, sf_dir, "ship2", parts=8, top="sample")
        asks = points(spark, sf_dir, "orders2").df.select(F.col("pid").alias("qid"), F.col("x").alias("q"))
        return _rounded(joins.knn_join(index, asks, 5, r, bound))

    return run


def _knn_join_sql(r: float | None) -> str:
    asks = "qs AS (SELECT pid AS qid, x0 AS q0, x1 AS q1 FROM ords)"
    return f"WITH {oracle.points('ship2')}, {oracle.points('orders2', 'ords')}, {asks}, {oracle.pairs(2, r)}, {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked WHERE rank <= 5"


def _knn_join_grid(cell: float) -> str:
    """The same by an equi-join of cells: right as long as each query has its five within a cell's side, else rows would be missing."""
    asks = f"qs AS (SELECT pid AS qid, x0 AS q0, x1 AS q1, floor(x0 / {cell}) + dx AS c0, floor(x1 / {cell}) + dy AS c1 FROM ords, (VALUES (-1), (0), (1)) a(dx), (VALUES (-1), (0), (1)) b(dy))"
    held = f"held AS (SELECT *, floor(x0 / {cell}) AS c0, floor(x1 / {cell}) AS c1 FROM pts)"
    near = f"pairs AS (SELECT qid, pid, {oracle.d2(2)} AS d2 FROM qs JOIN held USING (c0, c1))"
    return f"WITH {oracle.points('ship2')}, {oracle.points('orders2', 'ords')}, {asks}, {held}, {near}, {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked WHERE rank <= 5 AND d2 <= {cell} * {cell}"


def _knn_join_cells(cell: float) -> str:
    """The same by cells where a query has its five within a cell's side, and by all pairs for the queries that don't: whole on any tables."""
    asks = "qs AS (SELECT pid AS qid, x0 AS q0, x1 AS q1 FROM ords)"
    moved = f"moved AS (SELECT *, floor(q0 / {cell}) + dx AS c0, floor(q1 / {cell}) + dy AS c1 FROM qs, (VALUES (-1), (0), (1)) a(dx), (VALUES (-1), (0), (1)) b(dy))"
    held = f"held AS (SELECT *, floor(x0 / {cell}) AS c0, floor(x1 / {cell}) AS c1 FROM pts)"
    near = f"near AS (SELECT qid, pid, {oracle.d2(2)} AS d2 FROM moved JOIN held USING (c0, c1))"
    full = f"full_ AS (SELECT qid FROM near WHERE d2 <= {cell} * {cell} GROUP BY qid HAVING count(*) >= 5)"
    few = "few AS (SELECT * FROM qs ANTI JOIN full_ USING (qid))"
    pairs = f"pairs AS (SELECT qid, pid, d2 FROM near SEMI JOIN full_ USING (qid) UNION ALL SELECT qid, pid, {oracle.d2(2)} AS d2 FROM few, pts)"
    return f"WITH {oracle.points('ship2')}, {oracle.points('orders2', 'ords')}, {asks}, {moved}, {held}, {near}, {full}, {few}, {pairs}, {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked WHERE rank <= 5"


#: Without cells, on the smallest tables, where ranking all pairs is quick: tests hold the joins against both.
SMALL_ORACLES = {"knn_join_two_round": _knn_join_sql(None), "knn_join_metadata": _knn_join_sql(None)}
_JOIN_CELL = 0.1
query("knn_join_two_round", _knn_join_cells(_JOIN_CELL))(_knn_join(None))
query("knn_join_bounded", _knn_join_sql(0.01))(_knn_join(0.01))
query("knn_join_metadata", _knn_join_grid(_JOIN_CELL))(_knn_join(None, "metadata"))

_ASKS_SELF = "qs AS (SELECT pid AS qid, x0 AS q0, x1 AS q1 FROM pts)"


@query("self_neighbours", f"WITH {oracle.points('orders2')}, {_ASKS_SELF}, {oracle.pairs(2, 0.005)} SELECT qid, pid, round(sqrt(d2), 6) AS dist FROM pairs WHERE qid <> pid")
def self_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, p = indexed(spark, sf_dir, "orders2")
    return _rounded(joins.self_neighbours(index, p.df, 0.005))


@query("knn_self_join", f"WITH {oracle.points('cust2')}, pairs AS (SELECT a.pid AS qid, b.pid AS pid, (b.x0 - a.x0) * (b.x0 - a.x0) + (b.x1 - a.x1) * (b.x1 - a.x1) AS d2 FROM pts a JOIN pts b ON a.pid <> b.pid), {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked WHERE rank <= 3")
def knn_self_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, p = indexed(spark, sf_dir, "cust2")
    return _rounded(joins.knn_self_join(index, p.df, 3)).select("qid", F.col("rank").cast("int").alias("rank"), "pid", "dist")


@query("rotated_knn", _nearest_sql("line4", 10))
def rotated_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A tree over points turned to their principal components; queries are turned alike."""
    p = points(spark, sf_dir, "line4")
    return _rounded(search.knn_search(build_tree(p, BuildConfig(), transform="pca"), _uniform(spark, 4), 10))


@query("grid_range_join", oracle.in_range("ship2", oracle.uniform(2, 200), 0.01))
def grid_range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir, "ship2")
    return _rounded(joins.grid_range_join(p.df, _uniform(spark, 2, 200), 0.01, 2))


_OTHERS = f"WITH {oracle.points('orders2')} SELECT pid FROM pts a WHERE {{}} EXISTS (SELECT 1 FROM pts b WHERE b.pid <> a.pid AND (a.x0 - b.x0) * (a.x0 - b.x0) + (a.x1 - b.x1) * (a.x1 - b.x1) <= 0.004e0 * 0.004e0)"


@query("range_semi_join", _OTHERS.format(""))
def range_semi_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, p = indexed(spark, sf_dir, "orders2")
    return joins.range_semi_join(index, p.df, 0.004).select("pid")


@query("range_anti_join", _OTHERS.format("NOT"))
def range_anti_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, p = indexed(spark, sf_dir, "orders2")
    return joins.range_anti_join(index, p.df, 0.004).select("pid")


_MICROS = VIEWS["events_tv2"].spark[0].rsplit("/", 1)[0].strip()


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").withColumn("micros", F.expr(_MICROS).cast("long"))


@query("interval_join", "SELECT p.event_id, e.event_id AS error_id FROM events p JOIN events e ON p.user_id = e.user_id AND abs(epoch_us(p.ts) - epoch_us(e.ts)) <= 3600000000 WHERE p.event_type = 'purchase' AND e.event_type = 'error'")
def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _events(spark, sf_dir)
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", F.col("micros").alias("p_micros"))
    right = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("micros").alias("e_micros"))
    return joins.interval_join(left, right, ["user_id"], "p_micros", "e_micros", 3_600_000_000).select("event_id", "error_id")


@query(
    "asof_event",
    "SELECT p.event_id, (SELECT max(struct_pack(t := epoch_us(e.ts), i := e.event_id)).i FROM events e WHERE e.user_id = p.user_id AND e.ts < p.ts) AS last_event FROM events p WHERE p.event_type = 'purchase'",
)
def asof_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _events(spark, sf_dir).select("event_id", "user_id", "event_type", "micros")
    return joins.asof_join(e.where("event_type = 'purchase'"), e, "user_id", "micros", "event_id", "last_event").select("event_id", "last_event")


# --- splits over all points -------------------------------------------------------------------------

ROOT_VIEWS = ("orders2", "ship2", "events_uv2")


def _each(views: tuple[str, ...], one: Callable[[str, Points], DataFrame]) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        for v in views:
            rows = one(v, points(spark, sf_dir, v)).withColumn("view", F.lit(v))
            out = rows if out is None else out.unionByName(rows)
        return out

    return run


def _each_sql(views: tuple[str, ...], select: str, step: Callable[[str], str] | None = None) -> str:
    return " UNION ALL ".join(f"SELECT * FROM (WITH {oracle.root(v)}{', ' + step('top') if step else ''} {select.replace('{view}', v)})" for v in views)


def _coded(p: Points) -> DataFrame:
    return p.df.select(F.lit(1).cast("long").alias("code"), "pid", "x")


def _moments(v: str, p: Points) -> DataFrame:
    m = levels.node_moments(_coded(p), 2)
    return m.select("n", *[F.round(F.col("mean")[j], 6).alias(f"mean{j}") for j in range(2)], *[F.round(F.col("c")[i] / F.col("n"), 6).alias(c) for i, c in enumerate(("var0", "cov", "var1"))])


query(
    "root_moments",
    _each_sql(ROOT_VIEWS, "SELECT count(*) AS n, round(avg(x0), 6) AS mean0, round(avg(x1), 6) AS mean1, round(var_pop(x0), 6) AS var0, round(covar_pop(x0, x1), 6) AS cov, round(var_pop(x1), 6) AS var1, '{view}' AS view FROM top"),
)(_each(ROOT_VIEWS, _moments))


def _axis(gram: bool) -> Callable[[str, Points], DataFrame]:
    def one(v: str, p: Points) -> DataFrame:
        m = levels.raw_moments(_coded(p), 2) if gram else levels.node_moments(_coded(p), 2)
        return levels.principal_axis(m, 2).select(F.round(F.col("axis")[0], 6).alias("axis0"), F.round(F.col("axis")[1], 6).alias("axis1"))

    return one


query("root_axis", _each_sql(ROOT_VIEWS, "SELECT round(w0, 6) AS axis0, round(w1, 6) AS axis1, '{view}' AS view FROM axis", lambda at: oracle.pab_step(at)))(_each(ROOT_VIEWS, _axis(False)))
query("root_axis_gram", _each_sql(ROOT_VIEWS, "SELECT round(w0, 6) AS axis0, round(w1, 6) AS axis1, '{view}' AS view FROM axis", lambda at: oracle.pab_step(at, gram=True)))(_each(ROOT_VIEWS, _axis(True)))


def _placed(p: Points, cfg: BuildConfig) -> tuple[DataFrame, DataFrame]:
    rows = _coded(p)
    m = levels.raw_moments(rows, p.dim) if cfg.axis == "gram" else levels.node_moments(rows, p.dim)
    placed = levels.projected(rows, levels.principal_axis(m, p.dim), p.dim)
    return placed, levels.extents(placed)


query("root_projection_extent", _each_sql(ROOT_VIEWS, "SELECT round(t_min, 6) AS t_min, round(t_max, 6) AS t_max, '{view}' AS view FROM ext", lambda at: oracle.pab_step(at)))(
    _each(ROOT_VIEWS, lambda v, p: _placed(p, BuildConfig())[1].select(F.round("t_min", 6).alias("t_min"), F.round("t_max", 6).alias("t_max")))
)


def _scan(v: str, p: Points) -> DataFrame:
    cfg = BuildConfig()
    return _rounded(levels.section_scan(*_placed(p, cfg), cfg).select("section", "t_c", "n_below", "f1", "f2", "f"), "t_c", "f1", "f2", "f")


query("root_section_scan", _each_sql(("events_uv2",), "SELECT section, round(t_c, 6) AS t_c, n_below, round(f1, 6) AS f1, round(f2, 6) AS f2, round(f, 6) AS f, '{view}' AS view FROM goal", lambda at: oracle.pab_step(at)))(_each(("events_uv2",), _scan))


def _cut(cut: Callable, cfg: BuildConfig) -> Callable[[str, Points], DataFrame]:
    def one(v: str, p: Points) -> DataFrame:
        placed, extent = _placed(p, cfg)
        found = cut(levels.section_scan(placed, extent, cfg)) if cut is levels.best_cut else cut(placed, extent, cfg)
        return found.select(F.round("t_c", 6).alias("t_c"), F.col("n_lo").cast("long"), F.col("n_hi").cast("long"))

    return one


_CUT = "SELECT round(t_c, 6) AS t_c, n_below AS n_lo, n - n_below AS n_hi, '{view}' AS view FROM cut"
CUT_VIEWS = ("events_uv2",)
query("root_cut_centred", _each_sql(CUT_VIEWS, _CUT, lambda at: oracle.pab_step(at)))(_each(CUT_VIEWS, _cut(levels.best_cut, BuildConfig())))
query("root_cut_printed", _each_sql(CUT_VIEWS, _CUT, lambda at: oracle.pab_step(at, offset="printed")))(_each(CUT_VIEWS, _cut(levels.best_cut, BuildConfig(offset="printed"))))

_MEANS = (
    ", sec AS (SELECT code, t, t_min, t_max, n, least(63, CAST(floor((t - t_min) / (t_max - t_min) * 64) AS INTEGER)) AS section FROM (SELECT code, t FROM place) JOIN ext USING (code)), "
    "mid AS (SELECT code, section, avg(t) AS t_c, any_value(t_min) AS t_min, any_value(t_max) AS t_max, any_value(n) AS n FROM sec GROUP BY code, section), "
    "low AS (SELECT m.*, (SELECT count(*) FROM sec s WHERE s.t < m.t_c) AS n_below FROM mid m) "
)
_BEST = "ORDER BY round(abs(n - 2 * n_below) / CAST(n AS DOUBLE) + 0.5e0 * abs(2 * (t_c - t_min) / (t_max - t_min) - 1), 12), t_c LIMIT 1"
query("root_cut_datamean", _each_sql(CUT_VIEWS, _MEANS + f"SELECT round(t_c, 6) AS t_c, n_below AS n_lo, n - n_below AS n_hi, '{{view}}' AS view FROM low {_BEST}", lambda at: oracle.pab_step(at)).replace(")  , sec", "), sec"))(
    _each(CUT_VIEWS, _cut(levels.mean_cut, BuildConfig(candidate="data_mean")))
)
_GAPS = (
    ", vals AS (SELECT t, count(*) AS c FROM place GROUP BY t), gaps AS (SELECT (t + lead(t) OVER (ORDER BY t)) / 2 AS t_c, CAST(sum(c) OVER (ORDER BY t) AS BIGINT) AS n_below FROM vals), "
    "low AS (SELECT gaps.*, t_min, t_max, n FROM gaps, ext WHERE t_c IS NOT NULL) "
)
query("root_cut_exhaustive", _each_sql(CUT_VIEWS, _GAPS + f"SELECT round(t_c, 6) AS t_c, n_below AS n_lo, n - n_below AS n_hi, '{{view}}' AS view FROM low {_BEST}", lambda at: oracle.pab_step(at)))(
    _each(CUT_VIEWS, _cut(levels.exhaustive_cut, BuildConfig(cut="exhaustive")))
)


def _level3(view: str, **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = points(spark, sf_dir, view)
        return levels.levels(p.df, p.dim, BuildConfig(**options), 3).groupBy("code").agg(F.count("*").alias("n"))

    return run


query("pab_level3", oracle.level3("events_uv2", oracle.pab_step))(_level3("events_uv2"))
query("fpb_level3", oracle.level3("events_uv2", oracle.fpb_step))(_level3("events_uv2", kind="fpb"))
query("kdt_level3", oracle.level3("events_uv2", oracle.kdt_step))(_level3("events_uv2", kind="kdt"))


@query("fpb_root", f"WITH {oracle.root('events_uv2')}, {oracle.fpb_step('top')} SELECT round(a0, 6) AS lo0, round(a1, 6) AS lo1, round(b0, 6) AS hi0, round(b1, 6) AS hi1 FROM two")
def fpb_root(spark: SparkSession, sf_dir: str) -> DataFrame:
    pivots = levels.fpb_pivots(_coded(points(spark, sf_dir, "events_uv2")), 2)
    return pivots.select(*[F.round(F.col(f"pivot_{s}")[j], 6).alias(f"{s}{j}") for s in ("lo", "hi") for j in range(2)])


@query("kdt_root", f"WITH {oracle.root('events_uv2')}, {oracle.kdt_step('top')} SELECT CAST(dim AS INTEGER) AS dim, round(cut, 6) AS cut, n FROM kcut")
def kdt_root(spark: SparkSession, sf_dir: str) -> DataFrame:
    return levels.kd_cuts(_coded(points(spark, sf_dir, "events_uv2")), 2, BuildConfig(kind="kdt")).select("dim", F.round("cut", 6).alias("cut"), "n")


@query("root_ball", f"WITH {oracle.points('orders2')}, m AS (SELECT count(*) AS n, avg(x0) AS q0, avg(x1) AS q1 FROM pts) SELECT any_value(n) AS n, round(any_value(q0), 6) AS center0, round(any_value(q1), 6) AS center1, round(sqrt(max({oracle.d2(2)})), 6) AS radius FROM pts, m")
def root_ball(spark: SparkSession, sf_dir: str) -> DataFrame:
    return levels.root_ball(points(spark, sf_dir, "orders2").df, 2).select("n", F.round(F.col("center")[0], 6).alias("center0"), F.round(F.col("center")[1], 6).alias("center1"), F.round("radius", 6).alias("radius"))


# --- invariants: violation counts, zero in a sound tree ---------------------------------------------


def _invariant(name: str, column: str) -> None:
    @query(name, f"SELECT kind, (SELECT count(*) FROM orders) AS points, CAST(0 AS BIGINT) AS {column} FROM (VALUES ('pab'), ('fpb'), ('kdt')) t(kind)")
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        for kind in workloads.KINDS:
            index, _ = indexed(spark, sf_dir, "orders2", kind=kind, leaf_capacity=8)
            row = stats.invariants(index).select(F.lit(kind).alias("kind"), "points", F.col(column).cast("long").alias(column))
            out = row if out is None else out.unionByName(row)
        return out


for _name, _column in (("inv_cover", "cover"), ("inv_partition", "partition_gap"), ("inv_leafcap", "over_capacity"), ("inv_parent_n", "parent_gap"), ("inv_progress", "unsplit")):
    _invariant(_name, _column)


@query("inv_bound", "SELECT CAST(0 AS BIGINT) AS violations, count(*) AS points FROM orders")
def inv_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every point against the balls of all nodes above it: no carried bound can be above a true distance."""
    index, p = indexed(spark, sf_dir, "orders2", leaf_capacity=8)
    return stats.ancestors_cover(index).select("violations", F.lit(index.n).cast("long").alias("points"))


@query("inv_dominance", "SELECT CAST(200 AS BIGINT) AS queries, CAST(0 AS BIGINT) AS above_knn, CAST(0 AS BIGINT) AS above_range")
def inv_dominance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.dominance(spark, sf_dir, "orders2", 10, 0.02)


@query("ball_enclosing", "SELECT count(*) AS points, CAST(0 AS BIGINT) AS cover, CAST(0 AS BIGINT) AS larger FROM events")
def ball_enclosing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Enclosing balls cover their points, and none is larger than the centroid ball of the same node."""
    small, _ = indexed(spark, sf_dir, "events_uv2", ball="enclosing")
    plain, _ = indexed(spark, sf_dir, "events_uv2")
    node = ["part_id", "node_id"]
    both = small.nodes().select(*node, "radius").join(plain.nodes().select(*node, F.col("radius").alias("other")), node)
    larger = both.agg(F.count_if(F.col("radius") > F.col("other") * (1 + 1e-9)).alias("larger"))
    return stats.invariants(small).select("points", "cover").join(larger)


@query("exactness_report", "SELECT engine, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra FROM (VALUES ('routed'), ('frontier'), ('flat'), ('fpb'), ('kdt'), ('two tiers')) t(engine)")
def exactness_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir, "orders2")
    qs = _uniform(spark, 2, 20)
    truth = search.brute(p.df, qs, 2, None, 0.05)
    ways = {"routed": ({}, "routed"), "frontier": ({}, "frontier"), "flat": ({}, "flat"), "fpb": ({"kind": "fpb"}, "routed"), "kdt": ({"kind": "kdt"}, "routed"), "two tiers": ({"parts": 16, "top": "sample"}, "routed")}
    out = None
    for name, (options, engine) in ways.items():
        index, _ = indexed(spark, sf_dir, "orders2", **options)
        row = stats.compare_exact(search.range_search(index, qs, 0.05, engine), truth).select(F.lit(name).alias("engine"), "missing", "extra")
        out = row if out is None else out.unionByName(row)
    return out


# --- reports ----------------------------------------------------------------------------------------

QUERIES |= {
    "depth_report": partial(workloads.depth_report, families=()),
    "quality_report": workloads.quality_report,
    "visit_report": partial(workloads.visit_report, families=()),
    "cvisit_report": partial(workloads.cvisit_report, families=()),
    "alpha_sweep": workloads.alpha_sweep,
    "outlier_study": workloads.outlier_study,
    "scale_report": workloads.scale_report,
    "high_dimension_report": workloads.high_dimension,
    "reduction_report": workloads.reduction_report,
}

#: The same on the generated sets, a query for each, as they have many points.
QUERIES |= {f"{name}_{family}": partial(report, views=(), families=(family,)) for family in workloads.SYNTHETIC for name, report in (("depth", workloads.depth_report), ("visits", workloads.visit_report), ("cvisits", workloads.cvisit_report))}

REPORT_VIEWS, REPORT_K, REPORT_R = ("orders2", "events_uv2"), (1, 10), (0.02, 0.05)


def _answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(view, k, r, qid, pid) of constrained searches on a grid: each is a prefix of the widest one's answers."""
    out = None
    for v in REPORT_VIEWS:
        index, p = indexed(spark, sf_dir, v)
        found = search.constrained_knn(index, _uniform(spark, p.dim), max(REPORT_K), max(REPORT_R)).withColumn("view", F.lit(v))
        out = found if out is None else out.unionByName(found)
    grid = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.lit(r).alias("r")) for k in REPORT_K for r in REPORT_R]))
    return out.withColumn("g", grid).where((F.col("rank") <= F.col("g.k")) & (F.col("dist") <= F.col("g.r"))).select("view", "g.k", "g.r", "qid", "pid")


_ANSWERS_SQL = "WITH answers AS (" + " UNION ALL ".join(
    f"SELECT '{v}' AS view, k, r, qid, pid FROM ({oracle.k_nearest(v, oracle.uniform(2, 50), max(REPORT_K), max(REPORT_R), 'qid, rank, pid, sqrt(d2) AS dist')}), "
    f"(VALUES {', '.join(f'({k}, {oracle.number(r)})' for k in REPORT_K for r in REPORT_R)}) g(k, r) WHERE rank <= k AND dist <= r"
    for v in REPORT_VIEWS
) + ") "
query("report_cube", _ANSWERS_SQL + "SELECT view, k, r, count(*) AS answers FROM answers GROUP BY CUBE (view, k, r)")(lambda spark, sf_dir: _answers(spark, sf_dir).cube("view", "k", "r").agg(F.count("*").alias("answers")))
query("report_rollup", _ANSWERS_SQL + "SELECT view, k, r, count(*) AS answers FROM answers GROUP BY ROLLUP (view, k, r)")(lambda spark, sf_dir: _answers(spark, sf_dir).rollup("view", "k", "r").agg(F.count("*").alias("answers")))
query("report_pivot", _ANSWERS_SQL + "SELECT view, count(*) FILTER (k = 1) AS k1, count(*) FILTER (k = 10) AS k10 FROM answers GROUP BY view")(
    lambda spark, sf_dir: _answers(spark, sf_dir).withColumn("k", F.concat(F.lit("k"), "k")).groupBy("view").pivot("k", ["k1", "k10"]).count()
)


@query("report_grouping_sets", _ANSWERS_SQL + "SELECT view, k, count(*) AS answers, count(DISTINCT pid) AS points FROM answers GROUP BY GROUPING SETS ((view), (k), ())")
def report_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    _answers(spark, sf_dir).createOrReplaceTempView("ballspark_answers")
    return spark.sql("SELECT view, k, count(*) AS answers, count(DISTINCT pid) AS points FROM ballspark_answers GROUP BY GROUPING SETS ((view), (k), ())")


@query(
    "distance_distribution",
    f"WITH {oracle.points('orders2')}, {oracle.uniform(2, 50)}, {oracle.pairs(2)}, {oracle.RANKED} SELECT qid, CAST(ntile(4) OVER w AS INTEGER) AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, "
    "round(sqrt(d2) - lag(sqrt(d2)) OVER w, 6) AS step FROM ranked WHERE rank = 10 WINDOW w AS (ORDER BY d2, qid)",
)
def distance_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How the tenth distances of the queries are spread: one row a query, a bounded set."""
    index, _ = indexed(spark, sf_dir, "orders2")
    tenth = search.knn_search(index, _uniform(spark, 2), 10).where("rank = 10")
    w = Window.orderBy("dist", "qid")
    return tenth.select("qid", F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.round(F.col("dist") - F.lag("dist").over(w), 6).alias("step"))


@query("price_neighbours", "SELECT o_orderkey, count(*) OVER (ORDER BY o_totalprice RANGE BETWEEN 50 PRECEDING AND 50 FOLLOWING) - 1 AS near FROM orders")
def price_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many other orders are within 50 of each one's price: a range search in one dimension, counted by cells, without a global sort."""
    cell = F.floor(F.col("o_totalprice") / 50).cast("long")
    rows = load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice", cell.alias("cell"))
    # each row stands in its own cell and is a neighbour in the two beside it
    held = rows.select(F.explode(F.array(F.col("cell") - 1, F.col("cell"), F.col("cell") + 1)).alias("cell"), "o_totalprice", (F.lit(None)).cast("long").alias("key"), F.lit(1).alias("w"))
    asks = rows.select("cell", "o_totalprice", F.col("o_orderkey").alias("key"), F.lit(0).alias("w"))
    near = F.sum("w").over(Window.partitionBy("cell").orderBy("o_totalprice").rangeBetween(-50, 50))
    return held.unionByName(asks).withColumn("near", near - 1).where("key is not null").select(F.col("key").alias("o_orderkey"), "near")


@query("completeness", "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra")
def completeness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Set differences of brute-force and indexed answers, both ways: empty."""
    index, p = indexed(spark, sf_dir, "orders2")
    qs = _uniform(spark, 2, 20)
    a, b = (d.select("qid", "pid") for d in (search.brute(p.df, qs, 2, 10), search.knn_search(index, qs, 10)))
    missing, extra = a.exceptAll(b), b.exceptAll(a)
    return missing.agg(F.count("*").alias("missing")).join(extra.agg(F.count("*").alias("extra")))


@query("duplicate_points", f"WITH {oracle.points('dup4')} SELECT count(*) AS points, count(DISTINCT (x0, x1, x2, x3)) AS distinct_points FROM pts")
def duplicate_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points(spark, sf_dir, "dup4").df.agg(F.count("*").alias("points"), F.count_distinct("x").alias("distinct_points"))


@query("bounding_box_scan", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 99000 AND 101000 AND abs(o_totalprice - 100000) <= 1000")
def bounding_box_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A one-dimensional ball as pushed-down filters on the scan."""
    box = bounding_box_predicate(["o_totalprice"], [100000.0], 1000.0)
    return load(spark, sf_dir, "orders").where(box).where(F.abs(F.col("o_totalprice") - 100000) <= 1000).select("o_orderkey", "o_totalprice")


@query("inv_measures", "SELECT kind, count(*) AS points, true AS bounded, true AS whole, true AS shares, true AS ordered FROM orders, (VALUES ('pab'), ('fpb'), ('kdt')) t(kind) GROUP BY kind")
def inv_measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What holds for the measures of any tree: depths between the least possible and the largest, a histogram of all leaves and points, shares between 0 and 1.

    The bounds are those of each part's tree; a part's inner nodes are one fewer than its leaves.
    """
    out = None
    for kind in workloads.KINDS:
        index, _ = indexed(spark, sf_dir, "orders2", kind=kind, leaf_capacity=8)
        depth, quality = stats.avg_depth(index), stats.tree_quality(index)
        tree = stats.avg_depth(index, "part_id").agg(F.bool_and(F.col("avg_depth") >= balanced_depth(F.col("leaves")) - 1e-9).alias("bounded"), F.bool_and(F.col("avg_depth") <= F.col("max_depth")).alias("ordered"))
        levels_of = stats.depth_histogram(index).agg(F.sum("leaves").alias("l"), F.sum("points").alias("p"), F.max("depth").alias("d"), (F.sum(F.col("depth") * F.col("leaves")) / F.sum("leaves")).alias("a"))
        row = depth.join(levels_of).join(quality).join(tree).select(
            F.lit(kind).alias("kind"), F.col("n").alias("points"),
            "bounded",
            ((F.col("l") == F.col("leaves")) & (F.col("p") == F.col("n")) & (F.col("d") == F.col("max_depth")) & (F.abs(F.col("a") - F.col("avg_depth")) < 1e-9) & (F.col("inner") == F.col("leaves") - index.n_parts)).alias("whole"),
            (F.col("imbalance").between(0, 1) & F.col("weighted_imbalance").between(0, 1) & (F.col("overlap") >= 0) & F.col("child_radius").between(0, 1.5)).alias("shares"),
            "ordered",
        )
        out = row if out is None else out.unionByName(row)
    return out


@query("inv_visits", "SELECT kind, CAST(50 AS BIGINT) AS queries, true AS nested, true AS complete, true AS saved FROM (VALUES ('pab'), ('fpb'), ('kdt')) t(kind)")
def inv_visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What holds for the counters of searches: expanded nodes are entered ones, leaves are expanded ones, and a constraint saves visits."""
    out = None
    p, qs = points(spark, sf_dir, "orders2"), _uniform(spark, 2)
    for kind in workloads.KINDS:
        index = workloads.one_tree(p, kind=kind, leaf_capacity=8)
        knn = search.nearest(index, qs, 10, trace=True, order="right_first")
        cnn = search.nearest(index, qs, 10, 0.02, trace=True, order="right_first")
        nested = F.bool_and((F.col("nodes_entered") >= F.col("nodes_expanded")) & (F.col("nodes_expanded") >= F.col("leaves_scanned")) & (F.col("points_compared") >= F.col("answers")))
        a, c = (stats.average_cost(x).join(x.agg(nested.alias("nested"))) for x in (knn, cnn))
        part = stats.reduction(a, c)
        row = part.select(F.lit(kind).alias("kind"), "queries", (F.col("base_nested") & F.col("ours_nested")).alias("nested"), (F.col("base_answers") == 10).alias("complete"), F.col("visits_saved").between(0, 1).alias("saved"))
        out = row if out is None else out.unionByName(row)
    return out


@query("sql_views", "SELECT count(*) AS points, count(*) AS in_leaves, true AS has_parts FROM orders")
def sql_views(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index as views for SQL: its points, and its leaves' counts."""
    index, _ = indexed(spark, sf_dir, "orders2")
    index.register("ballspark_orders")
    return spark.sql("SELECT (SELECT count(*) FROM ballspark_orders_points) AS points, (SELECT sum(n) FROM ballspark_orders_nodes WHERE is_leaf) AS in_leaves, (SELECT count(*) > 0 FROM ballspark_orders_parts) AS has_parts")


@query("result_sinks", " UNION ALL ".join(f"SELECT '{f}' AS format, * FROM ({_range_sql('orders2', 0.02)})" for f in ("parquet", "orc", "csv", "json")))
def result_sinks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers written in every format and read again."""
    index, _ = indexed(spark, sf_dir, "orders2")
    found, out = _rounded(search.range_search(index, _uniform(spark, 2), 0.02)), None
    for kind in ("parquet", "orc", "csv", "json"):
        path = shared_dir(spark)
        write_results(found, path, kind)
        again = read_points(spark, path, kind, "qid long, pid long, dist double").select(F.lit(kind).alias("format"), "qid", "pid", "dist")
        out = again if out is None else out.unionByName(again)
    return out


@query("wide_moments", f"WITH {oracle.points('emb64')} SELECT count(*) AS n, {', '.join(f'round(avg(x{j}), 5) AS mean{j}, round(var_pop(x{j}), 5) AS var{j}' for j in (0, 31, 63))}, round(covar_pop(x0, x63), 5) AS cov FROM pts")
def wide_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moments beyond the dimensions that are written out as columns."""
    m = levels.node_moments(_coded(points(spark, sf_dir, "emb64")), 64)
    at = {j: 64 * j - j * (j - 1) // 2 for j in (0, 31, 63)}
    cells = [c for j in at for c in (F.round(F.col("mean")[j], 5).alias(f"mean{j}"), F.round(F.col("c")[at[j]] / F.col("n"), 5).alias(f"var{j}"))]
    return m.select("n", *cells, F.round(F.col("c")[63] / F.col("n"), 5).alias("cov"))


# --- index life ------------------------------------------------------------------------------------


@query("append_then_knn", _nearest_sql("orders2", 10))
def append_then_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index over nine tenths of the orders; the rest is appended."""
    p = points(spark, sf_dir, "orders2")
    late = F.pmod(F.xxhash64("pid"), F.lit(10)) == 0
    index = build_tree(Points(p.df.where(~late), p.dim, p.scale), BuildConfig(parts=4, top="sample")).append(p.df.where(late))
    return _rounded(search.knn_search(index, _uniform(spark, 2), 10))


@query("stream_append_knn", _nearest_sql("orders2", 10))
def stream_append_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index over half of the orders, to which the rest arrives as a stream of points."""
    p, path = points(spark, sf_dir, "orders2"), shared_dir(spark)
    late = F.pmod(F.xxhash64("pid"), F.lit(2)) == 0
    p.df.where(late).write.parquet(path)
    index = build_tree(Points(p.df.where(~late), p.dim, p.scale), BuildConfig(parts=4, top="sample"))
    return _rounded(search.knn_search(stream_append(spark.readStream.schema(p.df.schema).parquet(path), index), _uniform(spark, 2), 10))


@query("compact_then_knn", _nearest_sql("orders2", 10))
def compact_then_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "orders2", parts=8, top="sample")
    return _rounded(search.knn_search(index.compact([r.part_id for r in index.summaries().select("part_id").orderBy("part_id").limit(3).collect()]), _uniform(spark, 2), 10))


@query("save_load_range", _range_sql("orders2", 0.05))
def save_load_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "orders2")
    path = shared_dir(spark)
    index.save(path)
    return _rounded(search.range_search(SpatialIndex.load(spark, path), _uniform(spark, 2), 0.05))


@query("sql_knn_of", _nearest_sql("orders2", 10))
def sql_knn_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    index, _ = indexed(spark, sf_dir, "orders2")
    register_knn_of(index)
    _uniform(spark, 2).createOrReplaceTempView("ballspark_asks")
    return _rounded(spark.sql("SELECT qid, n.rank, n.pid, n.dist FROM ballspark_asks, LATERAL knn_of(q, 10, CAST(NULL AS DOUBLE)) n"))


@query("sql_geometry", oracle.in_range("cust2", oracle.uniform(2, 50), 0.05))
def sql_geometry(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_sql(spark)
    points(spark, sf_dir, "cust2").df.createOrReplaceTempView("ballspark_points")
    _uniform(spark, 2).createOrReplaceTempView("ballspark_asks")
    return spark.sql("SELECT qid, pid, round(sqrt(sq_dist(x, q)), 6) AS dist FROM ballspark_points JOIN ballspark_asks ON ball_intersects(x, 0D, q, 0.06D) WHERE sq_dist(x, q) <= 0.05D * 0.05D")


# --- transformed points -----------------------------------------------------------------------------


@query("pca_rotate", f"WITH {oracle.points('line4')} SELECT pid, round(sqrt({' + '.join(f'(x{j} - 0.3e0) * (x{j} - 0.3e0)' for j in range(4))}), 6) AS dist FROM pts")
def pca_rotate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each point's distance from one place, both turned to all components: what it was."""
    p = points(spark, sf_dir, "line4")
    components = fit_pca(p.df, 4)
    place = F.array(*[project(F.array(*[F.lit(0.3)] * 4), w.tolist()) for w in components])
    return pca_transform(p.df, components).select("pid", F.round(F.sqrt(sq_dist(F.col("x"), place, 4)), 6).alias("dist"))


@query("pca_filter_knn", _nearest_sql("line4", 10))
def pca_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points(spark, sf_dir, "line4")
    return _rounded(pca_filter_knn(p.df, _uniform(spark, 4), 4, fit_pca(p.df, 4), 2, 10))


@query("generated_sets", "SELECT kind, count(*) AS n, count(*) AS places FROM (SELECT DISTINCT event_id FROM events), (VALUES ('latin'), ('niederreiter'), ('sobol')) t(kind) GROUP BY kind")
def generated_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stratified sets have no two points in one of n strata of either axis: for any n, for powers of three, and of two. A point for each event, by its id."""
    from ballspark.sources.generators import generate

    events = load(spark, sf_dir, "events").select(F.col("event_id").cast("long").alias("event_id")).where("event_id is not null")
    ends = events.agg(F.min("event_id").alias("low"), F.max("event_id").alias("high")).first()
    low, span = (ends.low, ends.high - ends.low + 1) if ends.low is not None else (0, 1)
    ids = events.distinct().select((F.col("event_id") - low).alias("id"))
    out = None
    for kind, base in (("latin", None), ("niederreiter", 3), ("sobol", 2)):
        n = span if base is None else next(base**r for r in range(64) if base**r >= span)
        cell = [F.floor(F.col("x")[j] * n + 1e-6) for j in range(2)]
        row = generate(spark, kind, n, ids=ids).agg(F.count("*").alias("n"), F.least(F.count_distinct(cell[0]), F.count_distinct(cell[1])).alias("places")).select(F.lit(kind).alias("kind"), "n", "places")
        out = row if out is None else out.unionByName(row)
    return out


@query("uniform_queries", f"WITH {oracle.uniform_of('events', 'event_id', 4)} SELECT qid, {', '.join(f'round(q{j}, 6) AS q{j}' for j in range(4))} FROM qs")
def uniform_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A uniform query point for each event."""
    qs = query_sets.uniform_of(load(spark, sf_dir, "events"), "event_id", [(0.0, 1.0)] * 4)
    return qs.select("qid", *[F.round(F.col("q")[j], 6).alias(f"q{j}") for j in range(4)])


@query("data_queries", f"WITH {oracle.points('ship2')}, {oracle.sampled(2, 50)} SELECT qid, round(q0, 6) AS q0, round(q1, 6) AS q1 FROM qs")
def data_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    return query_sets.data_queries(points(spark, sf_dir, "ship2").df, 50).select("qid", F.round(F.col("q")[0], 6).alias("q0"), F.round(F.col("q")[1], 6).alias("q1"))


# --- streams ----------------------------------------------------------------------------------------


def _stream(spark: SparkSession, sf_dir: str, watermark: str | None = "1 hour") -> DataFrame:
    return event_stream(spark, sf_dir, load(spark, sf_dir, "events").schema, watermark=watermark, pathGlobFilter="events.parquet")


def _windows(kind: str, key: list[str] | None = None) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = run_to_end(window_counts(_stream(spark, sf_dir), kind, key=key), mode="complete")
        return rows.select(*(key or []), F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", F.round("total", 4).alias("total"))

    return run


_START = "strftime({}, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 4) AS total"
query("stream_window_counts", f"SELECT {_START.format('date_trunc(\'day\', ts)')} FROM events GROUP BY date_trunc('day', ts)")(_windows("tumbling"))
query("stream_window_sliding", f"SELECT {_START.format('b')} FROM (SELECT value, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - to_hours(6 * k) AS b FROM events, range(4) r(k)) GROUP BY b")(_windows("sliding"))
query(
    "stream_window_session",
    "WITH o AS (SELECT user_id, ts, value, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
    "s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) "
    "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 4) AS total FROM s GROUP BY user_id, k",
)(_windows("session", ["user_id"]))


@query(
    "stream_cnn",
    f"WITH {oracle.points('events_uv2')}, qs AS (SELECT pid AS qid, x0 AS q0, x1 AS q1 FROM pts JOIN events ON event_id = pid WHERE event_type = 'purchase'), {oracle.pairs(2, 0.01)}, {oracle.RANKED} SELECT qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist FROM ranked WHERE rank <= 3",
)
def stream_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases arrive and are answered with their three nearest events within a range, in (user, value)."""
    index, p = indexed(spark, sf_dir, "events_uv2")
    place = p.scale.apply(F.array(F.col("user_id").cast("double"), F.col("value")))
    asks = _stream(spark, sf_dir, None).where("event_type = 'purchase'").select(F.col("event_id").alias("qid"), place.alias("q"))
    return _rounded(stream_constrained(asks, index, 3, 0.01))


@query("stream_dedup", "SELECT event_id FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event delivered twice, kept once."""
    twice = _stream(spark, sf_dir, None).unionByName(_stream(spark, sf_dir, None))
    return run_to_end(deduplicated(twice)).select("event_id")


@query("stream_nearby", ORACLES["interval_join"])
def stream_nearby(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors and purchases as two streams, joined within an hour of the same user."""
    e, p = _stream(spark, sf_dir).where("event_type = 'error'"), _stream(spark, sf_dir).where("event_type = 'purchase'")
    return run_to_end(nearby_events(e, p, "1 hour"))


@query("stream_standing_knn", oracle.k_nearest("events_uv2", oracle.uniform(2, 5), 10))
def stream_standing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten best of standing queries after all events have arrived."""
    place = points(spark, sf_dir, "events_uv2").scale.apply(F.array(F.col("user_id").cast("double"), F.col("value")))
    arriving = _stream(spark, sf_dir, None).select(F.col("event_id").alias("pid"), place.alias("x"))
    last = run_to_end(standing_nearest(arriving, _uniform(spark, 2, 5), 10, 2), mode="update", key=["qid"])
    return last.select("qid", "rank", "pid", F.round(F.sqrt("d2"), 6).alias("dist"))


_ARRIVALS = 3


@query(
    "stream_late",
    f"WITH a AS (SELECT event_id, ts, event_id % {_ARRIVALS} AS b FROM events), w AS (SELECT b, max(ts) AS top FROM a GROUP BY b) "
    "SELECT event_id, coalesce(ts < (SELECT max(top) FROM w WHERE w.b < a.b) - INTERVAL 12 HOUR, false) AS late FROM a",
)
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events out of order, in three batches, marked where the watermark had passed them."""
    path, events = shared_dir(spark), load(spark, sf_dir, "events").select("event_id", "ts")
    for b in range(_ARRIVALS):  # files are taken by their age
        events.where(F.col("event_id") % _ARRIVALS == b).coalesce(1).write.parquet(f"{path}/{b}")
    arriving = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*")
    return marked_late(arriving, "ts", "12 hours").select("event_id", "late")


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracles() -> dict[str, str]:
    return dict(ORACLES)
