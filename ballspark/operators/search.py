"""Searches over an index: routed, relational (frontier), flat, and brute force.

A routed search sends each query to the parts it can meet, found on the parts' balls or boxes alone,
and searches there all queries of a part together. The queries of a part travel to its tree in groups of a bounded
size, however many there are: in a broadcast where they are counted to be few, else by a join on the part,
which Spark can split. Nearest-neighbour searches take two rounds, first a home part, whose answers bound the second.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ballspark.functions.geometry import ball_intersects, box_min_dist, sq_dist

from .index import SpatialIndex, saved
from .kernel import SLACK, Trace, Tree, count_kernel, nearest_kernel, nearest_together, nearest_traces, nearest_traces_of_parts, range_together, range_traces, range_traces_of_parts
from .routing import matrix

#: Routed queries of two dimensions that are broadcast to the trees at most, fewer of more; queries of a group that meets a tree, on average.
BROADCAST_QUERIES, CHUNK = 200_000, 8192
FOUND = "qid long, pid long, d2 double"
#: Arrays of a tree that searches read.
SEARCHED = ("x", "pid", "lo", "hi", "begin", "end", "depth", "center", "radius", "box_lo", "box_hi")
COUNTERS = ("nodes_entered", "nodes_expanded", "leaves_scanned", "points_compared")
TRACE = ", ".join(f"{c} long" for c in COUNTERS)

#: What a search does at a tree: (tree, vectors, the queries' qid, k and r) to columns of answers.
Work = Callable[[Tree, np.ndarray, pd.DataFrame], Iterator[pd.DataFrame]]


def one_by_one(each: Callable[[Tree, dict], Iterator[tuple]], schema: str) -> Work:
    """Work that searches query after query, where counters or the variants of a procedure are asked for."""
    names = [c.strip().split(" ")[0] for c in schema.split(",")]

    def work(tree: Tree, q: np.ndarray, rows: pd.DataFrame) -> Iterator[pd.DataFrame]:
        asked = zip(rows["qid"], rows["k"], rows["r"], q.tolist())
        yield pd.DataFrame([row for qid, k, r, v in asked for row in each(tree, {"qid": qid, "q": v, "k": k, "r": r})], columns=names)

    return work


def _limits(rows: pd.DataFrame) -> np.ndarray:
    return rows["r"].astype(float).fillna(math.inf).to_numpy()


def _at_parts(index: SpatialIndex, routed: DataFrame, work: Work, schema: str) -> DataFrame:
    """``work`` for the routed queries (part_id, qid, q, k, r) at their parts' trees."""
    routed = saved(routed.select("part_id", "qid", "q", "k", "r"))
    counts = routed.groupBy("part_id").agg(F.ceil(F.count("*") / CHUNK).alias("chunks"))
    few = routed.count() * (index.dim + 3) <= 5 * BROADCAST_QUERIES
    counts = F.broadcast(counts) if few else counts
    chunk = F.pmod(F.xxhash64("qid"), F.col("chunks"))
    groups = routed.join(counts, "part_id").groupBy("part_id", chunk.alias("chunk")).agg(F.collect_list(F.struct("qid", "q", "k", "r")).alias("todo"))
    joined = index.parts.select("part_id", "tree").join(F.broadcast(groups) if few else groups, "part_id")

    answers = to_arrow_schema(T.StructType.fromDDL(schema))

    def mapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, t = None, None
        for batch in batches:
            todo = batch.column("todo")
            for i in range(len(batch)):
                tree, asked = batch.column("tree")[i].as_py(), todo[i].values  # arrays of the group, never objects
                if tree != held:  # the groups of a part mostly follow one another
                    held, t = tree, Tree.from_bytes(tree, SEARCHED)
                fields = dict(zip((f.name for f in asked.type), asked.flatten()))
                rows = pd.DataFrame({n: fields[n].to_pandas() for n in ("qid", "k", "r")})
                for found in work(t, fields["q"].flatten().to_numpy(zero_copy_only=False).reshape(len(rows), -1), rows):
                    yield pa.RecordBatch.from_pandas(found[answers.names], answers, preserve_index=False)

    return joined.select("tree", "todo").mapInArrow(mapped, schema)


def _single(index: SpatialIndex, queries: DataFrame, work: Work, schema: str) -> DataFrame:
    """Queries against an index of one part: its tree, at most ``local_rows`` points, is broadcast to the queries."""
    tree = index.spark.sparkContext.broadcast(index.parts.select("tree").first().tree)

    def mapped(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        t = Tree.from_bytes(tree.value, SEARCHED)
        for batch in batches:
            if len(batch):
                yield from work(t, matrix(batch["q"]), batch)

    return queries.select("qid", "q", "k", "r").mapInPandas(mapped, schema)


def _of_parts(queries: DataFrame, counted: Callable[[np.ndarray, pd.DataFrame], np.ndarray]) -> DataFrame:
    """Counters by query over one tree of several parts, which each task reads one after another."""

    def mapped(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = [batch for batch in batches if len(batch)]
        if held:
            rows = pd.concat(held, ignore_index=True)  # the queries of a task together, so that parts are read seldom
            yield pd.DataFrame({"qid": rows["qid"].to_numpy()} | dict(zip(("answers", *COUNTERS), counted(matrix(rows["q"]), rows).T)))

    return queries.select("qid", "q", "k", "r").mapInPandas(mapped, f"qid long, answers long, {TRACE}")


def _run(index: SpatialIndex, queries: DataFrame, radius: str, work: Work, schema: str) -> DataFrame:
    if index.n_parts == 1:
        return _single(index, queries, work, schema)
    return _at_parts(index, index.routing().meets(queries, "q", radius), work, schema)


def _prepared(queries: DataFrame, k: int | None, r: float | None) -> DataFrame:
    """(qid, q, k, r) with the arguments in place of the columns where they are given; r < 0 or k < 1 is an error."""
    if (k is not None and k < 1) or (r is not None and not r >= 0):
        raise ValueError("k is at least 1 and r at least 0")
    have = dict(queries.dtypes)
    return queries.select("qid", "q", (F.lit(k) if k is not None else F.col("k") if "k" in have else F.lit(None)).cast("int").alias("k"), (F.lit(r) if r is not None else F.col("r") if "r" in have else F.lit(None)).cast("double").alias("r"))


def _limit(row) -> float:
    r = row["r"]
    return math.inf if r is None or r != r else r


def _counters(t: Trace) -> tuple:
    return t.nodes_entered, t.nodes_expanded, t.leaves_scanned, t.points_compared


def range_search(index: SpatialIndex, queries: DataFrame, r: float | None = None, engine: str = "routed", trace: bool = False) -> DataFrame:
    """(qid, pid, dist) of all points within r of each query, the border included; with ``trace`` the counters by query."""
    queries = index.turned(_prepared(queries, None, r))
    if not index.n_parts:
        return index.spark.createDataFrame([], "qid long, pid long, dist double")
    if engine == "frontier":
        found = frontier_range(index, queries)
    elif engine == "flat":
        found = flat_range(index, queries)
    elif trace and index.top and index.n_parts > 1:
        top = index.top
        return _of_parts(queries, lambda q, rows: range_traces_of_parts(top, q, _limits(rows)))
    elif trace:
        return _run(index, queries, "r", _range_trace, f"qid long, answers long, {TRACE}").groupBy("qid").agg(F.sum("answers").alias("answers"), *[F.sum(c).alias(c) for c in COUNTERS])
    else:
        found = _run(index, queries, "r", _range_work, FOUND)
    return found.select("qid", "pid", F.sqrt("d2").alias("dist"))


def _range_work(tree: Tree, q: np.ndarray, rows: pd.DataFrame) -> Iterator[pd.DataFrame]:
    for of, pid, d2 in range_together(tree, q, _limits(rows)):
        yield pd.DataFrame({"qid": rows["qid"].to_numpy()[of], "pid": pid, "d2": d2})


def _range_trace(tree: Tree, q: np.ndarray, rows: pd.DataFrame) -> Iterator[pd.DataFrame]:
    counted = range_traces(tree, q, _limits(rows))
    yield pd.DataFrame({"qid": rows["qid"].to_numpy()} | dict(zip(("answers", *COUNTERS), counted.T)))


def range_count(index: SpatialIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """(qid, n): how many points are within r; nodes wholly inside are counted without being entered."""

    def work(tree: Tree, row) -> Iterator[tuple]:
        yield row["qid"], count_kernel(tree, list(row["q"]), _limit(row), Trace())

    queries = index.turned(_prepared(queries, None, r))
    counted = _run(index, queries, "r", one_by_one(work, "qid long, c long"), "qid long, c long") if index.n_parts else index.spark.createDataFrame([], "qid long, c long")
    return queries.join(counted.groupBy("qid").agg(F.sum("c").alias("n")), "qid", "left").select("qid", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def range_exists(index: SpatialIndex, queries: DataFrame, r: float | None = None) -> DataFrame:
    """(qid, found): whether any point is within r; a part stops at its first."""

    def work(tree: Tree, row) -> Iterator[tuple]:
        yield row["qid"], count_kernel(tree, list(row["q"]), _limit(row), Trace(), first_only=True) > 0

    queries = index.turned(_prepared(queries, None, r))
    seen = _run(index, queries, "r", one_by_one(work, "qid long, f boolean"), "qid long, f boolean") if index.n_parts else index.spark.createDataFrame([], "qid long, f boolean")
    return queries.join(seen.groupBy("qid").agg(F.bool_or("f").alias("f")), "qid", "left").select("qid", F.coalesce("f", F.lit(False)).alias("found"))


def _nearest_work(options: dict, counters: bool = False) -> tuple[Work, str]:
    """Work and its schema. Answers don't depend on ``options``, which are the procedure's: with some, or for counters, it runs for each query."""
    if not options and not counters:

        def together(tree: Tree, q: np.ndarray, rows: pd.DataFrame) -> Iterator[pd.DataFrame]:
            of, pid, d2 = nearest_together(tree, q, rows["k"].to_numpy(np.int64), _limits(rows))
            yield pd.DataFrame({"qid": rows["qid"].to_numpy()[of], "pid": pid, "d2": d2})

        return together, FOUND
    if counters and set(options) <= {"order"} and options.get("order") != "best_first":

        def traced(tree: Tree, q: np.ndarray, rows: pd.DataFrame) -> Iterator[pd.DataFrame]:
            counted = nearest_traces(tree, q, rows["k"].to_numpy(np.int64), _limits(rows), **options)
            yield pd.DataFrame({"qid": rows["qid"].to_numpy()} | dict(zip(("answers", *COUNTERS), counted.T)))

        return traced, f"qid long, answers long, {TRACE}"

    def each(tree: Tree, row: dict) -> Iterator[tuple]:
        t = Trace()
        found = nearest_kernel(tree, row["q"], int(row["k"]), _limit(row), t, **options)
        if counters:
            yield row["qid"], len(found), *_counters(t)
        else:
            for d2, pid in found:
                yield row["qid"], pid, d2

    schema = f"qid long, answers long, {TRACE}" if counters else FOUND
    return one_by_one(each, schema), schema


def ranked(found: DataFrame, queries: DataFrame | None = None) -> DataFrame:
    """(qid, rank, pid, dist): the k first of each query by (distance, pid). ``found`` has qid, pid, d2 and k."""
    place = F.row_number().over(Window.partitionBy("qid").orderBy("d2", "pid"))
    return found.withColumn("rank", place).where(F.col("rank") <= F.col("k")).select("qid", "rank", "pid", F.sqrt("d2").alias("dist"))


def nearest(index: SpatialIndex, queries: DataFrame, k: int | None = None, r: float | None = None, trace: bool = False, bound: str = "data", **options) -> DataFrame:
    """(qid, rank, pid, dist) of the k nearest points, within r if given; k and r may also be columns of the queries.

    Over several parts the first round searches each query's home part; its k-th distance (with
    bound='metadata' already that which the parts' counts guarantee) and r bound what the second
    round visits. With ``trace`` the counters by query, over a single tree only, where they mean what
    the measures mean.
    """
    queries = index.turned(_prepared(queries, k, r))
    if not index.n_parts:
        return index.spark.createDataFrame([], "qid long, rank int, pid long, dist double")
    if trace:
        if index.n_parts > 1:
            if not index.top or not set(options) <= {"order"} or options.get("order") == "best_first":
                raise ValueError("counters are those of a single tree")
            top = index.top
            return _of_parts(queries, lambda q, rows: nearest_traces_of_parts(top, q, rows["k"].to_numpy(np.int64), _limits(rows), **options))
        return _single(index, queries, *_nearest_work(options, True))
    if index.n_parts == 1:
        found = _single(index, queries, *_nearest_work(options))
        return ranked(found.join(queries.select("qid", "k"), "qid"))
    return _two_rounds(index, queries, bound, options)


def _two_rounds(index: SpatialIndex, queries: DataFrame, bound: str, options: dict) -> DataFrame:
    routing = index.routing()
    most = F.col("most") if bound == "metadata" else F.lit(math.inf)
    asked = routing.bounded(queries) if bound == "metadata" else queries
    at_home = routing.home(asked.select("qid", "q", "k", F.least(F.coalesce("r", F.lit(math.inf)), most).alias("r")), "q")
    at_home = saved(at_home.withColumn("home", F.col("part_id")))
    work, schema = _nearest_work(options)
    first = saved(_at_parts(index, at_home, work, schema))
    worst = first.groupBy("qid").agg(F.count("*").alias("c"), F.max("d2").alias("d2"))
    left = at_home.drop("part_id").join(worst, "qid", "left")
    full = F.col("c") >= F.col("k")
    left = left.withColumn("r", F.when(full, F.least("r", F.sqrt("d2") * (1 + SLACK))).otherwise(F.col("r"))).select("qid", "q", "k", "r", "home")
    others = routing.meets(left, "q", "r").where(F.col("part_id") != F.col("home"))
    second = _at_parts(index, others, work, schema)
    return ranked(first.unionByName(second).join(queries.select("qid", "k"), "qid"))


def knn_search(index: SpatialIndex, queries: DataFrame, k: int | None = None, **options) -> DataFrame:
    """The k nearest, at any distance."""
    return nearest(index, queries.drop("r"), k, **options)


def constrained_knn(index: SpatialIndex, queries: DataFrame, k: int | None = None, r: float | None = None, **options) -> DataFrame:
    """The k nearest among the points within r, pruned by both."""
    return nearest(index, queries, k, r, **options)


def knn_then_range(index: SpatialIndex, queries: DataFrame, k: int, r: float) -> DataFrame:
    """Baseline: the k nearest, of which those beyond r are dropped."""
    return knn_search(index, queries, k).where(F.col("dist") <= r)


def range_then_topk(index: SpatialIndex, queries: DataFrame, k: int, r: float) -> DataFrame:
    """Baseline: all within r, of which the k nearest."""
    queries = index.turned(_prepared(queries, k, r))
    found = _run(index, queries, "r", _range_work, FOUND) if index.n_parts else index.spark.createDataFrame([], FOUND)
    return ranked(found.withColumn("k", F.lit(k)))


# --- relational engines: the same answers as plans without Python ------------------------------------


def _node_gap(index: SpatialIndex, q: Column) -> Column:
    if index.config.kind == "kdt":
        return box_min_dist(F.col("box_lo"), F.col("box_hi"), q, index.dim) <= F.col("r")
    return ball_intersects(F.col("center"), F.col("radius"), q, F.col("r"), index.dim)


def frontier_range(index: SpatialIndex, queries: DataFrame) -> DataFrame:
    """(qid, pid, d2) by joins: one level of the tree a step, the (query, node) pairs still open being the frontier."""
    nodes = saved(index.nodes().select("part_id", "node_id", "lo_id", "hi_id", "is_leaf", "center", "radius", "box_lo", "box_hi"))
    points = saved(index.leaf_points())
    queries = queries.select("qid", "q", "r")
    test = _node_gap(index, F.col("q"))
    roots = index.routing().meets(queries, "q", "r").join(nodes.where("node_id = 0"), "part_id")
    frontier = roots.where(test).select("qid", "q", "r", "part_id", "node_id", "lo_id", "hi_id", "is_leaf")
    leaves = None
    while True:
        frontier = saved(frontier)
        done = frontier.where("is_leaf").select("qid", "q", "r", "part_id", F.col("node_id").alias("leaf_id"))
        leaves = done if leaves is None else leaves.unionByName(done)
        inner = frontier.where("not is_leaf")
        if inner.isEmpty():
            break
        kids = inner.select("qid", "q", "r", "part_id", F.explode(F.array("lo_id", "hi_id")).alias("node_id"))
        frontier = kids.join(nodes, ["part_id", "node_id"]).where(test).select("qid", "q", "r", "part_id", "node_id", "lo_id", "hi_id", "is_leaf")
    d2 = sq_dist(F.col("x"), F.col("q"), index.dim)
    return leaves.join(points, ["part_id", "leaf_id"]).withColumn("d2", d2).where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "pid", "d2")


def flat_range(index: SpatialIndex, queries: DataFrame) -> DataFrame:
    """(qid, pid, d2) from all leaf balls against all queries: what the hierarchy saves is the ablation's point."""
    leaves = index.nodes().where("is_leaf").select("part_id", F.col("node_id").alias("leaf_id"), "center", "radius", "box_lo", "box_hi")
    met = leaves.join(F.broadcast(queries.select("qid", "q", "r")), _node_gap(index, F.col("q"))).select("part_id", "leaf_id", "qid", "q", "r")
    d2 = sq_dist(F.col("x"), F.col("q"), index.dim)
    return met.join(index.leaf_points(), ["part_id", "leaf_id"]).withColumn("d2", d2).where(F.col("d2") <= F.col("r") * F.col("r")).select("qid", "pid", "d2")


# --- brute force --------------------------------------------------------------------------------------


def brute(points: DataFrame, queries: DataFrame, dim: int, k: int | None = None, r: float | None = None) -> DataFrame:
    """(qid, rank, pid, dist) from all pairs of points and queries; the oracle that exactness is measured against.

    The k first of each task's points are kept before anything is shuffled.
    """
    queries = _prepared(queries, k, r)
    d2 = sq_dist(F.col("x"), F.col("q"), dim)
    pairs = points.join(F.broadcast(queries)).withColumn("d2", d2).where(F.col("r").isNull() | (F.col("d2") <= F.col("r") * F.col("r"))).select("qid", "pid", "d2", F.coalesce("k", F.lit(2**31 - 1)).alias("k"))
    return ranked(pairs)


def attach(result: DataFrame, source: DataFrame, key: Column | str, columns: list[str]) -> DataFrame:
    """Answers with columns of the table that the points came from."""
    key = F.col(key) if isinstance(key, str) else key
    return result.join(source.select(key.cast("long").alias("pid"), *columns), "pid")
