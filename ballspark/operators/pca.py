"""Principal components of all points: rotation, and a projected filter for nearest neighbours."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ballspark.functions.geometry import project

from .levels import node_moments


def fit_pca(points: DataFrame, dim: int) -> np.ndarray:
    """All components, one a row, by falling variance, each with its largest component positive.

    d (d + 1) / 2 sums reach the driver, no points.
    """
    row = node_moments(points.withColumn("code", F.lit(1).cast("long")), dim).first()
    m = np.zeros((dim, dim))
    i, j = np.triu_indices(dim)
    m[i, j] = m[j, i] = row.c
    w = np.linalg.eigh(m)[1].T[::-1]
    return np.array([v * (1 if v[np.argmax(np.abs(v))] > 0 else -1) for v in w])


def pca_transform(points: DataFrame, components: np.ndarray, k: int | None = None) -> DataFrame:
    """(pid, x) in the first k components; all of them keep every distance."""
    rows = components[: k or len(components)]
    return points.withColumn("x", F.array(*[project(F.col("x"), w.tolist()) for w in rows]))


def pca_filter_knn(points: DataFrame, queries: DataFrame, dim: int, components: np.ndarray, k_components: int, k: int) -> DataFrame:
    """The k nearest by a filter in few components, verified on the original points.

    A projected distance never exceeds the true one. The k nearest by projection give true distances;
    the largest of them bounds the projected distance of any answer, and what lies within it is verified.
    """
    rows, found = components[:k_components], queries.select("qid", "q").collect()
    held = queries.sparkSession.sparkContext.broadcast(([r.qid for r in found], np.array([r.q for r in found], float).reshape(len(found), dim)))
    low, true = _differences(rows), _differences(np.eye(dim))
    first = _least(points, held, dim, k, "low double, pid long, d2 double", low, true)
    first = first.withColumn("i", F.row_number().over(Window.partitionBy("qid").orderBy("low", "pid"))).where(F.col("i") <= k)
    limits = {r.qid: r.bound for r in first.groupBy("qid").agg((F.max("d2") * (1 + 1e-9)).alias("bound")).collect()}
    kept = _least(points, held, dim, k, "d2 double, pid long, low double", true, low, limits)
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("d2", "pid"))
    return kept.withColumn("rank", rank).where(F.col("rank") <= k).select("qid", "rank", "pid", F.sqrt("d2").alias("dist"))


#: Points that are compared with a query at once.
PORTION = 1 << 16


def _differences(axes: np.ndarray):
    """Squared distances of points from a place, along the axes, summed from the first to the last."""

    def along(x: np.ndarray, w: np.ndarray) -> np.ndarray:
        return sum(x[..., j] * w[j] for j in range(len(w)) if w[j])

    def squares(x: np.ndarray, q: np.ndarray) -> np.ndarray:
        return sum(((along(x, w) - along(q, w)) ** 2 for w in axes), np.zeros(len(x)))

    return squares


def _least(points: DataFrame, held, dim: int, k: int, schema: str, by, other, limits: dict | None = None) -> DataFrame:
    """(qid, by, pid, other): of each task's points the k first of each query by (``by``, pid); with ``limits`` of those whose ``other`` is within the query's.

    So what leaves a task grows with the queries, not with the points.
    """
    names = ["qid", *(c.split()[0] for c in schema.split(", "))]

    def first(by: np.ndarray, pid: np.ndarray, other: np.ndarray) -> tuple[np.ndarray, ...]:
        if len(by) > k:  # all that are no farther than the k-th, of which the smallest pids
            near = by <= np.partition(by, k - 1)[k - 1]
            by, pid, other = by[near], pid[near], other[near]
        order = np.lexsort((pid, by))[:k]
        return by[order], pid[order], other[order]

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, places = held.value
        best = [(np.empty(0), np.empty(0, np.int64), np.empty(0))] * len(qids)
        for batch in batches:
            pids, xs = batch.column("pid").to_numpy(), batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
            for a in range(0, len(pids), PORTION):
                pid, x = pids[a : a + PORTION], np.asfortranarray(xs[a : a + PORTION])
                for i, q in enumerate(places):
                    near, far = by(x, q), None
                    inside = np.ones(len(x), bool) if limits is None else (far := other(x, q)) <= limits.get(qids[i], -1.0)
                    if len(best[i][0]) == k:
                        inside &= near <= best[i][0][-1]
                    at = np.nonzero(inside)[0]
                    if len(at):
                        far = other(x[at], q) if far is None else far[at]
                        best[i] = first(*(np.concatenate(both) for both in zip(best[i], (near[at], pid[at], far))))
        whose = np.repeat(np.array(qids, np.int64), [len(b[0]) for b in best])
        columns = [np.concatenate([b[j] for b in best]) if best else np.empty(0, kind) for j, kind in enumerate((np.float64, np.int64, np.float64))]
        yield pa.RecordBatch.from_arrays([pa.array(whose), *map(pa.array, columns)], names=names)

    return points.select("pid", "x").mapInArrow(pick, f"qid long, {schema}")


def balanced_depth(n: Column) -> Column:
    """``balanced_bound`` of a column."""
    h = F.floor(F.log2(n))
    return h + 2 - F.pow(F.lit(2.0), h + 1) / n


def balanced_bound(n: int) -> float:
    """The least possible mean depth of the leaves of a binary tree with n of them."""
    if n < 1:
        return 0.0
    h = int(math.floor(math.log2(n)))
    return h + 2 - 2 ** (h + 1) / n
