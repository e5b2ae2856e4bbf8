"""Geometry as column expressions, all inside code generation.

Vectors are arrays. Where the dimension is known sums are written out dimension by dimension, left
to right, the order in which kernels and oracles add, so that all give the same doubles.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _terms(a: Column, b: Column, dim: int | None, term, zero: float = 0.0) -> Column:
    if dim:
        return reduce(lambda s, t: s + t, [term(a[j], b[j]) for j in range(dim)])
    return F.aggregate(F.zip_with(a, b, term), F.lit(zero), lambda s, t: s + t)


def sq_dist(a: Column, b: Column, dim: int | None = None) -> Column:
    return _terms(a, b, dim, lambda u, v: (u - v) * (u - v))


def dist(a: Column, b: Column, dim: int | None = None) -> Column:
    return F.sqrt(sq_dist(a, b, dim))


def dot(a: Column, b: Column, dim: int | None = None) -> Column:
    return _terms(a, b, dim, lambda u, v: u * v)


def project(x: Column, w: list[float]) -> Column:
    """Scalar place of a point along a known axis."""
    return reduce(lambda s, t: s + t, [x[j] * F.lit(float(v)) for j, v in enumerate(w)])


def side_of(x: Column, w: list[float], cut: float) -> Column:
    return F.when(project(x, w) < F.lit(cut), "lo").otherwise("hi")


def ball_min_dist(center: Column, radius: Column, q: Column, dim: int | None = None) -> Column:
    return F.greatest(F.lit(0.0), dist(center, q, dim) - radius)


def ball_max_dist(center: Column, radius: Column, q: Column, dim: int | None = None) -> Column:
    return dist(center, q, dim) + radius


def ball_intersects(center: Column, radius: Column, q: Column, r: Column, dim: int | None = None) -> Column:
    """Whether the closed balls meet."""
    return dist(center, q, dim) <= radius + r


def ball_inside(center: Column, radius: Column, q: Column, r: Column, dim: int | None = None) -> Column:
    """Whether the first ball lies in the query ball."""
    return dist(center, q, dim) + radius <= r


def in_ball(x: Column, center: Column, radius: Column, dim: int | None = None) -> Column:
    return sq_dist(x, center, dim) <= radius * radius


def box_min_dist(low: Column, high: Column, q: Column, dim: int) -> Column:
    """From a rectangle to a point: 0 inside it."""
    out = [F.greatest(F.lit(0.0), low[j] - q[j], q[j] - high[j]) for j in range(dim)]
    return F.sqrt(reduce(lambda s, t: s + t, [g * g for g in out]))


def bounding_box_predicate(columns: list[str], q: list[float], r: float) -> Column:
    """Conjuncts on flat columns that every point within r fulfils; they reach a Parquet scan's row groups."""
    return reduce(lambda s, t: s & t, [F.col(c).between(v - r, v + r) for c, v in zip(columns, q)])


#: Geometry for SQL texts, as functions that Catalyst inlines.
SQL_FUNCTIONS = {
    "sq_dist": "(a array<double>, b array<double>) RETURNS double RETURN aggregate(zip_with(a, b, (u, v) -> (u - v) * (u - v)), 0D, (s, t) -> s + t)",
    "vec_dist": "(a array<double>, b array<double>) RETURNS double RETURN sqrt(aggregate(zip_with(a, b, (u, v) -> (u - v) * (u - v)), 0D, (s, t) -> s + t))",
    "dot": "(a array<double>, b array<double>) RETURNS double RETURN aggregate(zip_with(a, b, (u, v) -> u * v), 0D, (s, t) -> s + t)",
    "ball_intersects": "(c array<double>, radius double, q array<double>, r double) RETURNS boolean RETURN sqrt(aggregate(zip_with(c, q, (u, v) -> (u - v) * (u - v)), 0D, (s, t) -> s + t)) <= radius + r",
}


def register_sql(spark: SparkSession) -> None:
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
