"""Query sets, drawn by integer arithmetic so that any engine makes the same."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .views import hash_cut

MODULUS, FIRST = 2147483647, 1000003
#: Ids beyond are drawn again: squares of larger ones don't fit 64 bits.
WRAP = 8_000_009
# Fixed values: (a, b, c) of each dimension's quadratic; dimensions beyond take them in turn, c raised by 7919 a dimension.
QUADRATICS = [(48271, 69621, 12345), (16807, 39373, 67890), (40014, 40692, 24680), (53668, 52774, 13579)]


def quadratic(j: int) -> tuple[int, int, int]:
    a, b, c = QUADRATICS[j % 4]
    return a, b, c + (7919 * j if j > 3 else 0)


def _with(queries: DataFrame, k: int | None, r: float | None) -> DataFrame:
    return queries.withColumns({"k": F.lit(k).cast("int"), "r": F.lit(r).cast("double")})


def _draw(qid: Column, j: int, low: float, high: float) -> Column:
    a, b, c = quadratic(j)
    s = qid + FIRST
    return F.lit(low) + F.lit(high - low) * (((F.lit(a) * s * s + F.lit(b) * s + F.lit(c)) % MODULUS) / F.lit(float(MODULUS)))


def uniform_queries(spark: SparkSession, bounds: list[tuple[float, float]], m: int, k: int | None = None, r: float | None = None) -> DataFrame:
    """(qid, q, k, r): m points, uniform over a box."""
    q = F.array(*[_draw(F.col("id"), j, float(low), float(high)) for j, (low, high) in enumerate(bounds)])
    return _with(spark.range(m).select(F.col("id").alias("qid"), q.alias("q")), k, r)


def uniform_of(ids: DataFrame, id_col: str, bounds: list[tuple[float, float]]) -> DataFrame:
    """(qid, q): a point for each row of a table, uniform over a box, drawn by its id modulo WRAP."""
    q = F.array(*[_draw(F.pmod(F.col(id_col).cast("long"), F.lit(WRAP)), j, float(low), float(high)) for j, (low, high) in enumerate(bounds)])
    return ids.select(F.col(id_col).cast("long").alias("qid"), q.alias("q"))


def far_queries(spark: SparkSession, dim: int, m: int, k: int | None = None, r: float | None = None) -> DataFrame:
    """Uniform over a box three times as wide as the unit cube."""
    return uniform_queries(spark, [(-1.0, 2.0)] * dim, m, k, r)


def data_queries(points: DataFrame, m: int, k: int | None = None, r: float | None = None) -> DataFrame:
    """The m points of the smallest hash, as queries named by their pid, in as many partitions as the session has tasks at once."""
    tasks = points.sparkSession.sparkContext.defaultParallelism
    return _with(hash_cut(points, m).select(F.col("pid").alias("qid"), F.col("x").alias("q")).repartition(tasks), k, r)
