"""Synthetic point sets with the traits of the families that such trees are measured on.

All on ``spark.range`` with hashes as randomness: any n, the same points on any cluster.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

KINDS = ("latin", "highleyman", "niederreiter", "lithuanian", "sobol", "uniform")
#: Direction integers' seeds of the digital sequence's second dimension (primitive polynomial x + 1).
SOBOL_BITS = 31


def _unit(seed: int, *extra: int) -> Column:
    """Uniform in (0, 1) from a hash of the id."""
    h = F.xxhash64("id", *[F.lit(v) for v in (seed, *extra)])
    return (F.shiftrightunsigned(h, 11).cast("double") + 0.5) / F.lit(float(1 << 53))


def _normal(seed: int, k: int) -> Column:
    return F.sqrt(-2 * F.log(_unit(seed, k, 0))) * F.cos(2 * math.pi * _unit(seed, k, 1))


#: Rounds of a permutation; base of the digital sequence over another field than Sobol's.
ROUNDS, BASE = 24, 3


def _permuted(n: int, seed: int) -> Column:
    """A pseudo-random bijection of 0..n-1, for any n and without a sort: a swap-or-not shuffle.

    Each round pairs every number with its mirror image about a random place, and a hash of the pair says whether the two change places.
    """

    def swapped(x: Column, k: Column) -> Column:
        mirror = F.pmod(F.pmod(F.xxhash64(k, F.lit(seed)), F.lit(n)) - x, F.lit(n))
        return F.when(F.xxhash64(F.greatest(x, mirror), k, F.lit(seed)).bitwiseAND(F.lit(1)) == 1, mirror).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), F.col("id"), swapped)


def _digital(n: int, shift: int) -> Column:
    """The digital sequence in base 3 of the polynomial x - ``shift``: the digits of the id times a matrix of binomial coefficients."""
    digits = next(r for r in range(1, 64) if BASE**r >= n)
    of_id = F.transform(F.array(*[F.lit(BASE**r) for r in range(digits)]), lambda p: F.floor(F.col("id") / p) % BASE)
    out = F.lit(0.0)
    for j in range(digits):
        row = F.array(*[F.lit(math.comb(r, j) * shift ** max(0, r - j) % BASE) for r in range(digits)])
        total = F.aggregate(F.zip_with(of_id, row, lambda d, m: d * m), F.lit(0).cast("long"), lambda a, v: a + v)
        out = out + total % BASE / float(BASE ** (j + 1))
    return out


def _radical_inverse_2(i: Column, directions: list[int]) -> Column:
    out = F.lit(0).cast("long")
    for bit, v in enumerate(directions):
        out = out.bitwiseXOR(F.when(F.shiftright(i, bit).bitwiseAND(F.lit(1)) == 1, F.lit(v)).otherwise(F.lit(0)).cast("long"))
    return out.cast("double") / F.lit(float(1 << SOBOL_BITS))


def _directions(dimension: int) -> list[int]:
    """Of the base-2 digital sequence: bit reversal, and the sequence of the polynomial x + 1."""
    if dimension == 0:
        return [1 << (SOBOL_BITS - 1 - k) for k in range(SOBOL_BITS)]
    m = [1]
    for _ in range(1, SOBOL_BITS):
        m.append(m[-1] * 2 ^ m[-1])
    return [v << (SOBOL_BITS - 1 - k) for k, v in enumerate(m)]


def generate(spark: SparkSession, kind: str, n: int, seed: int = 42, ids: DataFrame | None = None) -> DataFrame:
    """(pid, x) of n points in two dimensions; with ``ids`` only those of these numbers (id, from 0 and below n)."""
    ids = spark.range(n) if ids is None else ids
    if kind == "latin":
        x = [(F.col("id") + 0.5) / n, (_permuted(n, seed) + 0.5) / n]
    elif kind == "highleyman":
        first = F.col("id") % 2 == 0
        x = [F.when(first, 1 + _normal(seed, 1)).otherwise(2 + 0.1 * _normal(seed, 1)), F.when(first, 1 + 0.5 * _normal(seed, 2)).otherwise(2 * _normal(seed, 2))]
    elif kind == "lithuanian":
        first, angle = F.col("id") % 2 == 0, (_unit(seed, 3) - 0.5) * math.pi * 1.2
        r = 5 + 0.5 * _normal(seed, 4)
        x = [F.when(first, r * F.cos(angle)).otherwise(3 - r * F.cos(angle)), F.when(first, r * F.sin(angle)).otherwise(4 + r * F.sin(angle))]
    elif kind == "sobol":
        gray = F.col("id").bitwiseXOR(F.shiftright("id", 1))
        x = [_radical_inverse_2(gray, _directions(d)) for d in (0, 1)]
    elif kind == "niederreiter":  # in base 2 its first two dimensions would be Sobol's points in another order
        x = [_digital(n, shift) for shift in (0, 1)]
    elif kind == "uniform":
        x = [_unit(seed, 7), _unit(seed, 8)]
    else:
        raise ValueError(f"kind is one of {', '.join(KINDS)}")
    return ids.select(F.col("id").alias("pid"), F.array(*[c.cast("double") for c in x]).alias("x"))


def with_outliers(points: DataFrame, dim: int, one_in: int = 1000, reach: float = 10.0) -> DataFrame:
    """Points of the unit cube with one in so many, chosen by hash, moved ``reach`` times as far out."""
    chosen = F.pmod(F.xxhash64("pid"), F.lit(one_in)) == 0
    return points.withColumn("x", F.when(chosen, F.array(*[F.col("x")[j] * reach for j in range(dim)])).otherwise(F.col("x")))
