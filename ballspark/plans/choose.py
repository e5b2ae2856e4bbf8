"""Which way a search should go, and how finely an index should be cut: decided on metadata before any plan is made."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ballspark.operators.index import SpatialIndex
from ballspark.operators.search import BROADCAST_QUERIES

#: Dimensions from which balls overlap so much that pruning is not to be expected; brute force up to so many pairs.
HIGH_DIM, FEW_PAIRS = 32, 50_000_000


def choose_engine(index: SpatialIndex, queries: int, k: int | None = None, r: float | None = None) -> str:
    """``brute`` where pruning is hopeless or everything is small, ``routed`` otherwise; the answers are equal."""
    if index.n * queries <= 1_000_000 or (index.dim >= HIGH_DIM and index.n * queries <= FEW_PAIRS):
        return "brute"
    if index.n_parts and queries <= BROADCAST_QUERIES and r is not None:
        widest = index.summaries().agg(F.max("radius")).first()[0]
        share = math.pow(min(1.0, r / max(1e-300, widest)), index.dim)
        if share > 0.5 and index.n * queries <= FEW_PAIRS:
            return "brute"
    return "routed"


def parts_for(n: int, dim: int, part_bytes: int = 256 << 20) -> int:
    """Parts of so many bytes of coordinates and ids each."""
    return max(1, -(-n * 8 * (dim + 1) // part_bytes))


def suggest_alpha(shared: float) -> float:
    """A weight of the offset term for queries that share that much of the data's distribution (0 to 1): none for all."""
    return round(2.0 * (1.0 - min(1.0, max(0.0, shared))), 3)
