"""Nearest neighbours inside SQL: a table function over an index."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ballspark.operators.index import SpatialIndex, shared_dir
from ballspark.operators.kernel import SLACK, Trace, Tree, nearest_kernel

#: Trees of parts that a worker keeps.
KEPT = 8


def register_knn_of(index: SpatialIndex, name: str = "knn_of") -> None:
    """Registers ``name(x, k, r)`` for LATERAL use: rows (rank, pid, dist) of one query vector; r may be null.

    A vector goes to the parts by the distance of their balls, until the next is farther than r or than the k-th
    answer so far. The balls are broadcast, a row for each part; the trees are files, of which a worker keeps a few.
    """
    spark: SparkSession = index.spark
    folder = shared_dir(spark)

    def put(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            places = [Tree.from_bytes(data).stored(folder, str(part), least=0) for part, data in zip(batch["part_id"], batch["tree"])]
            yield batch.drop(columns="tree").assign(place=places)

    rows = index.parts.select("center", "radius", "part_id", "tree").mapInPandas(put, "center array<double>, radius double, part_id int, place binary").toPandas().sort_values("part_id")
    parts = spark.sparkContext.broadcast((np.array(rows["center"].tolist(), float).reshape(len(rows), index.dim), rows["radius"].to_numpy(), [bytes(p) for p in rows["place"]]))

    class KnnOf:
        def __init__(self):
            self.center, self.radius, self.places = parts.value
            self.tree = lru_cache(KEPT)(lambda place: Tree.from_bytes(place))

        def eval(self, x, k, r):
            found, limit = [], math.inf if r is None else float(r)
            gap = np.maximum(0.0, np.sqrt(((self.center - np.array(x, float)) ** 2).sum(axis=1)) * (1 - SLACK) - self.radius)
            for i in np.argsort(gap, kind="stable"):
                if gap[i] > limit or len(found) >= k and gap[i] > math.sqrt(found[-1][0]) * (1 + SLACK):
                    break
                found = nearest_kernel(self.tree(self.places[i]), list(x), int(k), limit, Trace(), found=found)
            for rank, (d2, pid) in enumerate(found, 1):
                yield rank, int(pid), math.sqrt(d2)

    spark.udtf.register(name, udtf(KnnOf, returnType="rank int, pid long, dist double"))
