"""Which parts a query can meet: a tree over the parts' balls or boxes, gone down by many queries together.

Up to ROUTED_PARTS parts have one such tree, a *router*, which is broadcast once an index. Beyond that
the parts are dealt to blocks by their centres: a router over the blocks is broadcast, and each block's own
router is a row of a table that the queries are joined with, so that nothing holds all parts at once.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ballspark.config import BuildConfig

from .kernel import SLACK, Tree, build, gaps, nearest_together, nearer_path, open_leaves, squared

#: Parts of one router.
ROUTED_PARTS = 400_000
#: Parts of a router's leaf, and queries that go through it together.
LEAF, TOGETHER = 16, 8192


def matrix(x: pd.Series) -> np.ndarray:
    return np.array(x.tolist(), float).reshape(len(x), -1) if len(x) else np.empty((0, 1))


@dataclass
class Router:
    """A tree whose points are the centres of regions (parts or blocks), and whose nodes' regions cover theirs."""

    tree: Tree
    ids: np.ndarray
    n: np.ndarray
    radius: np.ndarray
    box_lo: np.ndarray
    box_hi: np.ndarray
    #: Points below each node.
    held: np.ndarray

    @classmethod
    def over(cls, regions: pd.DataFrame, kind: str, key: str = "part_id") -> Router:
        regions = regions.sort_values(key)
        tree = build(matrix(regions["center"]), np.arange(len(regions)), BuildConfig(leaf_capacity=LEAF))
        rows = regions.iloc[tree.pid]
        radius, low, high, n = rows["radius"].to_numpy(), matrix(rows["box_lo"]), matrix(rows["box_hi"]), rows["n"].to_numpy()
        held = np.concatenate([[0], np.cumsum(n)])
        for depth in range(int(tree.depth.max(initial=-1)) + 1):  # nodes of a level don't overlap
            node = np.nonzero(tree.depth == depth)[0]
            sizes = tree.end[node] - tree.begin[node]
            starts = np.cumsum(sizes) - sizes
            at = np.arange(sizes.sum()) + np.repeat(tree.begin[node] - starts, sizes)
            out = np.sqrt(squared(tree.x[at], np.repeat(tree.center[node], sizes, axis=0))) + radius[at]
            tree.radius[node] = np.maximum.reduceat(out, starts) * (1 + SLACK)
            tree.box_lo[node], tree.box_hi[node] = np.minimum.reduceat(low[at], starts), np.maximum.reduceat(high[at], starts)
        tree.kind = "kdt" if kind == "kdt" else "pab"
        tree.pid = np.arange(len(rows))
        return cls(tree, rows[key].to_numpy(), n, radius, low, high, held[tree.end] - held[tree.begin])

    def _region_gaps(self, q: np.ndarray, at: np.ndarray) -> np.ndarray:
        as_nodes = replace(self.tree, center=self.tree.x, radius=self.radius, box_lo=self.box_lo, box_hi=self.box_hi)
        return gaps(as_nodes, q, at)

    def _pairs(self, who: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sizes = self.tree.end[node] - self.tree.begin[node]
        return np.repeat(who, sizes), np.arange(sizes.sum()) + np.repeat(self.tree.begin[node] - np.cumsum(sizes) + sizes, sizes)

    def meets(self, q: np.ndarray, reach: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(query, region's id) of all regions within each query's reach, by query."""
        out = [(np.empty(0, np.int64), self.ids[:0])]
        for a in range(0, len(q), TOGETHER):
            some, far = q[a : a + TOGETHER], reach[a : a + TOGETHER]
            who, at = self._pairs(*open_leaves(self.tree, some, far))
            near = self._region_gaps(some[who], at) <= far[who]
            order = np.argsort(who[near], kind="stable")
            out.append((a + who[near][order], self.ids[at[near][order]]))
        return np.concatenate([o[0] for o in out]), np.concatenate([o[1] for o in out])

    def home(self, q: np.ndarray) -> np.ndarray:
        """For each query a region that is near: the nearest of those in the leaf on its nearer path."""
        *_, node = nearer_path(self.tree, q, np.ones(len(q), np.int64))
        who, at = self._pairs(np.arange(len(q)), node)
        order = np.lexsort((self.ids[at], self._region_gaps(q[who], at), who))
        return self.ids[at[order][np.searchsorted(who[order], np.arange(len(q)))]]

    def nearest_center(self, x: np.ndarray) -> np.ndarray:
        """The region whose centre is nearest; the lowest id among equals."""
        plain = build(self.tree.x, self.ids, BuildConfig(leaf_capacity=LEAF))
        who, ids, _ = nearest_together(plain, x, np.ones(len(x), np.int64), np.full(len(x), np.inf))
        return ids[np.argsort(who, kind="stable")]

    def bound(self, q: np.ndarray, k: np.ndarray) -> np.ndarray:
        """An upper bound of each query's k-th distance: the farthest reach of the nodes on its path that hold k points."""
        out = np.full(len(q), np.inf)
        for node in nearer_path(self.tree, q, np.ones(len(q), np.int64)):
            reach = np.sqrt(squared(self.tree.center[node], q)) + self.tree.radius[node]
            out = np.where(self.held[node] >= k, np.minimum(out, reach), out)
        who, at = self._pairs(np.arange(len(q)), node)
        reach = np.sqrt(squared(self.tree.x[at], q[who])) + self.radius[at]
        order = np.lexsort((reach, who))
        held = np.cumsum(self.n[at[order]])
        before = np.searchsorted(who[order], np.arange(len(q)))
        enough = held - (held[before] - self.n[at[order]][before])[who[order]] >= k[who[order]]
        hit = np.nonzero(enough)[0]
        of, first = np.unique(who[order][hit], return_index=True)
        out[of] = np.minimum(out[of], reach[order][hit[first]])
        return out * (1 + SLACK)


class Routing:
    """The routers of an index: one, or one over blocks of parts and a table of theirs."""

    def __init__(self, parts: DataFrame, n_parts: int, kind: str, cfg: BuildConfig):
        from .index import saved

        spark, self.blocks = parts.sparkSession, None
        regions = parts.drop("tree")
        if n_parts > ROUTED_PARTS:
            regions = saved(regions)
            self.blocks = saved(_blocks(regions, n_parts, kind, cfg))
            regions = self.blocks.drop("router").withColumnRenamed("block_id", "part_id")
        self.top = spark.sparkContext.broadcast(Router.over(regions.toPandas(), kind))

    def meets(self, queries: DataFrame, q: str, reach: str) -> DataFrame:
        """``queries`` with part_id, a row for each part within ``reach`` (a column; null is no limit) of the vector ``q``."""
        top = self.top

        @F.pandas_udf("array<int>")
        def regions(points: pd.Series, limit: pd.Series) -> pd.Series:
            who, ids = top.value.meets(matrix(points), limit.fillna(np.inf).to_numpy() * (1 + SLACK))
            return pd.Series(np.split(ids, np.searchsorted(who, np.arange(1, len(points)))) if len(points) else [])

        routed = queries.withColumn("part_id", F.explode(regions(q, reach)))
        if self.blocks is None:
            return routed
        return self._in_blocks(routed, queries.schema, lambda r, rows: r.meets(matrix(rows[q]), rows[reach].fillna(np.inf).to_numpy() * (1 + SLACK)))

    def home(self, queries: DataFrame, q: str, nearest_center: bool = False) -> DataFrame:
        """``queries`` with part_id: the part whose centre is nearest, or just a near one, with a bound of the k-th distance where there is a column k.

        Over blocks the nearest centre is that of the block whose centre is nearest.
        """
        top, ask = self.top, "nearest_center" if nearest_center else "home"

        @F.pandas_udf("int")
        def region(points: pd.Series) -> pd.Series:
            return pd.Series(getattr(top.value, ask)(matrix(points)), dtype="int32")

        routed = queries.withColumn("part_id", region(q))
        if self.blocks is None:
            return routed
        return self._in_blocks(routed, queries.schema, lambda r, rows: (np.arange(len(rows)), getattr(r, ask)(matrix(rows[q]))))

    def bounded(self, queries: DataFrame) -> DataFrame:
        """``queries`` with most: what the parts' counts and balls alone say that the k-th distance is at most."""
        top = self.top

        @F.pandas_udf("double")
        def most(points: pd.Series, k: pd.Series) -> pd.Series:
            return pd.Series(top.value.bound(matrix(points), k.to_numpy()))

        return queries.withColumn("most", most("q", "k"))

    def _in_blocks(self, routed: DataFrame, schema, ask) -> DataFrame:
        joined = routed.withColumnRenamed("part_id", "block_id").join(self.blocks.select("block_id", "router"), "block_id")
        names = [f.name for f in schema.fields]

        def asked(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                for _, rows in batch.groupby("block_id"):
                    who, ids = ask(pickle.loads(rows["router"].iloc[0]), rows)
                    yield rows[names].iloc[who].assign(part_id=ids.astype(np.int32))

        return joined.mapInPandas(asked, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema.fields) + ", part_id int")


def _blocks(regions: DataFrame, n_parts: int, kind: str, cfg: BuildConfig) -> DataFrame:
    """(block_id, n, center, radius, box_lo, box_hi, router) of blocks of parts, dealt by a tree over a sample of centres."""
    from .index import _top_tree_router

    count = max(2, -(-n_parts // (ROUTED_PARTS // 4 + 1)))
    share = min(1.0, 1.2 * count * cfg.sample_rows / n_parts)
    centers = regions.select(F.col("part_id").cast("long").alias("pid"), F.col("center").alias("x"))
    sample = centers.where(F.pmod(F.xxhash64("pid", F.lit(cfg.seed)), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).toPandas()
    dealt = regions.withColumn("block_id", _top_tree_router(sample, count, replace(cfg, kind="pab"))("center"))

    def block(rows: pd.DataFrame) -> pd.DataFrame:
        r = Router.over(rows, kind)
        one = {"block_id": [int(rows["block_id"].iloc[0])], "n": [int(rows["n"].sum())], "center": [r.tree.center[0]], "radius": [r.tree.radius[0]], "box_lo": [r.tree.box_lo[0]], "box_hi": [r.tree.box_hi[0]]}
        return pd.DataFrame(one | {"router": [pickle.dumps(r)]})

    return dealt.groupBy("block_id").applyInPandas(block, "block_id int, n long, center array<double>, radius double, box_lo array<double>, box_hi array<double>, router binary")
