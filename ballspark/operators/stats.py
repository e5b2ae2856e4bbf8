"""Measures of trees and of searches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .index import SpatialIndex
from .kernel import Top, Tree, squared

#: Arrays of a tree that depths are counted on, and the counts.
COUNTED, DEPTHS = ("lo", "depth", "begin", "end"), "part_id int, depth int, leaves long, points long"
#: Nodes that are measured at a time.
RUN = 1 << 20


def _depths_of(t: Tree, part: int) -> pd.DataFrame:
    leaf = np.nonzero(t.lo < 0)[0]
    depth = t.depth[leaf].astype(np.int64)
    leaves, points = np.bincount(depth), np.bincount(depth, t.end[leaf] - t.begin[leaf])
    at = np.nonzero(leaves)[0]
    return pd.DataFrame({"part_id": np.full(len(at), part, np.int32), "depth": at.astype(np.int32), "leaves": leaves[at], "points": points[at].astype(np.int64)})


def _leaf_depths(index: SpatialIndex) -> DataFrame:
    """(part_id, depth, leaves, points) of each part's leaves, counted where its tree is."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for part, data in zip(batch["part_id"], batch["tree"]):
                yield _depths_of(Tree.from_bytes(data, COUNTED), part)

    return index.parts.select("part_id", "tree").mapInPandas(count, DEPTHS)


def avg_depth(index: SpatialIndex, *by: str) -> DataFrame:
    """(n, leaves, avg_depth, weighted_depth, max_depth) over leaves; weighted by their points. ``by`` part_id, of each part's tree."""
    return _averaged(_leaf_depths(index), *by)


def _averaged(depths: DataFrame, *by: str) -> DataFrame:
    return depths.groupBy(*by).agg(
        F.sum("points").alias("n"), F.sum("leaves").alias("leaves"), (F.sum(F.col("depth") * F.col("leaves")) / F.sum("leaves")).alias("avg_depth"),
        (F.sum(F.col("points") * F.col("depth")) / F.sum("points")).alias("weighted_depth"), F.max("depth").alias("max_depth"),
    )


def depth_histogram(index: SpatialIndex) -> DataFrame:
    return _leaf_depths(index).groupBy("depth").agg(F.sum("leaves").alias("leaves"), F.sum("points").alias("points"))


def families(index: SpatialIndex) -> DataFrame:
    """Each internal node with its two children."""
    nodes = index.nodes()
    kid = nodes.select("part_id", F.col("node_id").alias("kid"), F.col("n").alias("n"), "radius", "center")
    lo, hi = (kid.select("part_id", F.col("kid").alias(f"{s}_id"), F.col("n").alias(f"n_{s}"), F.col("radius").alias(f"r_{s}"), F.col("center").alias(f"c_{s}")) for s in ("lo", "hi"))
    inner = nodes.where("not is_leaf").select("part_id", "node_id", "lo_id", "hi_id", "n", "radius", "objective")
    return inner.join(lo, ["part_id", "lo_id"]).join(hi, ["part_id", "hi_id"])


#: Arrays of a tree that its quality and depths are measured on, and the sums of each part's internal nodes.
QUALITY = ("lo", "hi", "depth", "begin", "end", "center", "radius", "objective", "box_lo", "box_hi")
SUMS = ("inner", "n", "imbalance", "weighted", "child_radius", "overlap", "objective", "objectives")


def _sums(t: Tree | Top, n: np.ndarray) -> tuple:
    """SUMS over the internal nodes of a tree, or of a top, whose nodes have ``n`` points, RUN nodes at a time."""
    inner, out = np.nonzero(t.lo >= 0)[0], np.zeros(len(SUMS))
    for a in range(0, len(inner), RUN):
        at = inner[a : a + RUN]
        lo, hi = t.lo[at], t.hi[at]
        apart, both = np.abs(n[lo] - n[hi]), t.radius[lo] + t.radius[hi]
        objective = t.objective[at]
        overlap = np.maximum(0.0, both - np.sqrt(squared(t.center[lo], t.center[hi])))
        out += (len(at), n[at].sum(), (apart / n[at]).sum(), apart.sum(), (both / 2 / t.radius[at]).sum(), overlap.sum(), np.nansum(objective), (~np.isnan(objective)).sum())
    return tuple(out.tolist())


def tree_quality(index: SpatialIndex) -> DataFrame:
    """(inner, imbalance, weighted_imbalance, child_radius, overlap, objective): means over internal nodes.

    Imbalance is the share by which the children's counts differ, child_radius the mean child's radius
    over its parent's, overlap by how much the children's balls reach into each other. They are summed where the trees are.
    """

    def summed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for data in batch["tree"]:
                t = Tree.from_bytes(data, QUALITY)
                yield pd.DataFrame([_sums(t, t.end - t.begin)], columns=SUMS)

    schema = ", ".join(f"{c} double" for c in SUMS)
    sums = index.parts.select("tree").mapInPandas(summed, schema)
    if index.top:
        sums = sums.unionByName(index.spark.createDataFrame([_sums(index.top, index.top.n)], schema))
    total = sums.agg(*[F.sum(c).alias(c) for c in SUMS])
    share = lambda a, b="inner": F.when(F.col(b) > 0, F.col(a) / F.col(b))
    return total.select(
        F.coalesce("inner", F.lit(0.0)).cast("long").alias("inner"), share("imbalance").alias("imbalance"), share("weighted", "n").alias("weighted_imbalance"),
        share("child_radius").alias("child_radius"), share("overlap").alias("overlap"), share("objective", "objectives").alias("objective"),
    )


def average_cost(trace: DataFrame) -> DataFrame:
    """(queries, avg_entered, avg_expanded, avg_leaves, avg_points, avg_answers) of a search's counters."""
    return trace.agg(
        F.count("*").alias("queries"), F.avg("nodes_entered").alias("avg_entered"), F.avg("nodes_expanded").alias("avg_expanded"),
        F.avg("leaves_scanned").alias("avg_leaves"), F.avg("points_compared").alias("avg_points"), F.avg("answers").alias("avg_answers"),
    )


def reduction(base: DataFrame, ours: DataFrame) -> DataFrame:
    """One row of two ``average_cost`` rows, base_ and ours_, with the shares of the base's visits and comparisons that are saved."""
    both = [df.select(*[F.col(c).alias(f"{side}_{c.removeprefix('avg_')}") for c in df.columns if c != "queries"], *([F.col("queries")] if side == "base" else [])) for df, side in ((base, "base"), (ours, "ours"))]
    saved = {f"{name}_saved": (F.col(f"base_{c}") - F.col(f"ours_{c}")) / F.col(f"base_{c}") for name, c in (("visits", "entered"), ("comparisons", "points"))}
    return both[0].join(both[1]).withColumns(saved)


def cardinality(found: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(queries, answers, fewer, none, share_fewer): how many queries have fewer than k answers, and none."""
    counted = queries.select("qid").join(found.groupBy("qid").agg(F.count("*").alias("n")), "qid", "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("long"))
    fewer = F.count_if(F.col("n") < k)
    return counted.agg(F.count("*").alias("queries"), F.sum("n").alias("answers"), fewer.alias("fewer"), F.count_if(F.col("n") == 0).alias("none"), (fewer / F.count("*")).alias("share_fewer"))


def compare_exact(result: DataFrame, oracle: DataFrame) -> DataFrame:
    """(missing, extra, max_error) of answers (qid, pid, dist) against the oracle's: what exact means is all zero."""
    a = result.select("qid", "pid", F.col("dist").alias("d1"), F.lit(True).alias("here"))
    b = oracle.select("qid", "pid", F.col("dist").alias("d2"), F.lit(True).alias("there"))
    both = a.join(b, ["qid", "pid"], "full")
    return both.agg(
        F.count_if(F.col("here").isNull()).alias("missing"), F.count_if(F.col("there").isNull()).alias("extra"),
        F.coalesce(F.max(F.abs(F.col("d1") - F.col("d2"))), F.lit(0.0)).alias("max_error"),
    )


def invariants(index: SpatialIndex) -> DataFrame:
    """(points, nodes, leaves, cover, partition_gap, over_capacity, parent_gap, unsplit): all but the counts are zero in a sound tree.

    cover: points outside their leaf's ball; partition_gap: points that are in no leaf or in two;
    over_capacity: leaves above capacity whose points are not all equal; parent_gap: internal nodes
    whose children don't add up; unsplit: internal nodes with an empty child.
    """
    from ballspark.functions.geometry import in_ball

    nodes, points = index.nodes(), index.leaf_points()
    leaf = nodes.where("is_leaf")
    covered = points.join(leaf.select("part_id", F.col("node_id").alias("leaf_id"), "center", "radius"), ["part_id", "leaf_id"])
    a = covered.agg(F.count("*").alias("points"), F.count_if(~in_ball(F.col("x"), F.col("center"), F.col("radius") * (1 + 1e-9) + 1e-12, index.dim)).alias("cover"))
    b = points.groupBy("part_id", "leaf_id").count().join(leaf.select("part_id", F.col("node_id").alias("leaf_id"), "n"), ["part_id", "leaf_id"], "full")
    b = b.agg(F.coalesce(F.sum(F.abs(F.coalesce("count", F.lit(0)) - F.coalesce("n", F.lit(0)))), F.lit(0)).alias("partition_gap"))
    spread = F.exists(F.zip_with("box_lo", "box_hi", lambda u, v: v > u), lambda t: t)
    c = nodes.agg(F.count("*").alias("nodes"), F.count_if("is_leaf").alias("leaves"), F.count_if(F.col("is_leaf") & (F.col("n") > index.config.leaf_capacity) & spread).alias("over_capacity"))
    f = families(index)
    d = f.agg(F.count_if(F.col("n") != F.col("n_lo") + F.col("n_hi")).alias("parent_gap"), F.count_if((F.col("n_lo") < 1) | (F.col("n_hi") < 1)).alias("unsplit"))
    return a.join(b).join(c).join(d)


def ancestors_cover(index: SpatialIndex) -> DataFrame:
    """(pairs, violations): points against the balls of all nodes above them, by walking up a level a step."""
    from ballspark.functions.geometry import in_ball

    from .index import saved

    nodes = saved(index.nodes().select("part_id", "node_id", "parent_id", "center", "radius"))
    here = index.leaf_points().withColumnRenamed("leaf_id", "node_id")
    total = bad = 0
    while True:
        met = saved(here.join(nodes, ["part_id", "node_id"]))
        got = met.agg(F.count("*").alias("c"), F.count_if(~in_ball(F.col("x"), F.col("center"), F.col("radius") * (1 + 1e-9) + 1e-12, index.dim)).alias("b")).first()
        if not got.c:
            break
        total, bad = total + got.c, bad + got.b
        here = met.where("parent_id >= 0").select("part_id", F.col("parent_id").alias("node_id"), "pid", "x")
    return index.spark.createDataFrame([(total, bad)], "pairs long, violations long")
