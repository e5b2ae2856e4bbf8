"""Splits as DataFrame plans: every node of a level at once, over all points, without Python on points.

Each step is one aggregate by node code (root 1, children 2c and 2c + 1): moments, extents, the
histogram of half-sections. Aggregates combine before the shuffle, so that what moves is a few rows a
node and task. Only node rows meet Python, for eigenvectors beyond two dimensions.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ballspark.config import BuildConfig
from ballspark.functions.geometry import dot, sq_dist

from .kernel import canonical

#: Nodes whose rows are broadcast to the points together; bins of a median's histogram, and values of a node that are gathered once there are no more.
AT_ONCE, BINS, GATHERED = 100_000, 1024, 4096
#: Levels that a 64-bit code has room for.
DEEPEST = 60
#: Above this dimension moments are summed as arrays in Python instead of by written-out columns.
WRITTEN_OUT = 16


def node_moments(points: DataFrame, dim: int, node: str = "code") -> DataFrame:
    """(code, n, mean, c): counts, means and sums of centred products, from a first pass for the means."""
    means = points.groupBy(node).agg(F.count("*").alias("n"), F.array(*[F.avg(F.col("x")[j]) for j in range(dim)]).alias("mean"))
    rows = points.join(F.broadcast(means), node)
    if dim > WRITTEN_OUT:
        return _wide_moments(rows, dim, node)
    centred = [F.col("x")[j] - F.col("mean")[j] for j in range(dim)]
    c = [F.sum(centred[i] * centred[j]) for i in range(dim) for j in range(i, dim)]
    return rows.groupBy(node).agg(F.first("n").alias("n"), F.first("mean").alias("mean"), F.array(*c).alias("c"))


def _wide_moments(rows: DataFrame, dim: int, node: str) -> DataFrame:
    """Products summed a batch at a time in Python, batches summed by Spark as one row a cell."""

    def partial(batches):
        for b in batches:
            for key, g in b.groupby(node):
                x = np.array(g["x"].tolist()) - np.array(g["mean"].iloc[0])
                yield pd.DataFrame({node: [key], "n": [g["n"].iloc[0]], "mean": [g["mean"].iloc[0]], "s": [(x.T @ x)[np.triu_indices(dim)]]})

    parts = rows.select(node, "n", "mean", "x").mapInPandas(partial, f"{node} long, n long, mean array<double>, s array<double>")
    cells = parts.select(node, F.posexplode("s").alias("i", "v")).groupBy(node, "i").agg(F.sum("v").alias("v"))
    sums = cells.groupBy(node).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda t: t["v"]).alias("c"))
    return rows.select(node, "n", "mean").dropDuplicates([node]).join(sums, node)


def raw_moments(points: DataFrame, dim: int, node: str = "code") -> DataFrame:
    """(code, n, mean, c) with uncentred products, for the uncentred axis."""
    c = [F.sum(F.col("x")[i] * F.col("x")[j]) for i in range(dim) for j in range(i, dim)]
    return points.groupBy(node).agg(F.count("*").alias("n"), F.array(*[F.avg(F.col("x")[j]) for j in range(dim)]).alias("mean"), F.array(*c).alias("c"))


def principal_axis(moments: DataFrame, dim: int) -> DataFrame:
    """``moments`` with ``axis``, the unit eigenvector of the largest eigenvalue, its largest component positive.

    In two dimensions the closed form of the total least-squares line; otherwise eigenvectors of node rows in Python.
    """
    if dim == 1:
        return moments.withColumn("axis", F.array(F.lit(1.0)))
    if dim == 2:
        xx, xy, yy = F.col("c")[0], F.col("c")[1], F.col("c")[2]
        angle = 0.5 * F.atan2(2 * xy, xx - yy)
        return moments.withColumn("axis", _positive(F.cos(angle), F.sin(angle)))

    @F.pandas_udf("array<double>")
    def eigen(c: pd.Series) -> pd.Series:
        m = np.zeros((len(c), dim, dim))
        i, j = np.triu_indices(dim)
        m[:, i, j] = m[:, j, i] = np.array(c.tolist()).reshape(len(c), -1)
        return pd.Series(list(canonical(np.linalg.eigh(m)[1][:, :, -1])))

    return moments.withColumn("axis", eigen("c"))


def _positive(a: Column, b: Column) -> Column:
    lead = F.when(F.abs(a) >= F.abs(b) * (1 - 1e-9), a).otherwise(b)
    sign = F.when(lead < 0, -1.0).otherwise(1.0)
    return F.array(a * sign, b * sign)


def projected(points: DataFrame, axes: DataFrame, dim: int, node: str = "code") -> DataFrame:
    """``points`` with t, the place on their node's axis."""
    return points.join(F.broadcast(axes.select(node, "axis")), node).withColumn("t", dot(F.col("x"), F.col("axis"), dim))


def extents(placed: DataFrame, node: str = "code") -> DataFrame:
    return placed.groupBy(node).agg(F.min("t").alias("t_min"), F.max("t").alias("t_max"), F.count("*").alias("n"))


def half_section(t: Column, t_min: Column, t_max: Column, sections: int) -> Column:
    """Which of 2S half-sections; the last takes t_max."""
    return F.least(F.lit(2 * sections - 1), F.floor((t - t_min) / (t_max - t_min) * (2 * sections))).cast("int")


def section_scan(placed: DataFrame, extent: DataFrame, cfg: BuildConfig, node: str = "code") -> DataFrame:
    """(code, section, t_c, n, n_below, f1, f2, f): the objective at each section's midpoint, from exact counts."""
    s = cfg.sections
    open_nodes = F.broadcast(extent.where("t_max > t_min"))
    bins = placed.drop("n").join(open_nodes, node).select(node, half_section(F.col("t"), F.col("t_min"), F.col("t_max"), s).alias("half")).groupBy(node, "half").count()
    # a midpoint is the lower edge of its odd half-section: that half-section and the even one after it lie above it
    lands = bins.select(node, F.ceil(F.col("half") / 2).cast("int").alias("section"), "count").groupBy(node, "section").agg(F.sum("count").alias("c"))
    grid = extent.where("t_max > t_min").withColumn("section", F.explode(F.sequence(F.lit(0), F.lit(s - 1))))
    below = F.coalesce(F.sum("c").over(Window.partitionBy(node).orderBy("section").rowsBetween(Window.unboundedPreceding, 0)), F.lit(0))
    rows = grid.join(lands, [node, "section"], "left").withColumn("n_below", below.cast("long"))
    share = (F.col("section") + 0.5) / s
    f1 = F.abs(F.col("n") - 2 * F.col("n_below")) / F.col("n")
    f2 = F.abs(2 * share - 1) if cfg.offset == "centred" else share
    t_c = F.col("t_min") + (F.col("t_max") - F.col("t_min")) * share
    return rows.select(node, "section", t_c.alias("t_c"), "t_min", "t_max", "n", "n_below", f1.alias("f1"), f2.alias("f2")).withColumn("f", F.col("f1") + F.lit(cfg.alpha) * F.col("f2"))


def best_cut(scan: DataFrame, node: str = "code") -> DataFrame:
    """(code, section, t_c, t_min, t_max, n, n_lo, n_hi, f): the first section of the least objective."""
    best = F.min_by(F.struct("section", "t_c", "t_min", "t_max", "n", "n_below", "f"), F.struct(F.round("f", 12), F.col("section")))
    b = scan.groupBy(node).agg(best.alias("b")).select(node, "b.*")
    return b.select(node, "section", "t_c", "t_min", "t_max", "n", F.col("n_below").alias("n_lo"), (F.col("n") - F.col("n_below")).alias("n_hi"), "f")


def mean_cut(placed: DataFrame, extent: DataFrame, cfg: BuildConfig, node: str = "code") -> DataFrame:
    """``best_cut`` with candidates at the mean of the points of each section: one more counting pass."""
    s = cfg.sections
    rows = placed.drop("n").join(F.broadcast(extent.where("t_max > t_min")), node)
    rows = rows.withColumn("section", F.least(F.lit(s - 1), F.floor((F.col("t") - F.col("t_min")) / (F.col("t_max") - F.col("t_min")) * s)).cast("int"))
    means = rows.groupBy(node, "section").agg(F.avg("t").alias("t_c"), F.count("*").alias("c"))
    inside = rows.join(F.broadcast(means), [node, "section"]).groupBy(node, "section").agg(F.count_if(F.col("t") < F.col("t_c")).alias("inside"))
    before = F.coalesce(F.sum("c").over(Window.partitionBy(node).orderBy("section").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    at = means.join(inside, [node, "section"]).withColumn("n_below", before + F.col("inside")).join(extent, node)
    share = (F.col("t_c") - F.col("t_min")) / (F.col("t_max") - F.col("t_min"))
    f2 = F.abs(2 * share - 1) if cfg.offset == "centred" else share
    return best_cut(at.withColumn("f", F.abs(F.col("n") - 2 * F.col("n_below")) / F.col("n") + F.lit(cfg.alpha) * f2), node)


def exhaustive_cut(placed: DataFrame, extent: DataFrame, cfg: BuildConfig, node: str = "code") -> DataFrame:
    """The best of all gaps between neighbouring projections: what the section scan approximates.

    Sorts whole nodes: an ablation for nodes of one task's size, not a way to build.
    """
    w = Window.partitionBy(node).orderBy("t")
    rows = placed.drop("n").groupBy(node, "t").count().withColumns({"next": F.lead("t").over(w), "n_below": F.sum("count").over(w.rowsBetween(Window.unboundedPreceding, 0))})
    gaps = rows.where("next is not null").join(F.broadcast(extent), node).withColumn("t_c", (F.col("t") + F.col("next")) / 2)
    share = (F.col("t_c") - F.col("t_min")) / (F.col("t_max") - F.col("t_min"))
    f2 = F.abs(2 * share - 1) if cfg.offset == "centred" else share
    f = F.abs(F.col("n") - 2 * F.col("n_below")) / F.col("n") + F.lit(cfg.alpha) * f2
    return best_cut(gaps.withColumns({"f": f, "section": F.row_number().over(w)}), node)


def split_level(points: DataFrame, dim: int, cfg: BuildConfig, depth: int) -> DataFrame:
    """``points`` (code, pid, x) with each splittable node's points moved to its children's codes."""
    if cfg.kind == "pab":
        moments = raw_moments(points, dim) if cfg.axis == "gram" else node_moments(points, dim)
        placed = projected(points, principal_axis(moments, dim), dim)
        extent = extents(placed)
        if cfg.cut == "exhaustive":
            cuts, rule = exhaustive_cut(placed, extent, cfg), F.col("t") >= F.col("t_c")
        elif cfg.candidate == "data_mean":
            cuts, rule = mean_cut(placed, extent, cfg), F.col("t") >= F.col("t_c")
        else:
            cuts, rule = best_cut(section_scan(placed, extent, cfg)), half_section(F.col("t"), F.col("t_min"), F.col("t_max"), cfg.sections) > 2 * F.col("section")
        cuts = cuts.where("n_lo > 0 and n_hi > 0").select("code", "section", "t_c", "t_min", "t_max")
        rows = placed.select("code", "pid", "x", "t").join(F.broadcast(cuts), "code", "left")
        side = F.when(F.col("t_c").isNull(), None).otherwise(rule.cast("int"))
    elif cfg.kind == "fpb":
        pivots = fpb_pivots(points, dim).where(sq_dist(F.col("pivot_lo"), F.col("pivot_hi"), dim) > 0)
        rows = points.join(F.broadcast(pivots), "code", "left")
        side = (sq_dist(F.col("x"), F.col("pivot_hi"), dim) < sq_dist(F.col("x"), F.col("pivot_lo"), dim)).cast("int")
    else:
        rows = points.join(F.broadcast(kd_cuts(points, dim, cfg, depth)), "code", "left")
        value = F.element_at("x", F.col("dim") + 1)
        side = F.when(F.col("above"), value > F.col("cut")).otherwise(value >= F.col("cut")).cast("int")
    code = F.when(side.isNull(), F.col("code")).otherwise(2 * F.col("code") + side)
    return rows.select(code.cast("long").alias("code"), "pid", "x")


def fpb_pivots(points: DataFrame, dim: int) -> DataFrame:
    """(code, n, pivot_lo, pivot_hi): the point farthest from the centroid and the point farthest from it; smallest pid among equals."""
    means = points.groupBy("code").agg(F.count("*").alias("n"), F.array(*[F.avg(F.col("x")[j]) for j in range(dim)]).alias("mean"))

    def farthest(rows: DataFrame, from_: str, name: str) -> DataFrame:
        return rows.groupBy("code").agg(F.max_by("x", F.struct(sq_dist(F.col("x"), F.col(from_), dim).alias("d"), (-F.col("pid")).alias("p"))).alias(name))

    one = farthest(points.join(F.broadcast(means), "code"), "mean", "pivot_lo")
    two = farthest(points.join(F.broadcast(one), "code"), "pivot_lo", "pivot_hi")
    return means.select("code", "n").join(one, "code").join(two, "code")


def kd_cuts(points: DataFrame, dim: int, cfg: BuildConfig, depth: int = 0) -> DataFrame:
    """(code, n, dim, cut, above): the axis and place of each node's cut; ``above``: equal values go to the lower side."""
    low, high = [F.min(F.col("x")[j]) for j in range(dim)], [F.max(F.col("x")[j]) for j in range(dim)]
    spread = [F.var_pop(F.col("x")[j]) for j in range(dim)] if cfg.kd_axis == "variance" else [h - lo for lo, h in zip(low, high)]
    boxes = points.groupBy("code").agg(F.count("*").alias("n"), F.array(*low).alias("low"), F.array(*high).alias("high"), F.array(*spread).alias("spread"))
    widest = (F.array_position("spread", F.array_max("spread")) - 1).cast("int")
    turn = F.when(F.col("high")[depth % dim] > F.col("low")[depth % dim], F.lit(depth % dim)).otherwise(widest) if cfg.kd_axis == "cycle" else widest
    boxes = boxes.withColumn("dim", turn).where(F.element_at("high", F.col("dim") + 1) > F.element_at("low", F.col("dim") + 1))
    at = F.col("dim") + 1
    if cfg.kd_cut == "midpoint":
        cuts = boxes.withColumn("cut", (F.element_at("low", at) + F.element_at("high", at)) / 2)
    else:
        values = points.join(F.broadcast(boxes.select("code", "dim")), "code").select("code", F.element_at("x", at).alias("v"))
        ranges = boxes.select("code", "n", F.element_at("low", at).alias("low"), F.element_at("high", at).alias("high"))
        cuts = boxes.join(medians(values, ranges), "code")
    return cuts.select("code", "n", "dim", "cut", (F.col("cut") <= F.element_at("low", at)).alias("above"))


def medians(values: DataFrame, ranges: DataFrame) -> DataFrame:
    """(code, cut): the exact median of each node's values (code, v), whose count and range are given (code, n, low, high).

    Each pass counts a node's values in BINS bins of its range, and goes on in the bin that has the middle
    one. Counts combine before the shuffle, so that no task holds a node's values, until they are few.
    """
    from .index import saved

    state = ranges.select("code", "n", "low", "high", F.lit(0).cast("long").alias("before"), F.col("n").alias("c"), F.lit(None).cast("double").alias("after"))
    while True:
        state = saved(state)
        if state.where((F.col("c") > GATHERED) & (F.col("low") < F.col("high"))).isEmpty():
            break
        place = F.when(F.col("low") < F.col("high"), F.least(F.lit(BINS - 1), F.floor((F.col("v") - F.col("low")) / (F.col("high") - F.col("low")) * BINS))).otherwise(0)
        here = values.join(F.broadcast(state.select("code", "low", "high")), "code").where(F.col("v").between(F.col("low"), F.col("high")))
        bins = here.select("code", place.alias("bin"), "v").groupBy("code", "bin").agg(F.count("*").alias("k"), F.min("v").alias("lo"), F.max("v").alias("hi"))
        along = Window.partitionBy("code").orderBy("bin")
        bins = bins.withColumns({"upto": F.sum("k").over(along.rowsBetween(Window.unboundedPreceding, 0)), "next": F.lead("lo").over(along)})
        found = bins.join(F.broadcast(state), "code").withColumn("upto", F.col("before") + F.col("upto"))
        middle = F.floor((F.col("n") - 1) / 2)
        found = found.where((F.col("upto") - F.col("k") <= middle) & (middle < F.col("upto")))
        state = found.select("code", "n", F.col("lo").alias("low"), F.col("hi").alias("high"), (F.col("upto") - F.col("k")).alias("before"), F.col("k").alias("c"), F.coalesce("next", "after").alias("after"))
    few = values.join(F.broadcast(state.where("low < high").select("code", "low", "high")), "code").where(F.col("v").between(F.col("low"), F.col("high")))
    lists = few.groupBy("code").agg(F.sort_array(F.collect_list("v")).alias("vs"))

    def ranked(rank: Column) -> Column:
        inside = F.when(F.col("low") < F.col("high"), F.get("vs", (rank - F.col("before")).cast("int"))).otherwise(F.col("low"))
        return F.when(rank < F.col("before") + F.col("c"), inside).otherwise(F.col("after"))

    rows = state.join(lists, "code", "left")
    return rows.select("code", ((ranked(F.floor((F.col("n") - 1) / 2)) + ranked(F.floor(F.col("n") / 2))) / 2).alias("cut"))


def levels(points: DataFrame, dim: int, cfg: BuildConfig, depth: int) -> DataFrame:
    """(code, pid, x) after ``depth`` levels of splits of all points; each level is written."""
    from .index import saved

    rows = points.select(F.lit(1).cast("long").alias("code"), "pid", "x")
    for d in range(depth):
        rows = saved(split_level(rows, dim, cfg, d))
    return rows


def assign_levels(points: DataFrame, dim: int, cfg: BuildConfig, max_rows: int) -> DataFrame:
    """(part_id, pid, x): splits of all points until no node has more than ``max_rows``, or none can be split.

    Of a level with very many nodes AT_ONCE are split at a time, so that what is broadcast is bounded. Nodes that are
    still too large after DEEPEST levels stay, and the caller cuts them by pid. Part ids number the nodes.
    """
    from .index import saved

    rows, was = saved(points.select(F.lit(1).cast("long").alias("code"), "pid", "x")), -1
    for depth in range(DEEPEST):
        sizes = saved(rows.groupBy("code").count())
        large = sizes.where(F.col("count") > max_rows)
        nodes, open_nodes = sizes.count(), large.count()
        if not open_nodes or nodes == was:
            break
        was, turns = nodes, -(-open_nodes // AT_ONCE)
        turn = large.select("code", F.pmod(F.xxhash64("code"), F.lit(turns)).alias("turn"))
        marked = rows.join(F.broadcast(turn) if turns == 1 else turn, "code", "left")
        marked = saved(marked) if turns > 1 else marked
        out = marked.where("turn is null").drop("turn")
        for i in range(turns):
            out = out.unionByName(split_level(marked.where(F.col("turn") == i).drop("turn"), dim, cfg, depth))
        rows = saved(out)
    numbers = saved(rows.select("code").distinct()).withColumn("part_id", (F.row_number().over(Window.orderBy("code")) - 1).cast("int"))  # a row for each node
    few = numbers.count() <= AT_ONCE
    return rows.join(F.broadcast(numbers) if few else numbers, "code").select("part_id", "pid", "x")


def root_ball(points: DataFrame, dim: int) -> DataFrame:
    """(n, center, radius) of all points: centroid and farthest distance."""
    mean = points.agg(F.count("*").alias("n"), F.array(*[F.avg(F.col("x")[j]) for j in range(dim)]).alias("center"))
    return points.join(F.broadcast(mean)).groupBy("n", "center").agg(F.sqrt(F.max(sq_dist(F.col("x"), F.col("center"), dim))).alias("radius"))
