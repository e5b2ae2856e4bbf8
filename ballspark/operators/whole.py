"""One tree over any number of points: its top is split by all tasks together, the subtrees below are built in tasks of their own.

Points are written once as blocks, plain files that many tasks read at once. All nodes of a level of the top are split
by a few passes over the blocks, each adding up a few numbers a node; a node of at most PART points is a part, whose
subtree one task builds. The splits are the kernel's, so that the tree is that which one task would build, up to the
order in which sums are rounded; depths, counters and measures are those of a single tree.
"""

from __future__ import annotations

import uuid
from collections import namedtuple
from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import SparkSession

from ballspark.config import BuildConfig
from ballspark.schema import PARTS
from ballspark.sources.points import Points

from .index import SpatialIndex, dropped, grown, shared_dir, vectors
from .kernel import SLACK, Top, Tree, _cells, _Level, _project, canonical, offset_term, squared

#: Points of a part and of a block at most; bins that a median's range is counted in.
PART, BLOCK, BINS = 1_500_000, 1_000_000, 4096
#: Variants that tops are split by.
SPLITS = {"axis": "covariance", "axis_solver": "eigh", "candidate": "midpoint", "cut": "sections", "ball": "centroid", "kd_axis": "widest", "kd_cut": "median"}
Depths = namedtuple("Depths", "n leaves avg_depth weighted_depth max_depth")


def _write(path: str, values: np.ndarray) -> None:
    store, base = fs.FileSystem.from_uri(path)
    store.create_dir(base.rsplit("/", 1)[0])
    with store.open_output_stream(base, compression=None) as out:
        out.write(pa.py_buffer(np.ascontiguousarray(values)))


def _read(path: str, kind: type, begin: int = 0, end: int | None = None) -> np.ndarray:
    size = np.dtype(kind).itemsize
    store, base = fs.FileSystem.from_uri(path)
    with store.open_input_file(base) as f:
        f.seek(begin * size)
        return np.frombuffer(f.read_buffer((f.size() // size if end is None else end) * size - begin * size), kind)


@dataclass
class Blocks:
    """(name, points) of the files below ``folder`` that have the points."""

    spark: SparkSession
    folder: str
    names: list[tuple[str, int]]
    dim: int

    @property
    def n(self) -> int:
        return sum(n for _, n in self.names)

    def drop(self) -> None:
        dropped(self.spark, self.folder)

    def each(self, work: Callable, *, combine: Callable | None = None) -> list:
        """``work`` of each block's name, in tasks; with ``combine`` the results of a task's blocks are one."""

        def run(names):
            some = (work(name) for name in names)
            if combine is None:
                return some
            out = None
            for got in some:
                out = got if out is None else combine(out, got)
            return [] if out is None else [out]

        cores = 2 * self.spark.sparkContext.defaultParallelism
        found = self.spark.sparkContext.parallelize([name for name, _ in self.names], max(1, min(len(self.names), cores))).mapPartitions(run).collect()
        if combine is None:
            return found
        out = found[0]
        for got in found[1:]:
            out = combine(out, got)
        return out


def blocked(points: Points) -> Blocks:
    """The points as blocks; they are made once, however many trees are built over them."""
    spark, dim = points.df.sparkSession, points.dim
    folder = shared_dir(spark)

    def write(batches):
        held, n, i = [], 0, 0

        def block():
            name = f"{TaskContext.get().partitionId():06d}-{i:06d}"
            _write(f"{folder}/{name}.pid", np.concatenate([h[0] for h in held]))
            _write(f"{folder}/{name}.x", np.concatenate([h[1] for h in held]))
            return pa.RecordBatch.from_pylist([{"name": name, "n": n}], pa.schema([("name", pa.string()), ("n", pa.int64())]))

        for b in batches:
            for at in range(0, b.num_rows, BLOCK):
                some = b.slice(at, BLOCK)
                held.append((some["pid"].to_numpy().copy(), vectors(some["x"]).astype(np.float64)))
                n += some.num_rows
                if n >= BLOCK:
                    yield block()
                    held, n, i = [], 0, i + 1
        if n:
            yield block()

    rows = points.df.select("pid", "x").mapInArrow(write, "name string, n long").collect()
    return Blocks(spark, folder, sorted((r.name, r.n) for r in rows), dim)


# --- passes over blocks ---------------------------------------------------------------------------------


@dataclass
class _Source:
    """Where a pass finds a block's points and the nodes that they are in."""

    folder: str
    run: str
    dim: int
    depth: int = 0

    def x(self, name: str) -> np.ndarray:
        return _read(f"{self.folder}/{name}.x", np.float64).reshape(-1, self.dim)

    def pid(self, name: str) -> np.ndarray:
        return _read(f"{self.folder}/{name}.pid", np.int64)

    def code(self, name: str, n: int) -> np.ndarray:
        return _read(f"{self.folder}/{self.run}/{name}.{self.depth}", np.int32) if self.depth else np.zeros(n, np.int32)

    def level(self, name: str, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, _Level] | None:
        """(places in the block, positions in ``ids``, points in node order) of those of the nodes that the block has points of."""
        x, pid = self.x(name), self.pid(name)
        place = np.full(ids.max() + 2, -1, np.int32)
        place[ids] = np.arange(len(ids))
        at = place[np.minimum(self.code(name, len(pid)), len(place) - 1)]
        if len(ids) < 1 << 15:
            at = at.astype(np.int16)  # sorted by digits
        order = np.argsort(at, kind="stable")
        sizes = np.bincount(at[at >= 0], minlength=len(ids))
        order = order[len(order) - sizes.sum() :]
        if not len(order):
            return None
        here = np.nonzero(sizes)[0]
        ends = np.cumsum(sizes[here])
        return order, here, _Level(x[order], pid[order], ends - sizes[here], ends)


def _sides(level: _Level, cut: dict, cfg: BuildConfig) -> np.ndarray:
    """Which points go to the second child, as the kernel decides it."""
    if cfg.kind == "pab":
        return _half(level, cut, cfg) > 2 * level.of(cut["best"])
    if cfg.kind == "fpb":
        return squared(level.x, level.of(cut["two"])) < squared(level.x, level.of(cut["one"]))
    v, at = _along(level, cut["dim"]), level.of(cut["cut"])
    return np.where(level.of(cut["above"]), v > at, v >= at)


def _along(level: _Level, dim: np.ndarray) -> np.ndarray:
    return level.x[np.arange(len(level.x)), dim[level.seg]]


def _half(level: _Level, cut: dict, cfg: BuildConfig) -> np.ndarray:
    t, s = _project(level, cut["axis"]), cfg.sections
    return np.clip(((t - level.of(cut["t_min"])) / level.of(cut["span"]) * (2 * s)).astype(np.int64), 0, 2 * s - 1)


def _spread(here: np.ndarray, m: int, values: np.ndarray, fill) -> np.ndarray:
    out = np.full((m, *values.shape[1:]), fill, values.dtype)
    out[here] = values
    return out


def _moved(source: _Source, name: str, ids: np.ndarray, cut: dict, kids: np.ndarray, cfg: BuildConfig) -> None:
    """Writes the nodes that a block's points are in after a level's nodes ``ids`` are cut."""
    found = source.level(name, ids)
    code = source.code(name, len(source.pid(name))).copy()
    if found:
        order, here, level = found
        code[order] = level.of(kids[here]) + _sides(level, {n: v[here] for n, v in cut.items()}, cfg)
    _write(f"{source.folder}/{source.run}/{name}.{source.depth + 1}", code)


def _moments(source: _Source, name: str, ids: np.ndarray) -> dict:
    m, d = len(ids), source.dim
    out = {"n": np.zeros(m, np.int64), "mean": np.zeros((m, d)), "c": np.zeros((m, d, d)), "low": np.full((m, d), np.inf), "high": np.full((m, d), -np.inf)}
    if found := source.level(name, ids):
        _, here, level = found
        mean = level.total(level.x) / level.n[:, None]
        c = level.x - level.of(mean)
        out["n"][here], out["mean"][here], out["low"][here], out["high"][here] = level.n, mean, level.least(level.x), level.most(level.x)
        for i in range(d):
            for j in range(i, d):
                out["c"][here, i, j] = out["c"][here, j, i] = level.total(c[:, i] * c[:, j])
    return out


def _moments_of_both(a: dict, b: dict) -> dict:
    n = a["n"] + b["n"]
    apart, share = b["mean"] - a["mean"], (b["n"] / np.maximum(n, 1))[:, None]
    c = a["c"] + b["c"] + apart[:, :, None] * apart[:, None, :] * (a["n"][:, None] * share)[:, :, None]
    return {"n": n, "mean": a["mean"] + apart * share, "c": c, "low": np.minimum(a["low"], b["low"]), "high": np.maximum(a["high"], b["high"])}


def _farthest(source: _Source, name: str, ids: np.ndarray, from_: np.ndarray) -> dict:
    """The largest squared distance from a place of each node, with its point of the smallest pid."""
    m = len(ids)
    out = {"d": np.full(m, -1.0), "pid": np.full(m, np.iinfo(np.int64).max), "x": np.zeros((m, source.dim))}
    if found := source.level(name, ids):
        _, here, level = found
        d = squared(level.x, level.of(from_[here]))
        hit = level.farthest(d)
        out["d"][here], out["pid"][here], out["x"][here] = d[hit], level.pid[hit], level.x[hit]
    return out


def _farther(a: dict, b: dict) -> dict:
    first = (a["d"] > b["d"]) | (a["d"] == b["d"]) & (a["pid"] <= b["pid"])
    return {n: np.where(first if a[n].ndim == 1 else first[:, None], a[n], b[n]) for n in a}


def _extents(source: _Source, name: str, ids: np.ndarray, axis: np.ndarray, mean: np.ndarray) -> dict:
    m = len(ids)
    out = {"low": np.full(m, np.inf), "high": np.full(m, -np.inf), "d": np.zeros(m)}
    if found := source.level(name, ids):
        _, here, level = found
        t = _project(level, axis[here])
        out["low"][here], out["high"][here], out["d"][here] = level.least(t), level.most(t), level.most(squared(level.x, level.of(mean[here])))
    return out


def _wider(a: dict, b: dict) -> dict:
    return {"low": np.minimum(a["low"], b["low"]), "high": np.maximum(a["high"], b["high"]), "d": np.maximum(a["d"], b["d"])}


def _halves(source: _Source, name: str, ids: np.ndarray, cut: dict, cfg: BuildConfig) -> np.ndarray:
    width = 2 * cfg.sections
    out = np.zeros((len(ids), width), np.int64)
    if found := source.level(name, ids):
        _, here, level = found
        half = _half(level, {n: v[here] for n, v in cut.items()}, cfg)
        out[here] = np.bincount(level.seg * width + half, minlength=len(here) * width).reshape(-1, width)
    return out


def _bins(source: _Source, name: str, ids: np.ndarray, dim: np.ndarray, low: np.ndarray, high: np.ndarray, mean: np.ndarray | None) -> dict:
    """Counts, least and largest values in BINS bins of a range of each node's values along ``dim``; the largest distance from ``mean``, where that is given."""
    m = len(ids)
    out = {"n": np.zeros((m, BINS), np.int64), "low": np.full((m, BINS), np.inf), "high": np.full((m, BINS), -np.inf), "d": np.zeros(m)}
    if found := source.level(name, ids):
        _, here, level = found
        if mean is not None:
            out["d"][here] = level.most(squared(level.x, level.of(mean[here])))
        v, lo, hi = _along(level, dim[here]), level.of(low[here]), level.of(high[here])
        inside = (v >= lo) & (v <= hi)
        seg, v = np.broadcast_to(level.seg, len(v))[inside], v[inside]
        lo, hi = low[here][seg], high[here][seg]
        cell = seg * BINS + np.minimum(BINS - 1, ((v - lo) / np.where(hi > lo, hi - lo, 1.0) * BINS).astype(np.int64))
        order = np.argsort(cell, kind="stable")
        cell, v = cell[order], v[order]
        first = np.nonzero(np.concatenate([[True], cell[1:] != cell[:-1]]))[0] if len(cell) else np.empty(0, np.int64)
        if len(first):
            i, j = here[cell[first] // BINS], cell[first] % BINS
            out["n"][i, j] = np.diff(np.append(first, len(cell)))
            out["low"][i, j], out["high"][i, j] = np.minimum.reduceat(v, first), np.maximum.reduceat(v, first)
    return out


def _binned(a: dict, b: dict) -> dict:
    return {"n": a["n"] + b["n"]} | _wider(a, b)


# --- the top --------------------------------------------------------------------------------------------


def _medians(blocks: Blocks, source: _Source, ids: np.ndarray, dim: np.ndarray, n: np.ndarray, low: np.ndarray, high: np.ndarray, mean: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(cut, largest squared distance from ``mean``) of each node: for both middle ranks, the bin that has it is counted again until it is one value."""
    m, sums, far = len(ids), np.zeros(len(ids)), None
    for rank in ((n - 1) // 2, n // 2):
        a, b, before, todo = low.copy(), high.copy(), np.zeros(m, np.int64), np.ones(m, bool)
        if far is not None and (odd := n % 2 == 1).any():  # the same value twice
            a[odd] = b[odd] = first[odd]
        while (todo := a < b).any():
            some = np.nonzero(todo)[0]
            got = blocks.each(lambda name: _bins(source, name, ids[some], dim[some], a[some], b[some], mean[some] if far is None else None), combine=_binned)  # noqa: B023
            if far is None:
                far = np.zeros(m)
                far[some] = got["d"]
            upto = before[some, None] + got["n"].cumsum(axis=1)
            at = (upto > rank[some, None]).argmax(axis=1)
            i = np.arange(len(some))
            before[some] = upto[i, at] - got["n"][i, at]
            a[some], b[some] = got["low"][i, at], got["high"][i, at]
        first = a
        sums += a
    return sums / 2, far


def _cuts(blocks: Blocks, source: _Source, ids: np.ndarray, at: dict, cfg: BuildConfig) -> tuple[dict, np.ndarray, np.ndarray, np.ndarray]:
    """(cuts, radius, objective, whether they part the points) of some nodes whose moments are ``at``."""
    mean, m = at["mean"], len(ids)
    objective, parted = np.full(m, np.nan), np.ones(m, bool)
    if cfg.kind == "pab":
        axis = canonical(np.linalg.eigh(at["c"])[1][:, :, -1])
        extent = blocks.each(lambda name: _extents(source, name, ids, axis, mean), combine=_wider)
        cut = {"axis": axis, "t_min": extent["low"], "span": np.where(extent["high"] > extent["low"], extent["high"] - extent["low"], 1.0)}
        below = blocks.each(lambda name: _halves(source, name, ids, cut, cfg), combine=np.add).cumsum(axis=1)[:, ::2]
        share = (np.arange(cfg.sections) + 0.5) / cfg.sections
        f = np.abs(at["n"][:, None] - 2 * below) / at["n"][:, None] + cfg.alpha * offset_term(share, cfg.offset)
        cut["best"], objective = f.argmin(axis=1), f.min(axis=1)
        low = below[np.arange(m), cut["best"]]
        parted, far = (low > 0) & (low < at["n"]), extent["d"]
    elif cfg.kind == "fpb":
        one = blocks.each(lambda name: _farthest(source, name, ids, mean), combine=_farther)
        two = blocks.each(lambda name: _farthest(source, name, ids, one["x"]), combine=_farther)
        cut, far = {"one": one["x"], "two": two["x"]}, one["d"]
    else:
        dim = (at["high"] - at["low"]).argmax(axis=1)
        low = at["low"][np.arange(m), dim]
        value, far = _medians(blocks, source, ids, dim, at["n"], low, at["high"][np.arange(m), dim], mean)
        cut = {"dim": dim, "cut": value, "above": low >= value}
    return cut, np.sqrt(far) * (1 + SLACK), np.where(parted, objective, np.nan), parted


def _top(blocks: Blocks, cfg: BuildConfig, run: str) -> tuple[Top, _Source]:
    """The nodes of more than PART points and their children; the source knows the parts that points are in."""
    if other := [n for n, v in SPLITS.items() if getattr(cfg, n) != v]:
        raise ValueError(f"a whole tree is not split by another {', '.join(other)}")
    source, d = _Source(blocks.folder, run, blocks.dim), blocks.dim
    levels, kids, before, parent, cells = [], 1, 0, np.array([-1]), None
    while True:
        m = len(parent)
        ids, depth = before + np.arange(m, dtype=np.int64), source.depth
        at = blocks.each(lambda name: _moments(source, name, ids), combine=_moments_of_both)  # noqa: B023
        rows = {"parent": parent, "depth": np.full(m, depth), "n": at["n"], "lo": np.full(m, -1), "hi": np.full(m, -1), "center": at["mean"], "radius": np.zeros(m), "objective": np.full(m, np.nan), "axis": np.zeros((m, d)), "cut": np.zeros(m)}
        rows["box_lo"], rows["box_hi"] = cells or (at["low"], at["high"])
        rows["flat"] = (at["low"] >= at["high"]).all(axis=1)
        levels.append(rows)
        some = np.nonzero((at["n"] > max(PART, cfg.leaf_capacity)) & ~rows["flat"])[0] if depth < cfg.max_depth else np.empty(0, np.int64)
        if len(some):
            cut, radius, objective, parted = _cuts(blocks, source, ids[some], {n: v[some] for n, v in at.items()}, cfg)
            some, cut, rows["radius"][some], rows["objective"][some] = some[parted], {n: v[parted] for n, v in cut.items()}, radius, objective
        if not len(some):
            names = set().union(*levels)
            return Top(cfg.kind, **{n: np.concatenate([level[n] for level in levels]) for n in names - {"axis", "cut"}}), source
        first = kids + 2 * np.arange(len(some))
        rows["lo"][some], rows["hi"][some] = first, first + 1
        if cfg.kind == "kdt":
            rows["axis"][some, cut["dim"]], rows["cut"][some] = 1, cut["cut"]
            cells = _cells(rows, some, cfg) if cfg.kd_bounds != "tight" else None
        blocks.each(lambda name: _moved(source, name, ids[some], cut, first, cfg))  # noqa: B023
        source = replace(source, depth=depth + 1)
        parent, before, kids = np.repeat(ids[some], 2), kids, kids + 2 * len(some)


def _dealt(blocks: Blocks, source: _Source, parts: np.ndarray) -> dict[int, list[tuple[str, int, int]]]:
    """Writes each block's points in the order of the parts; where the points of each part are."""

    def deal(name: str):
        order, here, level = source.level(name, parts)
        _write(f"{source.folder}/{source.run}/{name}.pid", level.pid)
        _write(f"{source.folder}/{source.run}/{name}.x", level.x)
        return [(int(parts[i]), name, int(a), int(a + n)) for i, a, n in zip(here, level.starts, level.n)]

    where: dict[int, list[tuple[str, int, int]]] = {int(part): [] for part in parts}
    for found in sorted(blocks.each(deal), key=lambda rows: rows[0][1]):
        for part, name, a, b in found:
            where[part].append((name, a, b))
    return where


def _subtrees(blocks: Blocks, cfg: BuildConfig, work: Callable, only: tuple[str, ...] | None, deepen: bool = True) -> tuple[Top, list]:
    """The top of the tree over the blocks' points, and ``work`` of (part, subtree) for each part, in a task each, the largest first."""
    run = uuid.uuid4().hex
    if blocks.n <= max(PART, cfg.leaf_capacity):  # the tree is one part, whose task finds its root's ball
        d = blocks.dim
        none = {"parent": np.array([-1]), "lo": np.array([-1]), "hi": np.array([-1]), "depth": np.zeros(1, np.int64), "n": np.array([blocks.n])}
        top = Top(cfg.kind, **none, center=np.zeros((1, d)), radius=np.zeros(1), box_lo=np.zeros((1, d)), box_hi=np.zeros((1, d)), objective=np.full(1, np.nan), flat=np.zeros(1, bool))
        where, folder, corners = {0: [(name, 0, n) for name, n in blocks.names]}, blocks.folder, False
    else:
        top, source = _top(blocks, cfg, run)
        parts = np.nonzero(top.lo < 0)[0]
        where, folder, corners = _dealt(blocks, source, parts), f"{blocks.folder}/{run}", cfg.kind == "kdt" and cfg.kd_bounds != "tight"
    todo = sorted(((part, slices, int(top.depth[part]), (top.box_lo[part, None], top.box_hi[part, None]) if corners else None) for part, slices in where.items()), key=lambda p: -top.n[p[0]])
    dim = blocks.dim

    def built(given):
        for part, slices, depth, cells in given:
            pid = np.concatenate([_read(f"{folder}/{name}.pid", np.int64, a, b) for name, a, b in slices])
            x = np.concatenate([_read(f"{folder}/{name}.x", np.float64, a * dim, b * dim) for name, a, b in slices]).reshape(-1, dim)
            held = [pid, x]
            del pid, x
            yield work(part, grown(held, cfg, only, depth, cells))

    found = blocks.spark.sparkContext.parallelize(todo, max(1, len(todo))).mapPartitions(built).collect()
    dropped(blocks.spark, f"{blocks.folder}/{run}")
    return top, found


def whole_depth(blocks: Blocks, cfg: BuildConfig) -> Depths:
    """Depths of the leaves of one tree over all the points, counted in the tasks that build its subtrees; no tree is written."""
    from .stats import COUNTED, _depths_of

    def counted(part: int, t: Tree) -> np.ndarray:
        return _depths_of(t, part)[["depth", "leaves", "points"]].to_numpy()

    depth, leaves, points = (int_ for int_ in np.concatenate(_subtrees(blocks, cfg, counted, COUNTED)[1]).T.astype(np.int64))
    n, m = int(points.sum()), int(leaves.sum())
    return Depths(n, m, int((depth * leaves).sum()) / m, int((depth * points).sum()) / n, int(depth.max()))


def whole_tree(blocks: Blocks, cfg: BuildConfig, scale=None, only: tuple[str, ...] | None = None) -> SpatialIndex:
    """An index of one tree over all the points: its parts are the subtrees, and ``top`` the nodes above them."""
    folder = shared_dir(blocks.spark)

    def kept(part: int, t: Tree) -> tuple:
        return part, len(t.pid), t.center[0].tolist(), float(t.radius[0]), t.box_lo[0].tolist(), t.box_hi[0].tolist(), bytearray(t.stored(folder, f"{part}-{uuid.uuid4().hex}", 0))

    top, rows = _subtrees(blocks, cfg, kept, only)
    for part, _, center, radius, low, high, _ in rows:  # the ball of a part is that of its subtree
        top.center[part], top.radius[part], top.box_lo[part], top.box_hi[part] = center, radius, low, high
    top.tree = {row[0]: bytes(row[-1]) for row in rows}
    parts = blocks.spark.createDataFrame(rows, PARTS)
    return SpatialIndex(parts, blocks.dim, cfg, scale, blocks.n, len(rows), places=(folder,), top=top)
