"""Trees over the points of one partition: built a level at a time, searched a query at a time.

All nodes of a level are split together by segment operations over points kept in node order, so a
node's points are always one range. Distances are summed strictly in the order of dimensions, as the
column functions do, and answers are ordered by (distance, pid).
"""

from __future__ import annotations

import heapq
import io
import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
from pyarrow import fs

from ballspark.config import BuildConfig

#: Bytes of a tree from which on it is a file of its own in the shared folder, and how the bytes begin that say where.
FILED, PLACE = 1 << 20, b"tree at "
#: Cells of a histogram that are held at once; points of the nodes that are split together, or of one node: few enough for a core's caches.
CELLS, SPLIT = 1 << 18, 1 << 16
#: Relative slack of radii, so that rounding never prunes an answer.
SLACK = 1e-12


def squared(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Squared distances of rows, summed from the first dimension to the last."""
    out = np.zeros(len(x))
    for j in range(x.shape[1]):
        out += (x[:, j] - q[..., j]) ** 2
    return out


@dataclass
class Tree:
    kind: str
    x: np.ndarray
    pid: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    parent: np.ndarray
    depth: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    center: np.ndarray
    radius: np.ndarray
    axis: np.ndarray
    cut: np.ndarray
    t_min: np.ndarray
    t_max: np.ndarray
    objective: np.ndarray
    box_lo: np.ndarray
    box_hi: np.ndarray
    pivot_lo: np.ndarray
    pivot_hi: np.ndarray
    lists: dict = field(default_factory=dict, repr=False)

    ARRAYS = ("x", "pid", "lo", "hi", "parent", "depth", "begin", "end", "center", "radius", "axis", "cut", "t_min", "t_max", "objective", "box_lo", "box_hi", "pivot_lo", "pivot_hi")

    def to_bytes(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, kind=np.array(self.kind), **{n: getattr(self, n) for n in self.ARRAYS})
        return out.getvalue()

    def stored(self, folder: str, name: str, least: int | None = None) -> bytes:
        """``to_bytes`` of a small tree; one of ``least`` (FILED) bytes is written below ``folder``, and the bytes say where."""
        if sum(getattr(self, n).nbytes for n in self.ARRAYS) < (FILED if least is None else least):
            return self.to_bytes()
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base)
        with store.open_output_stream(f"{base}/{name}.npz", compression=None) as out:
            np.savez(out, kind=np.array(self.kind), **{n: getattr(self, n) for n in self.ARRAYS})
        return PLACE + f"{folder}/{name}.npz".encode()

    @classmethod
    def from_bytes(cls, data: bytes, only: tuple[str, ...] | None = None) -> Tree:
        """The tree of ``to_bytes`` or ``stored``; with ``only`` the other arrays are empty and not read."""
        if data.startswith(PLACE):
            store, path = fs.FileSystem.from_uri(data[len(PLACE) :].decode())
            with store.open_input_file(path) as f:
                return cls._read(f, only)
        return cls._read(io.BytesIO(data), only)

    @classmethod
    def _read(cls, file, only: tuple[str, ...] | None) -> Tree:
        with np.load(file) as z:
            return cls(kind=str(z["kind"]), **{n: z[n] if only is None or n in only else np.empty(0) for n in cls.ARRAYS})

    def plain(self) -> dict:
        """Node arrays as Python lists, which single look-ups are faster on."""
        if not self.lists:
            self.lists = {n: getattr(self, n).tolist() for n in ("lo", "hi", "begin", "end", "center", "radius", "box_lo", "box_hi")}
        return self.lists


@dataclass
class Top:
    """The nodes above the parts of one tree, whose leaves are the roots of the parts' trees; ``tree`` has the bytes of those, by node."""

    kind: str
    parent: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    depth: np.ndarray
    n: np.ndarray
    center: np.ndarray
    radius: np.ndarray
    box_lo: np.ndarray
    box_hi: np.ndarray
    objective: np.ndarray
    flat: np.ndarray
    tree: dict = field(default_factory=dict, repr=False)

    def part(self, node: int) -> Tree:
        return Tree.from_bytes(self.tree[node], WALKED[self.kind])


#: Arrays that searches for counters read.
WALKED = {kind: ("x", "lo", "hi", "begin", "end", "center", "radius", *(("box_lo", "box_hi") if kind == "kdt" else ())) for kind in ("pab", "fpb", "kdt")}


class _Level:
    """The nodes of one level that hold points, with the points in node order."""

    def __init__(self, x: np.ndarray, pid: np.ndarray, begin: np.ndarray, end: np.ndarray):
        self.n = end - begin
        self.starts = np.concatenate([[0], np.cumsum(self.n)[:-1]])
        # one node, which may have all points, takes no place for what is the same at each
        self.seg = np.repeat(np.arange(len(self.n)), self.n) if len(self.n) > 1 else np.broadcast_to(np.int64(0), self.n)
        # nodes side by side, as on the upper levels, are seen in place instead of copied
        self.at = slice(begin[0], end[-1]) if (begin[1:] == end[:-1]).all() else np.arange(self.n.sum()) + np.repeat(begin - self.starts, self.n)
        self.x, self.pid = x[self.at], pid[self.at]

    def of(self, v: np.ndarray) -> np.ndarray:
        """The nodes' values beside their points."""
        return v[self.seg] if len(self.n) > 1 else v

    def sides(self, side: np.ndarray) -> np.ndarray:
        """Places of the points by node and side, in their order."""
        return np.argsort(self.seg * 2 + side if len(self.n) > 1 else side, kind="stable")

    def total(self, v: np.ndarray) -> np.ndarray:
        return np.add.reduceat(v, self.starts, axis=0)

    def least(self, v: np.ndarray) -> np.ndarray:
        return np.minimum.reduceat(v, self.starts, axis=0)

    def most(self, v: np.ndarray) -> np.ndarray:
        return np.maximum.reduceat(v, self.starts, axis=0)

    def farthest(self, d: np.ndarray) -> np.ndarray:
        """Position of each node's point with the largest value; the smallest pid among equals."""
        top = d == self.of(self.most(d))
        pid = self.least(np.where(top, self.pid, np.iinfo(np.int64).max))
        hit = np.nonzero(top & (self.pid == self.of(pid)))[0]
        return hit[np.unique(self.seg[hit], return_index=True)[1]]


def canonical(w: np.ndarray) -> np.ndarray:
    """Rows with the sign that makes their largest component positive; the lowest dimension among equals."""
    size = np.abs(w)
    lead = np.argmax(size >= size.max(axis=1, keepdims=True) * (1 - 1e-9), axis=1)
    return w * np.where(w[np.arange(len(w)), lead] < 0, -1.0, 1.0)[:, None]


def _first_axis(c: np.ndarray, level: _Level, solver: str) -> np.ndarray:
    d = c.shape[1]
    if solver == "power":
        w = np.ones((len(level.n), d)) / math.sqrt(d) + np.arange(d) * 1e-3
        for _ in range(60):
            t = np.einsum("ij,ij->i", c, w[level.seg])
            w = level.total(c * t[:, None])
            norm = np.linalg.norm(w, axis=1, keepdims=True)
            w = np.where(norm > 0, w / np.where(norm > 0, norm, 1), 1 / math.sqrt(d))
        return canonical(w)
    m = np.empty((len(level.n), d, d))
    for i in range(d):
        for j in range(i, d):
            m[:, i, j] = m[:, j, i] = level.total(c[:, i] * c[:, j])
    return canonical(np.linalg.eigh(m)[1][:, :, -1])


def _project(level: _Level, w: np.ndarray) -> np.ndarray:
    t = np.zeros(len(level.x))
    for j in range(level.x.shape[1]):
        t += level.x[:, j] * level.of(w[:, j])
    return t


def offset_term(share: np.ndarray, mode: str) -> np.ndarray:
    """Of a cut at that share of the way from t_min to t_max."""
    return np.abs(2 * share - 1) if mode == "centred" else share


def _pab(level: _Level, center: np.ndarray, cfg: BuildConfig) -> tuple[np.ndarray, dict]:
    w = _first_axis(level.x - level.of(center) if cfg.axis == "covariance" else level.x, level, cfg.axis_solver)
    t = _project(level, w)
    t_min, t_max = level.least(t), level.most(t)
    if cfg.axis == "gram" and (flat := t_max <= t_min).any():
        w = np.where(flat[:, None], _first_axis(level.x - level.of(center), level, cfg.axis_solver), w)
        t = _project(level, w)
        t_min, t_max = level.least(t), level.most(t)
    span = np.where(t_max > t_min, t_max - t_min, 1.0)
    if cfg.cut == "exhaustive":
        hi, cut, objective = _every_gap(level, t, t_min, span, cfg)
    elif cfg.candidate == "data_mean":
        hi, cut, objective = _section_means(level, t, t_min, span, cfg)
    else:
        hi, cut, objective = _midpoints(level, t, t_min, span, cfg)
    return hi, {"axis": w, "cut": cut, "t_min": t_min, "t_max": t_max, "objective": objective}


def _blocks(n_nodes: int, width: int):
    step = max(1, CELLS // width)
    return ((a, min(a + step, n_nodes)) for a in range(0, n_nodes, step))


def _midpoints(level: _Level, t: np.ndarray, t_min: np.ndarray, span: np.ndarray, cfg: BuildConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Counts in half-sections are exact at the midpoints of sections, so that the scan sees true counts."""
    s = cfg.sections
    half = np.clip(((t - level.of(t_min)) / level.of(span) * (2 * s)).astype(np.int64), 0, 2 * s - 1)
    share = (np.arange(s) + 0.5) / s
    best, objective = np.empty(len(level.n), np.int64), np.empty(len(level.n))
    for a, b in _blocks(len(level.n), 2 * s):
        i = slice(level.starts[a], level.starts[b] if b < len(level.n) else None)
        below = np.bincount((level.seg[i] - a) * (2 * s) + half[i], minlength=(b - a) * 2 * s).reshape(-1, 2 * s).cumsum(axis=1)[:, ::2]
        f = np.abs(level.n[a:b, None] - 2 * below) / level.n[a:b, None] + cfg.alpha * offset_term(share, cfg.offset)
        best[a:b] = f.argmin(axis=1)
        objective[a:b] = f.min(axis=1)
    # the side comes from the bin and not from comparing t again: counts and sides cannot disagree
    return half > 2 * best[level.seg], t_min + span * (best + 0.5) / s, objective


def _section_means(level: _Level, t: np.ndarray, t_min: np.ndarray, span: np.ndarray, cfg: BuildConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    s = cfg.sections
    section = np.clip(((t - t_min[level.seg]) / span[level.seg] * s).astype(np.int64), 0, s - 1)
    cut, objective = np.empty(len(level.n)), np.empty(len(level.n))
    for a, b in _blocks(len(level.n), s):
        i = slice(level.starts[a], level.starts[b] if b < len(level.n) else None)
        cell, size = (level.seg[i] - a) * s + section[i], (b - a) * s
        n = np.bincount(cell, minlength=size)
        mean = np.bincount(cell, weights=t[i], minlength=size) / np.maximum(n, 1)
        inside = np.bincount(cell, weights=t[i] < mean[cell], minlength=size)
        n, mean, inside = (v.reshape(-1, s) for v in (n, mean, inside))
        below = n.cumsum(axis=1) - n + inside
        share = (mean - t_min[a:b, None]) / span[a:b, None]
        f = np.where(n > 0, np.abs(level.n[a:b, None] - 2 * below) / level.n[a:b, None] + cfg.alpha * offset_term(share, cfg.offset), np.inf)
        k = f.argmin(axis=1)
        cut[a:b], objective[a:b] = mean[np.arange(b - a), k], f.min(axis=1)
    return t >= cut[level.seg], cut, objective


def _every_gap(level: _Level, t: np.ndarray, t_min: np.ndarray, span: np.ndarray, cfg: BuildConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    order = np.lexsort((t, level.seg))
    v = t[order]
    gap = np.nonzero((level.seg[:-1] == level.seg[1:]) & (v[:-1] < v[1:]))[0]
    seg, at = level.seg[gap], (v[gap] + v[gap + 1]) / 2
    below = gap - level.starts[seg] + 1
    f = np.abs(level.n[seg] - 2 * below) / level.n[seg] + cfg.alpha * offset_term((at - t_min[seg]) / span[seg], cfg.offset)
    cut, objective = t_min.copy(), np.zeros(len(level.n))
    if len(gap):
        first = np.lexsort((at, f, seg))
        owner, pick = np.unique(seg[first], return_index=True)
        cut[owner], objective[owner] = at[first][pick], f[first][pick]
    return t >= cut[level.seg], cut, objective


def _fpb(level: _Level, center: np.ndarray) -> tuple[np.ndarray, dict]:
    one = level.x[level.farthest(squared(level.x, level.of(center)))]
    to_one = squared(level.x, level.of(one))
    two = level.x[level.farthest(to_one)]
    return squared(level.x, level.of(two)) < to_one, {"pivot_lo": one, "pivot_hi": two}


def _kdt(level: _Level, lo: np.ndarray, hi: np.ndarray, center: np.ndarray, depth: int, cfg: BuildConfig) -> tuple[np.ndarray, dict]:
    d = level.x.shape[1]
    if cfg.kd_axis == "cycle":
        dim = np.full(len(level.n), depth % d)
        flat = hi[np.arange(len(dim)), dim] <= lo[np.arange(len(dim)), dim]
        dim = np.where(flat, np.argmax(hi - lo, axis=1), dim)
    elif cfg.kd_axis == "variance":
        dim = np.argmax(level.total((level.x - center[level.seg]) ** 2), axis=1)
    else:
        dim = np.argmax(hi - lo, axis=1)
    v = level.x[np.arange(len(level.x)), dim[level.seg]]
    if cfg.kd_cut == "median":
        s = v[np.lexsort((v, level.seg))]
        cut = (s[level.starts + (level.n - 1) // 2] + s[level.starts + level.n // 2]) / 2
    else:
        cut = (lo[np.arange(len(dim)), dim] + hi[np.arange(len(dim)), dim]) / 2
    side = v >= cut[level.seg]
    whole = level.total(side.astype(np.int64)) == level.n  # the cut is the least value: it then goes above it
    side = np.where(whole[level.seg], v > cut[level.seg], side)
    axis = np.zeros((len(dim), d))
    axis[np.arange(len(dim)), dim] = 1
    return side, {"axis": axis, "cut": cut}


def _balls(level: _Level, ball: str) -> tuple[np.ndarray, np.ndarray]:
    center = level.total(level.x) / level.n[:, None]
    radius = np.sqrt(level.most(squared(level.x, level.of(center))))
    if ball == "enclosing":  # steps towards the farthest point; the smaller ball is kept
        c = center.copy()
        for i in range(1, 41):
            far = level.x[level.farthest(squared(level.x, level.of(c)))]
            c += (far - c) / (i + 1)
            r = np.sqrt(level.most(squared(level.x, level.of(c))))
            center, radius = np.where((r < radius)[:, None], c, center), np.minimum(r, radius)
    return center, radius * (1 + SLACK)


def _cells(rows: dict, who: np.ndarray, cfg: BuildConfig) -> tuple[np.ndarray, np.ndarray]:
    """Lower and upper corners of the cells of the children of ``who``, lower sides first: the parent's cell cut, or the cut alone."""
    whole = cfg.kd_bounds == "plane"
    low = np.repeat(np.full_like(rows["box_lo"][who], -np.inf) if whole else rows["box_lo"][who], 2, axis=0)
    high = np.repeat(np.full_like(rows["box_hi"][who], np.inf) if whole else rows["box_hi"][who], 2, axis=0)
    dim, i = rows["axis"][who].argmax(axis=1), np.arange(len(who))
    high[2 * i, dim] = rows["cut"][who]
    low[2 * i + 1, dim] = rows["cut"][who]
    return low, high


def _together(sizes: np.ndarray) -> Iterator[slice]:
    """Runs of nodes with at most SPLIT points in all, or of one node."""
    ends, a = np.cumsum(sizes), 0
    while a < len(sizes):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + SPLIT, side="right")))
        yield slice(a, b)
        a = b


#: Arrays of nodes that a kind of tree has no values in.
UNUSED = {"pab": ("pivot_lo", "pivot_hi"), "kdt": ("pivot_lo", "pivot_hi"), "fpb": ("axis",)}


def _made(x: np.ndarray, pid: np.ndarray, nodes: dict, depth: int, first: int, kids: int, cells: tuple[np.ndarray, np.ndarray] | None, cfg: BuildConfig) -> tuple[dict, dict, tuple[np.ndarray, np.ndarray] | None]:
    """The rows of some nodes of a level, numbered from ``first``, whose points are put in the order of their sides; their children, numbered from ``kids``."""
    begin, end = nodes["begin"], nodes["end"]
    m, d = len(begin), x.shape[1]
    level = _Level(x, pid, begin, end)
    center, radius = _balls(level, cfg.ball)
    low, high = level.least(level.x), level.most(level.x)
    rows = nodes | {"depth": np.full(m, depth), "center": center, "radius": radius}
    rows["box_lo"], rows["box_hi"] = (low, high) if cells is None else cells
    for n in ("axis", "pivot_lo", "pivot_hi"):
        rows[n] = np.zeros((m, d))
    for n in ("cut", "t_min", "t_max", "objective"):
        rows[n] = np.full(m, np.nan)
    rows["lo"], rows["hi"] = np.full(m, -1), np.full(m, -1)
    sizes, level = level.n, None
    inner = np.nonzero((sizes > cfg.leaf_capacity) & (low < high).any(axis=1))[0] if depth < cfg.max_depth else np.empty(0, np.int64)
    if not len(inner):
        return rows, {n: np.empty(0, np.int64) for n in nodes}, None
    b, e = begin[inner], end[inner]
    part = _Level(x, pid, b, e)
    mean = part.total(part.x) / part.n[:, None]
    if cfg.kind == "pab":
        side, found = _pab(part, mean, cfg)
    elif cfg.kind == "fpb":
        side, found = _fpb(part, mean)
    else:
        side, found = _kdt(part, low[inner], high[inner], mean, depth, cfg)
    n_hi = part.total(side.astype(np.int64))
    split = (n_hi > 0) & (n_hi < part.n)
    order = part.sides(side & part.of(split))
    x[part.at], pid[part.at] = part.x[order], part.pid[order]
    for n, v in found.items():
        rows[n][inner[split]] = v[split]
    who, mid = inner[split], (e - n_hi)[split]
    k = np.arange(len(who))
    rows["lo"][who], rows["hi"][who] = kids + 2 * k, kids + 2 * k + 1
    below = {"parent": np.repeat(first + who, 2), "begin": np.stack([b[split], mid], axis=1).ravel(), "end": np.stack([mid, e[split]], axis=1).ravel()}
    return rows, below, _cells(rows, who, cfg) if cfg.kind == "kdt" and cfg.kd_bounds != "tight" else None


def build(x: np.ndarray, pid: np.ndarray, cfg: BuildConfig, own: bool = False, only: tuple[str, ...] | None = None, depth: int = 0, cells: tuple[np.ndarray, np.ndarray] | None = None) -> Tree:
    """A tree over all the points; none has no nodes. With ``own`` the arrays are the tree's from now on and not copied; with ``only`` the nodes' other arrays are empty and not kept.

    A subtree has the ``depth`` of its root and, where it has them, the ``cells`` of that.
    """
    x, pid = (np.require(v, kind, "CW") if own else np.array(v, kind) for v, kind in ((x, np.float64), (pid, np.int64)))
    x = x if x.ndim == 2 else x.reshape(len(pid), max(1, x.size // max(1, len(pid))))
    d, asked = x.shape[1], [n for n in Tree.ARRAYS[2:] if only is None or n in only]
    made = {n: [] for n in asked if n not in UNUSED[cfg.kind]}
    nodes, total = {"parent": np.array([-1]), "begin": np.zeros(1, np.int64), "end": np.array([len(pid)])}, 0
    while len(pid) and len(nodes["begin"]):
        kids, below, corners = total + len(nodes["begin"]), [], []
        for run in _together(nodes["end"] - nodes["begin"]):
            some = {n: v[run] for n, v in nodes.items()}
            rows, children, cut = _made(x, pid, some, depth, total + run.start, kids, cells and (cells[0][run], cells[1][run]), cfg)
            for n in made:
                made[n].append(rows[n])
            kids += len(children["begin"])
            below.append(children)
            if cut is not None:
                corners.append(cut)
        total += len(nodes["begin"])
        nodes = {n: np.concatenate([c[n] for c in below]) for n in nodes}
        cells = (np.concatenate([c[0] for c in corners]), np.concatenate([c[1] for c in corners])) if corners else None
        depth += 1
    shape = {"center": (0, d), "axis": (0, d), "box_lo": (0, d), "box_hi": (0, d), "pivot_lo": (0, d), "pivot_hi": (0, d)}
    arrays = {n: np.concatenate(v) if (v := made.pop(n)) else np.empty(shape.get(n, 0)) for n in list(made)}
    unused = {n: np.zeros((total, d)) for n in asked if n in UNUSED[cfg.kind]}
    return Tree(kind=cfg.kind, x=x, pid=pid, **{n: np.empty(0) for n in Tree.ARRAYS[2:] if n not in asked}, **arrays, **unused)


# --- searches -------------------------------------------------------------------------------------


@dataclass
class Trace:
    """Entered: the procedure was called on a node, rejected at once or not."""

    nodes_entered: int = 0
    nodes_expanded: int = 0
    leaves_scanned: int = 0
    points_compared: int = 0


def _gap(tree: Tree, p: dict, q: list[float]):
    """(function of a node: least distance of its region from q, function: distance of its centre)."""
    center, radius, dist = p["center"], p["radius"], math.dist
    if tree.kind == "kdt":
        low, high = p["box_lo"], p["box_hi"]

        def box(i: int) -> float:
            s = 0.0
            for a, b, v in zip(low[i], high[i], q):
                if v < a:
                    s += (a - v) ** 2
                elif v > b:
                    s += (v - b) ** 2
            return math.sqrt(s) * (1 - SLACK)

        return box, lambda i: dist(center[i], q)
    return (lambda i: max(0.0, dist(center[i], q) - radius[i])), (lambda i: dist(center[i], q))


def _scan(tree: Tree, p: dict, i: int, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    s = slice(p["begin"][i], p["end"][i])
    return squared(tree.x[s], q), tree.pid[s]


def range_kernel(tree: Tree, q: list[float], r: float, trace: Trace) -> list[tuple[float, int]]:
    """(squared distance, pid) of all points within r, the border included."""
    out: list[tuple[float, int]] = []
    if not len(tree.lo):
        return out
    p, array = tree.plain(), np.array(q, float)
    gap, _ = _gap(tree, p, q)
    stack = [0]
    while stack:
        i = stack.pop()
        trace.nodes_entered += 1
        if gap(i) > r:
            continue
        trace.nodes_expanded += 1
        if p["lo"][i] < 0:
            trace.leaves_scanned += 1
            d, pid = _scan(tree, p, i, array)
            trace.points_compared += len(d)
            inside = d <= r * r
            out += zip(d[inside].tolist(), pid[inside].tolist())
        else:
            stack += (p["hi"][i], p["lo"][i])
    return out


def count_kernel(tree: Tree, q: list[float], r: float, trace: Trace, first_only: bool = False) -> int:
    """How many points are within r; balls wholly inside are not entered further. With ``first_only`` at least one ends it."""
    if not len(tree.lo):
        return 0
    p, array, total = tree.plain(), np.array(q, float), 0
    gap, dist = _gap(tree, p, q)
    stack = [0]
    while stack and not (first_only and total):
        i = stack.pop()
        trace.nodes_entered += 1
        if gap(i) > r:
            continue
        trace.nodes_expanded += 1
        if dist(i) + p["radius"][i] <= r * (1 - 1e-9):
            total += p["end"][i] - p["begin"][i]
        elif p["lo"][i] < 0:
            trace.leaves_scanned += 1
            d, _ = _scan(tree, p, i, array)
            trace.points_compared += len(d)
            total += int((d <= r * r).sum())
        else:
            stack += (p["hi"][i], p["lo"][i])
    return total


def nearest_kernel(
    tree: Tree, q: list[float], k: int, r: float, trace: Trace, order: str = "near_first", prune: str = "either", carry_bound: bool = True, child_test: bool = True, ties: str = "pid",
    found: list[tuple[float, int]] | None = None,
) -> list[tuple[float, int]]:
    """The k nearest points within r as sorted (squared distance, pid); r may be infinite.

    ``order``: near_first, right_first (the lower side first) or best_first. ``prune``: either bound
    alone rejects a node, or only their conjunction does. ``found`` starts the list with answers from elsewhere.
    """
    best = [(-d, -pid) for d, pid in found or ()]  # a heap whose first is the worst
    heapq.heapify(best)
    if not len(tree.lo) or k < 1:
        return sorted((-d, -pid) for d, pid in best)
    p, array, r2 = tree.plain(), np.array(q, float), r * r
    gap, dist = _gap(tree, p, q)
    lo, hi, radius = p["lo"], p["hi"], p["radius"]

    def worst() -> float:
        return math.sqrt(-best[0][0]) * (1 + SLACK) if len(best) >= k else math.inf

    def rejected(bound: float) -> bool:
        far = bound >= worst() if ties == "any" else bound > worst()
        return (far or bound > r) if prune == "either" else (far and bound > r)

    def scan(i: int) -> None:
        trace.leaves_scanned += 1
        d, pid = _scan(tree, p, i, array)
        trace.points_compared += len(d)
        near = d <= (min(r2, -best[0][0]) if len(best) >= k else r2)
        for item in sorted(zip(d[near].tolist(), pid[near].tolist())):
            entry = (-item[0], -item[1])
            if len(best) < k:
                heapq.heappush(best, entry)
            elif entry > best[0]:
                heapq.heapreplace(best, entry)

    if order == "best_first":
        queue = [(gap(0), 0)]
        while queue:
            bound, i = heapq.heappop(queue)
            trace.nodes_entered += 1
            if rejected(bound):
                if prune == "either":
                    break
                continue
            trace.nodes_expanded += 1
            if lo[i] < 0:
                scan(i)
                continue
            for c in (lo[i], hi[i]):
                if not child_test or r == math.inf or gap(c) <= r:
                    heapq.heappush(queue, (max(bound, gap(c)) if carry_bound else gap(c), c))
        return sorted((-d, -pid) for d, pid in best)

    stack = [(0, gap(0))]
    while stack:
        i, bound = stack.pop()
        trace.nodes_entered += 1
        if rejected(bound):
            continue
        trace.nodes_expanded += 1
        if lo[i] < 0:
            scan(i)
            continue
        kids = [(lo[i], gap(lo[i])), (hi[i], gap(hi[i]))]
        if order == "near_first" and (kids[1][1], dist(kids[1][0])) < (kids[0][1], dist(kids[0][0])):
            kids.reverse()
        for c, g in reversed(kids):
            if not child_test or r == math.inf or g <= r:
                stack.append((c, max(bound, g) if carry_bound else g))
    return sorted((-d, -pid) for d, pid in best)


# --- searches of many queries at once -----------------------------------------------------------------

#: Points that are compared at once, queries that go through a tree together, and (query, node) pairs that are open at once.
COMPARED, TOGETHER, OPEN = 2_000_000, 4096, 1_000_000


def gaps(tree: Tree, q: np.ndarray, node: np.ndarray) -> np.ndarray:
    """Least distance of each node's region from the query beside it."""
    if tree.kind != "kdt":
        return np.maximum(0.0, np.sqrt(squared(tree.center[node], q)) - tree.radius[node])
    out = np.zeros(len(q))
    for j in range(q.shape[1]):
        out += np.maximum(0.0, np.maximum(tree.box_lo[node, j] - q[:, j], q[:, j] - tree.box_hi[node, j])) ** 2
    return np.sqrt(out) * (1 - SLACK)


def opened(tree: Tree, q: np.ndarray, reach: np.ndarray, counts: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(query, leaf) pairs of the leaves within each query's reach: all queries go down together, a level a step, OPEN pairs at a time.

    ``counts`` takes, for each query, the nodes entered and expanded, the leaves and their points, and the answers below nodes that
    are wholly within reach: all below such a node is visited, so it is counted without going down, and its leaves are not among the pairs.
    """
    if counts is not None:
        leaves_at = np.sort(tree.begin[tree.lo < 0])
    stack = [(np.arange(len(q)), np.zeros(len(q), np.int64))] if len(tree.lo) else []
    while stack:
        who, node = stack.pop()
        if len(who) > OPEN:
            stack += [(who[i : i + OPEN], node[i : i + OPEN]) for i in range(0, len(who), OPEN)]
            continue
        near = gaps(tree, q[who], node) <= reach[who]
        inside, at = who[near], node[near]
        if counts is not None:
            counts[0] += np.bincount(who, minlength=len(q))
            whole = np.sqrt(squared(tree.center[at], q[inside])) + tree.radius[at] <= reach[inside] * (1 - 1e-9)
            (of, begin, end), inside, at = (v[whole] for v in (inside, tree.begin[at], tree.end[at])), inside[~whole], at[~whole]
            below, points = np.searchsorted(leaves_at, end) - np.searchsorted(leaves_at, begin), end - begin
            for i, n in enumerate((2 * below - 2, 2 * below - 1, below, points, points)):
                counts[i] += np.bincount(of, n, len(q)).astype(np.int64)
        leaf = tree.lo[at] < 0
        if counts is not None:
            for i, some in enumerate((inside, inside[leaf])):
                counts[1 + i] += np.bincount(some, minlength=len(q))
        if leaf.any():
            yield inside[leaf], at[leaf]
        if not leaf.all():
            stack.append((np.repeat(inside[~leaf], 2), np.stack([tree.lo[at[~leaf]], tree.hi[at[~leaf]]], axis=1).ravel()))


def open_leaves(tree: Tree, q: np.ndarray, reach: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All pairs that ``opened`` finds."""
    found = [(np.empty(0, np.int64), np.empty(0, np.int64)), *opened(tree, q, reach)]
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


def nearer_path(tree: Tree, q: np.ndarray, least: np.ndarray):
    """The nodes on each query's way to the nearer child, as long as that has ``least`` points: arrays, the last being where it ends."""
    node = np.zeros(len(q), np.int64)
    while True:
        yield node
        on = np.nonzero(tree.lo[node] >= 0)[0]
        lo, hi = tree.lo[node[on]], tree.hi[node[on]]
        a, b = gaps(tree, q[on], lo), gaps(tree, q[on], hi)
        right = (b < a) | (a == b) & (squared(tree.center[hi], q[on]) < squared(tree.center[lo], q[on]))
        child = np.where(right, hi, lo)
        enough = tree.end[child] - tree.begin[child] >= least[on]
        if not enough.any():
            return
        node = node.copy()
        node[on[enough]] = child[enough]


def compared(tree: Tree, q: np.ndarray, who: np.ndarray, node: np.ndarray):
    """(query, place of the point, squared distance) of all points of the (query, node) pairs, some pairs at a time."""
    sizes = tree.end[node] - tree.begin[node]
    total = np.cumsum(sizes)
    begin = 0
    while begin < len(who):
        before = total[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(total, before + COMPARED, side="right")))
        n = sizes[begin:end]
        at = np.repeat(tree.begin[node[begin:end]] - (total[begin:end] - n - before), n) + np.arange(n.sum())
        of = np.repeat(who[begin:end], n)
        yield of, at, squared(tree.x[at], q[of])
        begin = end


def range_together(tree: Tree, q: np.ndarray, r: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(query, pid, squared distance) of all points within each query's r, the border included, in portions."""
    for a in range(0, len(q), TOGETHER):
        some, reach = q[a : a + TOGETHER], r[a : a + TOGETHER]
        for who, leaf in opened(tree, some, reach):
            for of, at, d2 in compared(tree, some, who, leaf):
                inside = d2 <= reach[of] * reach[of]
                yield a + of[inside], tree.pid[at[inside]], d2[inside]


def range_traces(tree: Tree, q: np.ndarray, r: np.ndarray) -> np.ndarray:
    """A row for each query: its answers and the counters of ``range_kernel``, whose visits don't depend on their order."""
    out = np.zeros((len(q), 5), np.int64)
    for a in range(0, len(q), TOGETHER):
        some, reach = q[a : a + TOGETHER], r[a : a + TOGETHER]
        counts = np.zeros((5, len(some)), np.int64)
        for who, leaf in opened(tree, some, reach, counts):
            for of, _, d2 in compared(tree, some, who, leaf):
                counts[3] += np.bincount(of, minlength=len(some))
                counts[4] += np.bincount(of[d2 <= reach[of] * reach[of]], minlength=len(some))
        out[a : a + TOGETHER] = np.stack([counts[4], *counts[:4]], axis=1)
    return out


def nearest_together(tree: Tree, q: np.ndarray, k: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, pid, squared distance) of the k nearest within r of each query, ties by pid: what ``nearest_kernel`` finds.

    The k-th distance in the smallest node on the nearer path that has k points bounds, with r, what is then visited.
    """
    out = [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))]
    for a in range(0, len(q) if len(tree.lo) else 0, TOGETHER):
        some, least, reach = q[a : a + TOGETHER], k[a : a + TOGETHER], r[a : a + TOGETHER].astype(float)
        *_, node = nearer_path(tree, some, least)
        bound = np.full(len(some), np.inf)
        for of, _, d2 in compared(tree, some, np.arange(len(some)), node):  # a pair's points come together
            order = np.lexsort((d2, of))
            first = np.searchsorted(of, np.arange(len(some)))
            n = np.bincount(of, minlength=len(some))
            full = (n >= least) & (n > 0)
            bound[full] = d2[order][(first + least - 1)[full]]
        reach = np.minimum(reach, np.sqrt(bound) * (1 + SLACK))
        limit = np.minimum(bound, r[a : a + TOGETHER].astype(float) ** 2)
        kept = [(o[:0], o[:0], d[:0]) for o, d in [(np.empty(0, np.int64), np.empty(0))]]
        for who, leaf in opened(tree, some, reach):
            for of, at, d2 in compared(tree, some, who, leaf):
                near = d2 <= limit[of]
                kept.append((of[near], tree.pid[at[near]], d2[near]))
        of, pid, d2 = (np.concatenate([x[i] for x in kept]) for i in range(3))
        order = np.lexsort((pid, d2, of))
        of, pid, d2 = of[order], pid[order], d2[order]
        first = np.searchsorted(of, np.arange(len(some)))
        top = np.arange(len(of)) - first[of] < least[of]
        out.append((a + of[top], pid[top], d2[top]))
    return tuple(np.concatenate([o[i] for o in out]) for i in range(3))


def nearest_traces(tree: Tree, q: np.ndarray, k: np.ndarray, r: np.ndarray, order: str = "near_first") -> np.ndarray:
    """A row for each query: its answers and the counters of ``nearest_kernel`` in that order, other options being the default ones.

    Each query has a stack of its own; all take a step at a time, in arrays.
    """
    out = np.zeros((len(q), 5), np.int64)
    for a in range(0, len(q) if len(tree.lo) else 0, TOGETHER):
        out[a : a + TOGETHER] = _traced(tree, q[a : a + TOGETHER], k[a : a + TOGETHER], r[a : a + TOGETHER].astype(float), order)
    return out


def _stacked(tree: Tree | Top, q: np.ndarray, r: np.ndarray, order: str, who: np.ndarray, at: np.ndarray, reach: np.ndarray, node: np.ndarray, bound: np.ndarray, top: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The queries' stacks with the children of the nodes that they are at, the one that is visited first on top."""
    first, second = tree.lo[at], tree.hi[at]
    g, h = gaps(tree, q[who], first), gaps(tree, q[who], second)
    if order == "near_first":
        swap = h < g
        if (tie := np.nonzero(h == g)[0]).size:
            swap[tie] = squared(tree.center[second[tie]], q[who[tie]]) < squared(tree.center[first[tie]], q[who[tie]])
        first, second, g, h = np.where(swap, second, first), np.where(swap, first, second), np.where(swap, h, g), np.where(swap, g, h)
    for child, gap in ((second, h), (first, g)):
        inside = gap <= r[who]
        i = who[inside]
        if len(i) and top[i].max() >= node.shape[1]:
            node, bound = np.pad(node, ((0, 0), (0, 64))), np.pad(bound, ((0, 0), (0, 64)))
        node[i, top[i]], bound[i, top[i]] = child[inside], np.maximum(reach, gap)[inside]
        top[i] += 1
    return node, bound


def _traced(tree: Tree, q: np.ndarray, k: np.ndarray, r: np.ndarray, order: str, near: np.ndarray | None = None, carried: np.ndarray | None = None) -> np.ndarray:
    """``near``, the nearest squared distances so far, is taken and brought up to date; ``carried`` is the bound that the root comes with."""
    m, every = len(q), np.arange(len(q))
    entered, expanded, leaves, points = np.zeros((4, m), np.int64)
    # the nearest distances in order, and what they and r leave to reach; which of equally distant points they are of changes no counter
    best = np.full((m, k.max()), np.inf) if near is None else near
    worst = np.minimum(np.sqrt(best[every, np.maximum(k, 1) - 1]) * (1 + SLACK), r)
    node, bound, top = np.zeros((m, 64), np.int64), np.zeros((m, 64)), np.ones(m, np.int64)
    bound[:, 0] = gaps(tree, q, node[:, 0]) if carried is None else carried
    on = every[k > 0]
    while len(on):
        top[on] -= 1
        at, reach = node[on, top[on]], bound[on, top[on]]
        entered[on] += 1
        kept = reach <= worst[on]
        who, at, reach = on[kept], at[kept], reach[kept]
        expanded[who] += 1
        leaf = tree.lo[at] < 0
        if leaf.any():
            here, of = who[leaf], at[leaf]
            n = tree.end[of] - tree.begin[of]
            leaves[here] += 1
            points[here] += n
            # leaves of about one size together, so that little is padded
            for width in np.unique(size := 1 << np.ceil(np.log2(n)).astype(np.int64)):
                for some in np.split(np.nonzero(size == width)[0], np.arange(step := max(1, COMPARED // int(width)), (size == width).sum(), step)):
                    i, place = here[some], tree.begin[of[some], None] + np.arange(width)
                    there = place < tree.end[of[some], None]
                    place = np.where(there, place, 0)
                    d2 = np.zeros(place.shape)
                    for j in range(q.shape[1]):
                        d2 += (tree.x[place, j] - q[i, j, None]) ** 2
                    d2[~there | (d2 > (r[i] * r[i])[:, None])] = np.inf
                    closer = d2.min(axis=1) < best[i, k[i] - 1]  # most leaves change nothing, and rows are merged where they do
                    if closer.any():
                        i = i[closer]
                        best[i] = np.sort(np.concatenate([best[i], d2[closer]], axis=1), axis=1)[:, : best.shape[1]]
                        worst[i] = np.minimum(np.sqrt(best[i, k[i] - 1]) * (1 + SLACK), r[i])
        who, at, reach = who[~leaf], at[~leaf], reach[~leaf]
        node, bound = _stacked(tree, q, r, order, who, at, reach, node, bound, top)
        on = on[top[on] > 0]
    answers = ((best < np.inf) & (np.arange(best.shape[1]) < k[:, None])).sum(axis=1)
    return np.stack([answers, entered, expanded, leaves, points], axis=1)


# --- the same over a tree of several parts ------------------------------------------------------------


def range_traces_of_parts(top: Top, q: np.ndarray, r: np.ndarray) -> np.ndarray:
    """``range_traces`` of the whole tree: through the nodes above the parts, then a part after another."""
    out = np.zeros((len(q), 5), np.int64)
    who, node, met = np.arange(len(q)), np.zeros(len(q), np.int64), []
    while len(who):
        part = top.lo[node] < 0
        met.append((who[part], node[part]))
        who, node = who[~part], node[~part]
        near = gaps(top, q[who], node) <= r[who]
        out[:, 1] += np.bincount(who, minlength=len(q))
        who, node = who[near], node[near]
        out[:, 2] += np.bincount(who, minlength=len(q))
        who, node = np.repeat(who, 2), np.stack([top.lo[node], top.hi[node]], axis=1).ravel()
    who, node = (np.concatenate([m[i] for m in met]) for i in (0, 1)) if met else (who, node)
    near = gaps(top, q[who], node) <= r[who]
    out[:, 1] += np.bincount(who[~near], minlength=len(q))  # parts whose roots are rejected
    who, node = who[near], node[near]
    for part in np.unique(node):
        some = who[node == part]
        out[some] += range_traces(top.part(part), q[some], r[some])
    return out


def nearest_traces_of_parts(top: Top, q: np.ndarray, k: np.ndarray, r: np.ndarray, order: str = "near_first") -> np.ndarray:
    """``nearest_traces`` of the whole tree: each query goes its own way and waits at a part's root until that part is read; of the parts the one that most wait for is next."""
    out, r = np.zeros((len(q), 5), np.int64), r.astype(float)
    if not len(q):
        return out
    best, worst = np.full((len(q), k.max()), np.inf), r.copy()
    node, bound, height = np.zeros((len(q), 64), np.int64), np.zeros((len(q), 64)), (k > 0).astype(np.int64)
    bound[:, 0] = gaps(top, q, node[:, 0])
    waits, carried = np.full(len(q), -1), np.zeros(len(q))
    on = np.nonzero(height)[0]
    while True:
        while len(on):
            height[on] -= 1
            at, reach = node[on, height[on]], bound[on, height[on]]
            kept = reach <= worst[on]
            stop = kept & (top.lo[at] < 0)
            waits[on[stop]], carried[on[stop]] = at[stop], reach[stop]
            out[on[~stop], 1] += 1  # a part's root is counted there
            down = kept & ~stop
            out[on[down], 2] += 1
            node, bound = _stacked(top, q, r, order, on[down], at[down], reach[down], node, bound, height)
            on = on[~stop]
            on = on[height[on] > 0]
        if not (waiting := waits[waits >= 0]).size:
            break
        part = np.bincount(waiting).argmax()
        tree, there = top.part(part), np.nonzero(waits == part)[0]
        for a in range(0, len(there), TOGETHER):
            some = there[a : a + TOGETHER]
            near = best[some]
            out[some, 1:] += _traced(tree, q[some], k[some], r[some], order, near, carried[some])[:, 1:]
            best[some] = near
        tree = None
        worst[there] = np.minimum(np.sqrt(best[there, k[there] - 1]) * (1 + SLACK), r[there])
        waits[there] = -1
        on = there[height[there] > 0]
    out[:, 0] = ((best < np.inf) & (np.arange(best.shape[1]) < k[:, None])).sum(axis=1)
    return out
