"""The spatial index: parts with their trees, as a relation, and its construction.

A part is a bounded share of the points with a tree over it. Its row has what routing needs (ball,
box, count) in columns and the tree's arrays in one binary column, so the metadata of all parts is
read without the trees, and a search reads the trees of only those parts that its queries can meet.
``nodes`` and ``leaf_points`` show the trees as plain relations.
"""

from __future__ import annotations

import json
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ballspark.config import BuildConfig
from ballspark.functions.geometry import project
from ballspark.schema import LEAF_POINTS, NODES, PARTS
from ballspark.sources.points import Points, Scale

from .kernel import PLACE, Top, Tree, build
from .routing import Routing
from .routing import matrix as _matrix


def shared_dir(spark: SparkSession) -> str:
    """A new folder below the one that the cluster shares for checkpoints; of this machine only where none is named."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        root = f"file://{tempfile.mkdtemp(prefix='ballspark-')}"
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


def saved(df: DataFrame, path: str | None = None) -> DataFrame:
    """``df`` written to the shared folder, or to ``path``, and read again."""
    path = path or shared_dir(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(spark: SparkSession, place: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(place)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


@dataclass
class SpatialIndex:
    parts: DataFrame
    dim: int
    config: BuildConfig
    scale: Scale | None = None
    n: int = 0
    n_parts: int = 0
    #: Rows of a rotation that the points went through, and that queries go through.
    rotation: tuple[tuple[float, ...], ...] | None = None
    made: Routing | None = field(default=None, repr=False, compare=False)
    #: Where its parts and trees were written when it was built.
    places: tuple[str, ...] = field(default=(), repr=False, compare=False)
    #: The nodes above the parts, where these are subtrees of one tree.
    top: Top | None = field(default=None, repr=False, compare=False)

    def scaled(self, queries: DataFrame) -> DataFrame:
        """Queries in the units of the source, brought to the index's scale."""
        return queries.withColumn("q", self.scale.apply(F.col("q"))) if self.scale else queries

    def turned(self, queries: DataFrame) -> DataFrame:
        """Queries in the index's scale, turned as its points were."""
        return queries.withColumn("q", F.array(*[project(F.col("q"), list(w)) for w in self.rotation])) if self.rotation else queries

    @property
    def spark(self) -> SparkSession:
        return self.parts.sparkSession

    def summaries(self) -> DataFrame:
        """What routing needs of every part, without the trees."""
        return self.parts.drop("tree")

    def routing(self) -> Routing:
        """The routers of the parts, made at the first search."""
        if self.made is None:
            self.made = Routing(self.parts, self.n_parts, self.config.kind, self.config)
        return self.made

    def nodes(self) -> DataFrame:
        return self.parts.select("part_id", "tree").mapInPandas(_node_rows, NODES)

    def leaf_points(self) -> DataFrame:
        return self.parts.select("part_id", "tree").mapInPandas(_point_rows, LEAF_POINTS)

    def meta(self) -> DataFrame:
        row = (uuid.uuid4().hex, self.config.kind, self.dim, self.n, self.config.params(), list(self.scale.shift) if self.scale else None, list(self.scale.factor) if self.scale else None)
        return self.spark.createDataFrame([row], "tree_id string, kind string, dim int, n long, params map<string,string>, scale_shift array<double>, scale_factor array<double>")

    def register(self, name: str) -> None:
        """Temporary views for SQL: <name>_parts, <name>_nodes, <name>_points."""
        self.parts.drop("tree").createOrReplaceTempView(f"{name}_parts")
        self.nodes().createOrReplaceTempView(f"{name}_nodes")
        self.leaf_points().createOrReplaceTempView(f"{name}_points")

    def save(self, path: str) -> None:
        """Parts in ranges and the order of part_id under ``path``/parts, so that a filter on it skips files; the rest as one JSON row under ``path``/meta."""
        self.parts.mapInPandas(_whole, PARTS).repartitionByRange("part_id").sortWithinPartitions("part_id").write.mode("overwrite").parquet(f"{path}/parts")
        facts = {"dim": self.dim, "n": self.n, "n_parts": self.n_parts, "config": self.config.__dict__, "shift": self.scale and list(self.scale.shift), "factor": self.scale and list(self.scale.factor), "rotation": self.rotation}
        self.spark.createDataFrame([(json.dumps(facts),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> SpatialIndex:
        facts = json.loads(spark.read.text(f"{path}/meta").first().value)
        scale = Scale(tuple(facts["shift"]), tuple(facts["factor"])) if facts["shift"] else None
        return cls(spark.read.schema(PARTS).parquet(f"{path}/parts"), facts["dim"], BuildConfig(**facts["config"]), scale, facts["n"], facts["n_parts"], facts["rotation"] and tuple(map(tuple, facts["rotation"])))

    def drop(self) -> None:
        """Deletes what was written when it was built: neither it nor an index made from it is searched any more."""
        for place in self.places:
            dropped(self.spark, place)

    def append(self, points: DataFrame) -> SpatialIndex:
        """With further points, each added to the part whose centre is nearest; only those parts' trees are made again.

        A part that comes to have more than four times ``local_rows`` points is cut by pid. Points are
        expected in the index's scale. An empty index is built from the points.
        """
        if not self.n_parts:
            return build_tree(Points(points, self.dim, self.scale), self.config)
        points = self.turned(points.withColumnRenamed("x", "q")).withColumnRenamed("q", "x")
        added = self.routing().home(points, "x", nearest_center=True)
        touched = added.select("part_id").distinct()
        old = self.parts.join(touched, "part_id", "left_semi").select("part_id", "tree").mapInPandas(_point_rows, LEAF_POINTS)
        together = saved(old.select("part_id", "pid", "x").unionByName(added.select("part_id", "pid", "x")))
        top = self.parts.agg(F.max("part_id")).first()[0] + 1
        again = _local_trees(_cut_crowded(together, self.config, top), self.config)
        parts = saved(self.parts.join(touched, "part_id", "left_anti").unionByName(again))
        got = parts.agg(F.sum("n").alias("n"), F.count("*").alias("p")).first()
        return replace(self, parts=parts, n=got.n, n_parts=got.p, made=None, top=None)

    def compact(self, part_ids: list[int]) -> SpatialIndex:
        """The trees of those parts, made again as one tree a part of at most ``local_rows`` points."""
        some = F.col("part_id").isin(part_ids)
        points = self.parts.where(some).select("part_id", "tree").mapInPandas(_point_rows, LEAF_POINTS).select("pid", "x")
        fresh = build_tree(Points(points, self.dim, self.scale), self.config)
        top = self.parts.agg(F.max("part_id")).first()[0] + 1
        parts = saved(self.parts.where(~some).unionByName(fresh.parts.withColumn("part_id", (F.col("part_id") + top).cast("int"))))
        return replace(self, parts=parts, n_parts=parts.count(), made=None, top=None)


def _whole(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Trees that are files of their own as bytes, so that a saved index needs nothing beside it."""
    for batch in batches:
        yield batch.assign(tree=[Tree.from_bytes(data).to_bytes() if data.startswith(PLACE) else data for data in batch["tree"]])


def _node_rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        for part, data in zip(batch["part_id"], batch["tree"]):
            t = Tree.from_bytes(data)
            for a in range(0, len(t.lo), 65536):
                s = slice(a, a + 65536)
                m = len(t.lo[s])
                yield pd.DataFrame(
                    {"part_id": np.full(m, part, np.int32), "node_id": a + np.arange(m), "parent_id": t.parent[s], "lo_id": t.lo[s], "hi_id": t.hi[s], "depth": t.depth[s].astype(np.int32), "is_leaf": t.lo[s] < 0, "n": (t.end - t.begin)[s]}
                    | {c: list(getattr(t, c)[s]) for c in ("center", "axis", "box_lo", "box_hi", "pivot_lo", "pivot_hi")}
                    | {c: getattr(t, c)[s] for c in ("radius", "cut", "t_min", "t_max", "objective")}
                )


def _point_rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        for part, data in zip(batch["part_id"], batch["tree"]):
            t = Tree.from_bytes(data)
            leaf = np.nonzero(t.lo < 0)[0]
            leaf = leaf[np.argsort(t.begin[leaf])]
            ids = np.repeat(leaf, t.end[leaf] - t.begin[leaf])
            for a in range(0, len(ids), 65536):
                s = slice(a, a + 65536)
                yield pd.DataFrame({"part_id": np.full(len(ids[s]), part, np.int32), "leaf_id": ids[s], "pid": t.pid[s], "x": list(t.x[s])})


def vectors(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def gathered(batches: Iterator[pa.RecordBatch]) -> list[np.ndarray]:
    """pid and x of all the batches' points; nothing where there are none."""
    held = [(b["pid"].to_numpy().copy(), vectors(b["x"]).copy()) for b in batches if b.num_rows]
    return [np.concatenate([h[i] for h in held]) for i in (0, 1)] if held else []


def grown(held: list[np.ndarray], cfg: BuildConfig, only: tuple[str, ...] | None = None, depth: int = 0, cells: tuple[np.ndarray, np.ndarray] | None = None) -> Tree:
    """The tree over ``held``, pid and x; it is emptied, so that no copy of the points stays beside the tree's."""
    order = np.argsort(held[0], kind="stable")  # a tree must not depend on the order of arrival
    pid, x = held.pop(0)[order], held.pop()[order]
    return build(x, pid, cfg, own=True, only=only, depth=depth, cells=cells)


def in_one_task(points: Points) -> DataFrame:
    """(pid, x) in one partition: rows that are files already are read there, others are made in many tasks and shuffled."""
    rows = points.df.select("pid", "x")
    return rows.coalesce(1) if points.filed else rows.repartition(1)


def _local_trees(assigned: DataFrame, cfg: BuildConfig, single: bool = False, folder: str | None = None, only: tuple[str, ...] | None = None) -> DataFrame:
    """A tree for each part_id; ``single`` says that there is one only, whose points are in one partition and needn't be sorted. Large ones are files below ``folder``."""
    folder = folder or shared_dir(assigned.sparkSession)

    def tree(part: int, held: list[np.ndarray]) -> pa.RecordBatch:
        t = grown(held, cfg, only)
        row = {"part_id": part, "n": len(t.pid), "center": t.center[0].tolist(), "radius": t.radius[0], "box_lo": t.box_lo[0].tolist(), "box_hi": t.box_hi[0].tolist(), "tree": t.stored(folder, f"{part}-{uuid.uuid4().hex}")}
        return pa.RecordBatch.from_pylist([row], _ROW)

    def one(rows: pa.Table) -> pa.Table:
        x = np.concatenate([vectors(c) for c in rows["x"].chunks if len(c)])
        return pa.Table.from_batches([tree(rows["part_id"][0].as_py(), [rows["pid"].to_numpy(), x])])

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if held := gathered(batches):
            yield tree(0, held)

    if single:
        return assigned.select("pid", "x").mapInArrow(whole, PARTS)
    return assigned.groupBy("part_id").applyInArrow(one, PARTS)


_ROW = pa.schema([("part_id", pa.int32()), ("n", pa.int64()), ("center", pa.list_(pa.float64())), ("radius", pa.float64()), ("box_lo", pa.list_(pa.float64())), ("box_hi", pa.list_(pa.float64())), ("tree", pa.binary())])


def _cut_crowded(assigned: DataFrame, cfg: BuildConfig, top: int) -> DataFrame:
    """Points (part_id, pid, x), those of parts with more than four times ``local_rows`` dealt by pid to as many parts as they need, numbered from ``top`` on."""
    crowded = assigned.groupBy("part_id").count().where(F.col("count") > 4 * cfg.local_rows)
    over = crowded.withColumn("cuts", F.ceil(F.col("count") / cfg.local_rows)).select(F.col("part_id").alias("of"), "cuts")
    firsts = sorted((r.of, r.cuts) for r in over.collect())  # a few parts, of local_rows and more points each
    if not firsts:
        return assigned
    begin, rows = top, []
    for part, cuts in firsts:
        rows.append((part, cuts, begin))
        begin += cuts
    table = assigned.sparkSession.createDataFrame(rows, "part_id int, cuts long, first long")
    dealt = F.coalesce(F.col("first") + F.pmod(F.xxhash64("pid"), F.col("cuts")), F.col("part_id")).cast("int")
    return assigned.join(F.broadcast(table), "part_id", "left").select(dealt.alias("part_id"), "pid", "x")


def _top_tree_router(sample: pd.DataFrame, parts: int, cfg: BuildConfig):
    """A tree over a sample with about ``parts`` leaves, as a pandas UDF from points to leaf numbers."""
    x, pid = _matrix(sample["x"]), sample["pid"].to_numpy()
    order = np.argsort(pid, kind="stable")
    t = build(x[order], pid[order], replace(cfg, leaf_capacity=max(1, -(-len(pid) // parts))))
    leaf = t.lo < 0
    number = np.where(leaf, np.cumsum(leaf) - 1, -1)
    arrays = {n: getattr(t, n) for n in ("lo", "hi", "axis", "cut", "pivot_lo", "pivot_hi")}

    @F.pandas_udf("int")
    def route(points: pd.Series) -> pd.Series:
        p = _matrix(points)
        at = np.zeros(len(p), np.int64)
        while (inner := arrays["lo"][at] >= 0).any():
            i, q = at[inner], p[inner]
            if cfg.kind == "fpb":
                hi = ((q - arrays["pivot_hi"][i]) ** 2).sum(axis=1) < ((q - arrays["pivot_lo"][i]) ** 2).sum(axis=1)
            else:
                hi = np.einsum("ij,ij->i", q, arrays["axis"][i]) >= arrays["cut"][i]
            at[inner] = np.where(hi, arrays["hi"][i], arrays["lo"][i])
        return pd.Series(number[at])

    return route


def build_tree(points: Points, cfg: BuildConfig | None = None, n: int | None = None, transform: str | None = None, only: tuple[str, ...] | None = None) -> SpatialIndex:
    """An index over all points.

    Up to ``local_rows`` points are one part, if not more are asked for. More are dealt to parts first, as many as ``local_rows`` needs at least: by a tree over a bounded
    sample (the answers stay exact, as balls are made from all points), or, with top='exact', by
    splits over all points level by level. A part that got more than four times ``local_rows``
    (many equal points, an unlucky sample) is cut by pid, which is always correct for searches.

    With transform='pca' points and later queries are rotated to all components; distances stay the
    same up to rounding. (Fewer components are a filter, ``pca_filter_knn``.) With ``only``, such as
    ``search.SEARCHED``, trees have those arrays of their nodes and no others, and serve what reads those.
    """
    cfg = cfg or BuildConfig()
    df, spark, rotation = points.df, points.df.sparkSession, None
    n = df.count() if n is None else n
    if not n:
        return SpatialIndex(spark.createDataFrame([], PARTS), points.dim, cfg, points.scale)
    if transform == "pca":
        from .pca import fit_pca, pca_transform

        components = fit_pca(df, points.dim)
        df, rotation = pca_transform(df, components), tuple(map(tuple, components.tolist()))
    parts = max(cfg.parts or 1, -(-n // cfg.local_rows))
    if parts <= 1:
        assigned = in_one_task(replace(points, df=df)).withColumn("part_id", F.lit(0))
    elif cfg.top == "exact":
        from .levels import assign_levels

        assigned = assign_levels(df, points.dim, cfg, max_rows=-(-n // parts) if cfg.parts else cfg.local_rows)
    else:
        share = min(1.0, 1.2 * parts * cfg.sample_rows / n)
        sample = df.where(F.pmod(F.xxhash64("pid", F.lit(cfg.seed)), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).toPandas()
        route = _top_tree_router(sample, parts, cfg)
        assigned = df.withColumn("part_id", route("x"))
    if parts > 1:
        assigned = saved(assigned.select("part_id", "pid", "x"))
        top = assigned.agg(F.max("part_id")).first()[0] + 1
        assigned = _cut_crowded(assigned, cfg, top)
    places = shared_dir(spark), shared_dir(spark)
    trees = saved(_local_trees(assigned.select("part_id", "pid", "x"), cfg, parts <= 1, places[0], only), places[1])
    return SpatialIndex(trees, points.dim, cfg, points.scale, n, trees.count(), rotation, places=places)
