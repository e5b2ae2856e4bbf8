"""What several of the corpus operators share: work folders, materialised steps, Arrow batches."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share, as ``spark.checkpoint.dir`` names it.

    Only where that is unset (tests, a laptop) a folder of this machine is made and also
    registered with Spark for ``checkpoint()``.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext.getCheckpointDir()
        if not root:
            root = f"file://{tempfile.mkdtemp(prefix='corpus-')}"
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


class _Folders(threading.local):
    """Folders that a thread of this driver has named, in order."""

    def __init__(self):
        self.made: list[str] = []


_folders = _Folders()


def work_dir(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that no other run uses."""
    _folders.made.append(f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}")
    return _folders.made[-1]


def mark() -> int:
    """For ``forget``: where the folders that are named from now on begin."""
    return len(_folders.made)


def forget(spark: SparkSession, since: int) -> None:
    """Deletes the folders that this thread has named since a mark but for the last, which holds the result: what led to a written result is not read again."""
    for name in _folders.made[since:-1]:
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    del _folders.made[since:-1]


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder, read again: cuts lineage and survives lost executors."""
    path = work_dir(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Bytes, as measured, up to which a side of a join is broadcast, and what a row takes beside its values.
BROADCAST_BYTES, ROW_BYTES = 96 << 20, 32


def few(keys: DataFrame) -> DataFrame:
    """For a join: broadcast where its rows are measured to take few enough bytes; else shuffled. ``keys`` should be a written table."""
    long = [F.coalesce(F.sum(F.octet_length(f"`{c}`")), F.lit(0)).alias(f"s{i}") for i, (c, kind) in enumerate(keys.dtypes) if kind in ("string", "binary")]
    count, *sizes = keys.agg(F.count("*"), *long).first()
    return F.broadcast(keys) if count * (ROW_BYTES + 8 * len(keys.columns)) + sum(sizes) <= BROADCAST_BYTES else keys


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner remove the shuffle files of plans that nothing refers to any more.

    It acts when the driver collects garbage, which a driver with little to do may not do for long;
    after a large step whose result is written, its shuffle files only take room.
    """
    gc.collect()
    spark.sparkContext._jvm.System.gc()


_held: dict = {}


def held(key: tuple, make: Callable):
    """What ``make`` gives, kept in this process for later tasks until another is asked for: workers outlive operators, whose tables would add up."""
    if key not in _held:
        let_go()
        _held[key] = make()
    return _held[key]


def let_go() -> None:
    """Frees what ``held`` keeps, and gives the system back what was freed: tasks of operators that keep nothing begin with it."""
    _held.clear()
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # of the C library on Linux
        trim(0)


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Fewer rows in an Arrow batch than by default: texts are long, and a worker holds a batch and what it makes of it."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def as_bytes(column: pa.Array) -> list[bytes]:
    """The UTF-8 bytes of a string column; nulls are empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def batch_of(schema: pa.Schema, columns: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in schema], schema=schema)


def portions(texts: list, most: int, count: int = 1 << 30) -> Iterator[list]:
    """The texts in runs that end once they have ``most`` characters (or bytes) or ``count`` texts."""
    run, n = [], 0
    for t in texts:
        run.append(t)
        n += len(t)
        if n >= most or len(run) >= count:
            yield run
            run, n = [], 0
    if run:
        yield run


def gathered(batches: Iterator[pa.RecordBatch], column: str, most: int) -> Iterator[pa.RecordBatch]:
    """The rows of the batches in fewer ones, each of which ends once ``column`` has ``most`` bytes."""
    run, n = [], 0
    for batch in batches:
        run.append(batch)
        n += batch.column(column).nbytes
        if n >= most:
            yield pa.concat_batches(run)
            run, n = [], 0
    if run:
        yield pa.concat_batches(run)
