"""Packing documents into windows by non-negative least squares over their lengths.

A document's whole windows stand alone; what is left of it, its *remainder*, is rounded up to a class
of UNIT tokens. The corpus's histogram of classes (at most WINDOW / UNIT counts) goes to the driver.
There every combination of at most DEPTH classes that fills a window is a column, and non-negative
least squares finds how often to repeat each so that the histogram is met. Tasks then realise the
plan on their own documents: each repeats the combinations in its share of the plan, rounded, then
as often as what it still has allows, and packs the residue greedily, largest first and then what
fits best, cutting a document only where nothing fits well. So nothing is shuffled, only the last
window of a group has much padding, and a lost task is simply run again.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import id_type, token_ids
from .common import batch_of, small_batches, work_dir

WINDOW, UNIT, DEPTH = 2048, 8, 3
CLASSES = WINDOW // UNIT
#: Tokens that a greedily filled window may leave empty before a document is cut to fill it.
SLACK = 16
#: Tokens of remainders that a task packs together; bounds its memory.
GROUP = 24_000_000


def combinations(total: int = CLASSES, depth: int = DEPTH) -> np.ndarray:
    """The multisets of at most three classes that sum to ``total``; 0 stands for none."""
    rows = [(total, 0, 0)]
    if depth > 1:
        rows += [(a, total - a, 0) for a in range((total + 1) // 2, total)]
    if depth > 2:
        rows += [(a, b, total - a - b) for a in range(-(-total // 3), total) for b in range((total - a + 1) // 2, min(a, total - a - 1) + 1)]
    return np.array(rows)


def nnls(columns: np.ndarray, target: np.ndarray, rounds: int = 400) -> np.ndarray:
    """How often to take each combination: least squares against ``target`` over non-negative counts.

    An active-set method; ``columns`` lists each column's classes, so products with the matrix are
    look-ups. Columns enter a few at a time, those with the steepest descent first.
    """
    n, scale = len(columns), max(1.0, float(target.max(initial=0)))
    h = np.concatenate([[0.0], target / scale])  # place 0 takes the empty slots
    x, free = np.zeros(n), np.zeros(n, bool)

    def matrix(which: np.ndarray) -> np.ndarray:
        a = np.zeros((len(h), len(which)))
        for slot in columns[which].T:
            np.add.at(a, (slot, np.arange(len(which))), 1.0)
        a[0] = 0
        return a

    for _ in range(rounds):
        left = h - matrix(np.nonzero(free)[0]) @ x[free] if free.any() else h.copy()
        left[0] = 0
        gain = left[columns].sum(axis=1)
        gain[free] = -1
        if gain.max() < 1e-6:
            break
        best = np.argsort(-gain, kind="stable")[:16]
        free[best[gain[best] > 0.5 * gain.max()]] = True
        while free.any():
            at = np.nonzero(free)[0]
            solved = np.linalg.lstsq(matrix(at), h, rcond=None)[0]
            if solved.min() > 1e-12:
                x[:] = 0
                x[at] = solved
                break
            down = solved <= 1e-12
            step = min(1.0, np.min(x[at][down] / np.maximum(x[at][down] - solved[down], 1e-30)))
            x[at] += step * (solved - x[at])
            gone = at[down & (x[at] <= 1e-9)]
            free[gone if len(gone) else at[down]] = False
            x[~free] = 0
    return x * scale


def plan(histogram: dict[int, int]) -> list[tuple[tuple[int, ...], float]]:
    """The combinations to repeat, with their share of all remainders; most used first."""
    h = np.array([float(histogram.get(c, 0)) for c in range(1, CLASSES + 1)])
    columns = combinations()
    repeats = nnls(columns, h)
    order = np.argsort(-repeats, kind="stable")
    return [(tuple(int(c) for c in columns[i] if c), float(repeats[i] / h.sum())) for i in order if repeats[i] > 1e-9]


def fill(lengths: list[int], strategies: list[tuple[tuple[int, ...], float]]) -> list[list[tuple[int, int, int]]]:
    """Windows over remainders of these lengths: lists of (which, begin, length), no window over WINDOW.

    Each token of each remainder is in exactly one piece.
    """
    pools: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
    for i, n in enumerate(lengths):
        pools[-(-n // UNIT)].append((i, 0, n))
    windows = []

    def repeat(classes: tuple[int, ...], times: int) -> None:
        need = {c: classes.count(c) for c in classes}
        for _ in range(min(times, *(len(pools[c]) // k for c, k in need.items()))):
            windows.append([pools[c].pop() for c in classes])

    for classes, share in strategies:
        repeat(classes, round(share * len(lengths)))
    for classes, _ in strategies:
        repeat(classes, len(lengths))

    held = np.zeros(CLASSES + 1, np.int64)
    for c, pool in pools.items():
        held[c] = len(pool)

    def largest(most: int) -> int:
        fitting = np.nonzero(held[1 : most + 1])[0]
        return int(fitting[-1]) + 1 if len(fitting) else 0

    def take(c: int) -> tuple[int, int, int]:
        held[c] -= 1
        return pools[c].pop()

    while top := largest(CLASSES):
        window = [take(top)]
        room = WINDOW - window[0][2]
        while room > SLACK and (c := largest(room // UNIT)):
            window.append(take(c))
            room -= window[-1][2]
        if room > SLACK and (c := largest(CLASSES)):
            which, begin, n = take(c)
            window.append((which, begin, min(n, room)))
            if n > room:
                rest = -(-(n - room) // UNIT)
                pools[rest].append((which, begin + room, n - room))
                held[rest] += 1
        windows.append(window)
    return windows


def pack(docs: DataFrame, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, start, length, ids, doc_tokens, sequence_id, offset): a row for each piece.

    ``start`` counts the ids of the row's document before the piece, ``ids`` are little-endian 32-bit
    integers, ``offset`` is the piece's place in its sequence. A null text is an empty one and has its
    end id only; rows with one id, or with none, are packed one by one; texts of any length are cut into windows; an empty table has no pieces. Columns
    beside the two that are read play no part, whatever their names. Ids are written
    once, as a table in the shared folder, so the plan and the packing see the same.
    """
    small_batches(docs.sparkSession)
    spark = docs.sparkSession
    table = work_dir(spark, "ids")
    token_ids(docs, path, end_id, id_col, text_col).write.option("compression", "zstd").parquet(table)
    ids = spark.read.schema("id long, ids binary, n long").parquet(table)
    remainder = F.col("n") % WINDOW
    counts = ids.where(remainder > 0).groupBy(F.ceil(remainder / UNIT).cast("int").alias("c")).count().collect()  # CLASSES rows at most
    strategies = plan({r["c"]: r["count"] for r in counts}) if counts else []
    width, dtype = id_type(path).itemsize, id_type(path)
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids", pa.binary()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])

    def wide(data: bytes) -> bytes:
        return np.frombuffer(data, dtype).astype("<u4").tobytes()

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sequence = TaskContext.get().partitionId() << 36
        rest: list[tuple[int | None, int, bytes, int]] = []  # (doc, start, ids, the document's tokens)
        tokens = 0

        def packed() -> Iterator[pa.RecordBatch]:
            nonlocal sequence
            rows = []
            for window in fill([len(r[2]) // width for r in rest], strategies):
                offset = 0
                for i, begin, n in window:
                    doc, start, data, total = rest[i]
                    rows.append((doc, start + begin, n, wide(data[begin * width : (begin + n) * width]), total, sequence, offset))
                    offset += n
                sequence += 1
                if len(rows) >= 4096:
                    yield _batch(rows, schema)
                    rows = []
            yield _batch(rows, schema)
            rest.clear()

        for batch in batches:
            rows = []
            for doc, data, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                for begin in range(0, n - n % WINDOW, WINDOW):
                    rows.append((doc, begin, WINDOW, wide(data[begin * width : (begin + WINDOW) * width]), n, sequence, 0))
                    sequence += 1
                if n % WINDOW:
                    rest.append((doc, n - n % WINDOW, data[(n - n % WINDOW) * width :], n))
                    tokens += n % WINDOW
                if len(rows) >= 4096:
                    yield _batch(rows, schema)
                    rows = []
                if tokens >= GROUP:
                    yield from packed()
                    tokens = 0
            if rows:
                yield _batch(rows, schema)
        yield from packed()

    return ids.mapInArrow(pieces, "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long")


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return batch_of(schema, {f.name: [r[i] for r in rows] for i, f in enumerate(schema)})
