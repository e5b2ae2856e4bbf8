"""Token files of directly addressable codes.

An id is split into chunks, low bits first. Level k has the k-th chunks of those ids that are long
enough, packed, and, but for the last level, a bitmap that says which of them go on; the place of the
rest at the next level is the rank of that bit, which a directory of counts before every 512 bits
gives at once. So any token of a file is read by a few bytes a level, without decoding a block.

File: segments, then a footer (JSON, its length in the last 8 bytes) with each segment's parts. A
segment has whole documents only: their ids, the offsets of their tokens, and the levels.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import encoder
from .common import batch_of, small_batches, text_or_empty, work_dir

#: Bits of each level's chunks.
WIDTHS = (8, 4, 4, 8, 8)
#: Bits between counts of the rank directory; tokens after which a segment is closed.
BLOCK, SEGMENT = 512, 2_000_000
MAGIC = b"DACTOK01"


def _pack(chunks: np.ndarray, width: int) -> np.ndarray:
    if width == 8:
        return chunks.astype(np.uint8)
    even = np.zeros((len(chunks) + 1) // 2 * 2, np.uint8)
    even[: len(chunks)] = chunks
    return even[::2] | even[1::2] << 4


def _unpack(data: np.ndarray, width: int, n: int) -> np.ndarray:
    if width == 8:
        return data[:n]
    out = np.empty(2 * len(data), np.uint8)
    out[::2], out[1::2] = data & 15, data >> 4
    return out[:n]


def encode_levels(ids: np.ndarray) -> list[dict[str, np.ndarray]]:
    """For each level: packed ``chunks``, and unless no id goes on, the bitmap ``more`` and its ``ranks``."""
    levels, rest = [], ids.astype(np.uint32)
    for k, width in enumerate(WIDTHS):
        level = {"chunks": _pack(rest & ((1 << width) - 1), width)}
        rest = rest >> width
        goes_on = rest > 0
        levels.append(level)
        if k == len(WIDTHS) - 1 or not goes_on.any():
            break
        bits = np.packbits(goes_on, bitorder="little")
        bits = np.pad(bits, (0, -len(bits) % (BLOCK // 8)))
        ones = np.bitwise_count(bits.reshape(-1, BLOCK // 8)).sum(axis=1)
        level |= {"more": bits, "ranks": np.concatenate([[0], np.cumsum(ones)]).astype("<u4")}
        rest = rest[goes_on]
    return levels


def decode_levels(levels: list[dict[str, np.ndarray]], n: int) -> np.ndarray:
    """All ``n`` ids."""
    out, at, shift = np.zeros(n, np.uint32), None, 0
    for width, level in zip(WIDTHS, levels):
        count = n if at is None else len(at)
        chunks = _unpack(level["chunks"], width, count).astype(np.uint32) << np.uint32(shift)
        if at is None:
            out |= chunks
        else:
            out[at] |= chunks
        if "more" not in level:
            break
        goes_on = np.nonzero(np.unpackbits(level["more"], count=count, bitorder="little"))[0]
        at = goes_on if at is None else at[goes_on]
        shift += width
    return out


class Writer:
    """Writes one file; ``add`` takes documents in their order."""

    def __init__(self, stream):
        self.stream, self.at, self.segments = stream, 0, []
        self.docs: list[int | None] = []
        self.ids: list[np.ndarray] = []
        self.tokens = self.total = self.n_docs = 0
        self._put(MAGIC)

    def _put(self, data: bytes) -> int:
        self.stream.write(data)
        self.at += len(data)
        return self.at - len(data)

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.docs.append(doc_id)
        self.ids.append(ids)
        self.tokens += len(ids)
        if self.tokens >= SEGMENT:
            self.flush()

    def flush(self) -> None:
        if not self.docs:
            return
        ends = np.cumsum([len(x) for x in self.ids])
        parts = {
            "docs": np.array([x or 0 for x in self.docs], "<i8"),
            "null": np.array([x is None for x in self.docs], np.uint8),
            "offsets": np.concatenate([[0], ends]).astype("<i8"),
        }
        for k, level in enumerate(encode_levels(np.concatenate(self.ids))):
            parts |= {f"{name}{k}": a for name, a in level.items()}
        where = {name: [self._put(a.tobytes()), a.nbytes] for name, a in parts.items()}
        self.segments.append({"first": self.total, "tokens": self.tokens, "docs": len(self.docs), "parts": where})
        self.total += self.tokens
        self.n_docs += len(self.docs)
        self.docs, self.ids, self.tokens = [], [], 0

    def close(self) -> None:
        self.flush()
        footer = json.dumps({"widths": WIDTHS, "segments": self.segments}).encode()
        self._put(footer + len(footer).to_bytes(8, "little"))


class Reader:
    """Reads one file from anything with ``size()``, ``seek`` and ``read``."""

    TYPES = {"docs": "<i8", "offsets": "<i8", "ranks": "<u4"}

    def __init__(self, stream):
        self.stream, size = stream, stream.size()
        if self._bytes(0, 8) != MAGIC:
            raise ValueError("not a file of directly addressable codes")
        length = int.from_bytes(self._bytes(size - 8, 8), "little")
        footer = json.loads(self._bytes(size - 8 - length, length))
        if tuple(footer["widths"]) != WIDTHS:
            raise ValueError(f"chunks of {footer['widths']} bits")
        self.segments = footer["segments"]

    def _bytes(self, at: int, n: int) -> bytes:
        self.stream.seek(at)
        return self.stream.read(n)

    def _part(self, segment: dict, name: str, k: str = "") -> np.ndarray:
        at, n = segment["parts"][name + k]
        return np.frombuffer(self._bytes(at, n), self.TYPES.get(name, "u1"))

    def documents(self) -> Iterator[tuple[int | None, int, np.ndarray]]:
        """(doc_id, tokens before it in the file, ids) of each document."""
        for s in self.segments:
            levels = []
            while (k := str(len(levels))) and f"chunks{k}" in s["parts"]:
                levels.append({name: self._part(s, name, k) for name in ("chunks", "more", "ranks") if name + k in s["parts"]})
            ids = decode_levels(levels, s["tokens"])
            offsets = self._part(s, "offsets").tolist()
            for doc, null, begin, end in zip(self._part(s, "docs").tolist(), self._part(s, "null").tolist(), offsets, offsets[1:]):
                yield None if null else doc, s["first"] + begin, ids[begin:end]

    def token(self, i: int) -> int:
        """The i-th id of the file, by at most three short reads a level."""
        s = next(s for s in self.segments if s["first"] <= i < s["first"] + s["tokens"])
        i, shift, out = i - s["first"], 0, 0
        for k, width in enumerate(WIDTHS):
            at = s["parts"][f"chunks{k}"][0]
            chunk = self._bytes(at + i * width // 8, 1)[0]
            out |= (chunk if width == 8 else chunk >> 4 * (i % 2) & 15) << shift
            if f"more{k}" not in s["parts"]:
                break
            block, bit = divmod(i, BLOCK)
            word = int.from_bytes(self._bytes(s["parts"][f"more{k}"][0] + block * BLOCK // 8, BLOCK // 8), "little")
            if not word >> bit & 1:
                break
            rank = int.from_bytes(self._bytes(s["parts"][f"ranks{k}"][0] + 4 * block, 4), "little")
            i, shift = rank + (word & (1 << bit) - 1).bit_count(), shift + width
        return out


def write_tokens(docs: DataFrame, folder: str, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes ``docs`` in ascending order of their ids into files below ``folder``; returns the manifest.

    The manifest has a row for each file: (shard, file, n_docs, n_tokens, n_bytes, start), start being
    the tokens of all files before. Null ids come first, rows with one id in the order of a hash of
    their texts, so that no number of them is bound to one task. A file is named by its task's attempt
    and counts only once the manifest lists it, so lost and repeated attempts leave nothing in the way.
    ``folder`` is a URI that ``pyarrow.fs`` opens, and shared. An empty table gives an empty manifest; null texts are
    empty ones, texts of any length are whole in one segment, and columns beside the two that are read play no part, whatever their names.
    """
    small_batches(docs.sparkSession)
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("shard", pa.int32()), ("file", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("n_bytes", pa.int64())])
        task, e, out = TaskContext.get(), encoder(path), None
        end = e._bytes([end_id])
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base)
        name = f"{base}/tokens-{task.partitionId():06d}-{task.taskAttemptId()}.dac"
        for batch in batches:
            if batch.num_rows:
                out = out or Writer(store.open_output_stream(name))
                for doc, ids in zip(batch.column(0).to_pylist(), e.encode(batch.column(1).to_pylist())):
                    out.add(doc, np.frombuffer(ids + end, e.dtype))
        if out:
            out.close()
            out.stream.close()
            yield batch_of(schema, {"shard": [task.partitionId()], "file": [name], "n_docs": [out.n_docs], "n_tokens": [out.total], "n_bytes": [out.at]})

    spark = docs.sparkSession
    rows = docs.select(docs[id_col].cast("long").alias("id"), text_or_empty(text_col).alias("text")).withColumn("tie", F.xxhash64("text"))
    ordered = rows.repartitionByRange("id", "tie").sortWithinPartitions("id", "tie").select("id", "text")
    files = ordered.mapInArrow(write, "shard int, file string, n_docs long, n_tokens long, n_bytes long").collect()  # a row for each file
    start, manifest = 0, []
    for f in sorted(files, key=lambda f: f.shard):
        manifest.append((*f, start))
        start += f.n_tokens
    return spark.createDataFrame(manifest, "shard int, file string, n_docs long, n_tokens long, n_bytes long, start long")


def read_tokens(manifest: DataFrame, folder: str) -> DataFrame:
    """(id, start, n, ids) of each document in the files of a manifest; ids as little-endian 32-bit integers."""
    schema = pa.schema([("id", pa.int64()), ("start", pa.int64()), ("n", pa.int64()), ("ids", pa.binary())])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, _ = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for file, start in zip(batch.column("file").to_pylist(), batch.column("start").to_pylist()):
                rows: dict[str, list] = {f.name: [] for f in schema}
                held = 0
                with store.open_input_file(file) as stream:
                    for doc, before, ids in Reader(stream).documents():
                        for k, v in (("id", doc), ("start", start + before), ("n", len(ids)), ("ids", ids.astype("<u4").tobytes())):
                            rows[k].append(v)
                        held += len(ids)
                        if held >= SEGMENT:
                            yield batch_of(schema, rows)
                            rows, held = {f.name: [] for f in schema}, 0
                yield batch_of(schema, rows)

    files = manifest.select("file", "start")
    return files.repartition(max(1, manifest.count())).mapInArrow(read, "id long, start long, n long, ids binary")


def token_file_folder(spark: SparkSession) -> str:
    return work_dir(spark, "tokens")
