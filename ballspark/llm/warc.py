"""WARC archives with a two-level capture index.

Archives are real WARC/1.1 files, a gzip member for each record, written by tasks through
``pyarrow.fs`` into a shared folder. The index has a line for each record, (key, archive, place, ...),
its key the url with the host's labels reversed. Lines are sorted and cut into compressed blocks; the
second level, the block directory, has each block's first key. A look-up binary-searches the
directory, reads one block, binary-searches it and reads the records' byte ranges. Any number of keys
are looked up together: keys of one block meet, and read it once. Archives are written in the order of keys, so
a block's records are neighbours.
"""

from __future__ import annotations

import bisect
import hashlib
import json
import zlib
from collections.abc import Iterator
from uuid import NAMESPACE_URL, uuid5

import pandas as pd
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import as_bytes, batch_of, few, small_batches, text_or_empty, work_dir, written
from .url_filters import url_host

#: Lines of an index block; payloads of fewer bytes are never revisits.
BLOCK_LINES, REVISIT_BYTES = 1000, 1000
#: Blocks of a directory that every task searches; a longer one is searched by way of sections of SECTION blocks.
SEARCHED, SECTION = 50_000, 1000
#: Fixed value: the date of records, as these tables have none.
DATE = "2024-01-01T00:00:00Z"
#: Fixed value: the published name of the profile of revisits with equal payloads.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

LINE = "key string, page_id long, archive string, at long, length long"


def capture_key(url: Column) -> Column:
    """``org,example,www)/path?query`` for ``https://www.example.org/path?query#part``; empty for null."""
    host = url_host(url)
    rest = F.regexp_extract(F.regexp_replace(url, r"^(.*?)://", ""), r"^[^/?#]*([^#]*)", 1)
    return F.coalesce(F.concat(F.array_join(F.reverse(F.split(host, r"\.")), ","), F.lit(")"), rest), F.lit(""))


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One record: a response with its payload, or a revisit without it that names the response's record."""
    head = {"WARC-Type": "response" if refers_to is None else "revisit", "WARC-Record-ID": _record_id(page_id), "WARC-Date": DATE}
    if url is not None:
        head["WARC-Target-URI"] = url.translate({10: "%0A", 13: "%0D"})
    head |= {"WARC-Payload-Digest": f"sha1:{digest}", "X-Page": json.dumps(page_id), "X-Payload-Bytes": str(len(payload))}
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    if refers_to is not None:
        head |= {"WARC-Refers-To": _record_id(refers_to), "X-Refers-To-Page": str(refers_to), "WARC-Profile": PROFILE}
        payload = b""
    head |= {"Content-Type": "application/http;msgtype=response", "Content-Length": str(len(http) + len(payload))}
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode() + b"\r\n" + http + payload + b"\r\n\r\n"


def _record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid5(NAMESPACE_URL, f'page:{page_id}')}>"


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    """Named fields and payload of one record's bytes."""
    head, _, body = data.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    body = body[: int(fields["Content-Length"])]
    return fields, body.partition(b"\r\n\r\n")[2]


def _gzip(data: bytes) -> bytes:
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def responses(pages: DataFrame) -> DataFrame:
    """``pages`` with ``digest`` and ``refers_to``, the page whose response a row revisits (null: it is one).

    Of rows with equal payloads of at least REVISIT_BYTES bytes that with the largest page_id responds. Payloads that
    occur once take no part in the join; the others' digests are broadcast where they take few bytes, else it can be split where one payload has very many rows. Rows
    without page_id never respond for others; of repeated rows of the largest page_id all respond.
    """
    payload = F.encode(text_or_empty("html"), "UTF-8")
    rows = pages.select("page_id", "url", text_or_empty("html").alias("html")).withColumns({"digest": F.sha1(payload), "bytes": F.octet_length(payload).cast("long")})
    shared = rows.where(F.col("bytes") >= REVISIT_BYTES).groupBy("digest").agg(F.max("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").select("digest", "first")
    shared = few(written(shared, "shared"))
    refers = F.when((F.col("bytes") >= REVISIT_BYTES) & (F.col("first") != F.coalesce("page_id", F.col("first") - 1)), F.col("first"))
    return rows.join(shared, "digest", "left").withColumn("refers_to", refers).drop("first")


def write_archives(pages: DataFrame, folder: str) -> DataFrame:
    """Writes a record for each of ``pages`` (page_id, url, html) below ``folder``; returns the index lines.

    Records stand in the order of their keys. Lines are LINE, a written table. An archive's name has its task's attempt, and archives that no
    line names don't count, so tasks can be lost and repeated. Null html is an empty payload, a null url
    leaves the record without a target; an empty table writes nothing.
    """
    small_batches(pages.sparkSession)
    schema = pa.schema([("key", pa.string()), ("page_id", pa.int64()), ("archive", pa.string()), ("at", pa.int64()), ("length", pa.int64())])

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base)
        task = TaskContext.get()
        name, out, at = f"{base}/{task.partitionId():06d}-{task.taskAttemptId()}.warc.gz", None, 0
        for batch in batches:
            rows: dict[str, list] = {f.name: [] for f in schema}
            columns = [batch.column(n).to_pylist() for n in ("key", "page_id", "url", "digest", "refers_to")]
            for key, page, url, digest, refers, html in zip(*columns, as_bytes(batch.column("html"))):
                out = out or store.open_output_stream(name, compression=None)
                data = _gzip(record(page, url, html, digest, refers))
                out.write(data)
                for k, v in (("key", key), ("page_id", page), ("archive", name), ("at", at), ("length", len(data))):
                    rows[k].append(v)
                at += len(data)
            yield batch_of(schema, rows)
        if out:
            out.close()

    rows = responses(pages).select(capture_key(F.col("url")).alias("key"), F.col("page_id").cast("long"), "url", "html", "digest", F.col("refers_to").cast("long"))
    tie = F.xxhash64("page_id", "digest")  # so that a key with very many pages is not bound to one task
    rows = rows.withColumn("tie", tie).repartitionByRange("key", "tie").sortWithinPartitions("key", "tie").drop("tie")
    return written(rows.mapInArrow(write, LINE), "captures")


def write_index(lines: DataFrame, folder: str) -> DataFrame:
    """Sorts ``lines`` by key into compressed blocks below ``folder``; returns the block directory.

    The directory is (first_key, last_key, file, at, length, n), a row for each block. Lines with one
    key stand in the order of a hash, so that no key is bound to one task; a key's lines can then be
    in several blocks, and a look-up reads all of them.
    """
    schema = pa.schema([("first_key", pa.string()), ("last_key", pa.string()), ("file", pa.string()), ("at", pa.int64()), ("length", pa.int64()), ("n", pa.int64())])

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base)
        task = TaskContext.get()
        name, out, at = f"{base}/{task.partitionId():06d}-{task.taskAttemptId()}.index", None, 0
        held: list[tuple] = []
        rows: list[tuple] = []

        def flush(block: list[tuple]) -> None:
            nonlocal out, at
            out = out or store.open_output_stream(name, compression=None)
            data = _gzip("\n".join(map(json.dumps, block)).encode())
            out.write(data)
            rows.append((block[0][0], block[-1][0], name, at, len(data), len(block)))
            at += len(data)

        for batch in batches:
            held += zip(*(c.to_pylist() for c in batch.columns))
            while len(held) >= BLOCK_LINES:
                flush(held[:BLOCK_LINES])
                held = held[BLOCK_LINES:]
        if held:
            flush(held)
        if out:
            out.close()
        yield batch_of(schema, {f.name: [r[i] for r in rows] for i, f in enumerate(schema)})

    tie = F.xxhash64("archive", "at")
    ordered = lines.withColumn("tie", tie).repartitionByRange("key", "tie").sortWithinPartitions("key", "tie").drop("tie")
    return written(ordered.mapInArrow(write, "first_key string, last_key string, file string, at long, length long, n long"), "blocks")


def _range(store: fs.FileSystem, file: str, at: int, length: int) -> bytes:
    with store.open_input_file(file) as f:
        f.seek(at)
        return f.read(length)


def block_lines(store: fs.FileSystem, file: str, at: int, length: int) -> list[list]:
    return [json.loads(x) for x in zlib.decompress(_range(store, file, at, length), 31).split(b"\n")]


class CaptureIndex:
    """Look-ups by key, one at a time. A directory of up to SEARCHED blocks is held sorted; of a longer one only what a key needs is read."""

    def __init__(self, directory: DataFrame, folder: str):
        self.store, _ = fs.FileSystem.from_uri(folder)
        self.directory = directory if directory.count() > SEARCHED else None
        self.blocks = [] if self.directory is not None else sorted(directory.collect(), key=lambda b: (b.first_key, b.last_key))
        self.first = [b.first_key for b in self.blocks]

    def _blocks(self, key: str) -> Iterator:
        if self.directory is not None:
            yield from self.directory.where((F.col("first_key") <= key) & (F.col("last_key") >= key)).toLocalIterator()
            return
        at = bisect.bisect_right(self.first, key) - 1
        while at >= 0 and self.blocks[at].last_key >= key:
            yield self.blocks[at]
            at -= 1

    def lines(self, key: str) -> Iterator[list]:
        """The index lines of a key, from the blocks that can have it."""
        for b in self._blocks(key):
            yield from lines_of(block_lines(self.store, b.file, b.at, b.length), key)

    def records(self, key: str) -> Iterator[tuple[dict[str, str], bytes]]:
        for _, _, archive, at, length in self.lines(key):
            yield parse(zlib.decompress(_range(self.store, archive, at, length), 31))


def lines_of(lines: list[list], key: str) -> Iterator[list]:
    """The lines of a key in a block, by binary search."""
    begin = bisect.bisect_left(lines, key, key=lambda x: x[0])
    while begin < len(lines) and lines[begin][0] == key:
        yield lines[begin]
        begin += 1


def _searched(keys: DataFrame, directory: DataFrame) -> DataFrame:
    """``keys`` with the rows of a directory of at most SEARCHED rows whose first and last keys have each between them, by binary search."""
    rows = sorted(directory.collect(), key=lambda b: (b.first_key, b.last_key))
    held = directory.sparkSession.sparkContext.broadcast(([b.first_key for b in rows], [b.last_key for b in rows]))

    @F.pandas_udf("array<int>")
    def places(key: pd.Series) -> pd.Series:
        first, last = held.value

        def of(k: str) -> list[int]:
            at = end = bisect.bisect_right(first, k)
            while at > 0 and last[at - 1] >= k:
                at -= 1
            return list(range(at, end))

        return key.map(of)

    numbered = directory.sparkSession.createDataFrame([(i, *r) for i, r in enumerate(rows)], T.StructType([T.StructField("place", T.IntegerType()), *directory.schema.fields]))
    return keys.withColumn("place", F.explode(places("key"))).join(F.broadcast(numbered), "place").drop("place")


def blocks_of(keys: DataFrame, directory: DataFrame) -> DataFrame:
    """(key, file, at, length): the blocks that can have each of ``keys`` (key)."""
    if directory.count() <= SEARCHED:
        return _searched(keys, directory).select("key", "file", "at", "length")

    def sections(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, SECTION):
                some = batch.slice(i, SECTION)
                first, last = some.column("first_key").to_pylist(), some.column("last_key").to_pylist()
                yield pa.RecordBatch.from_pylist([{"first_key": first[0], "last_key": max(last), "section": first[0] + "\0" + last[-1] + str(some.column("at")[0]), "blocks": some.to_pylist()}], schema)

    block = [("first_key", pa.string()), ("last_key", pa.string()), ("file", pa.string()), ("at", pa.int64()), ("length", pa.int64())]
    schema = pa.schema([("first_key", pa.string()), ("last_key", pa.string()), ("section", pa.string()), ("blocks", pa.list_(pa.struct(block)))])
    ordered = directory.select(*[n for n, _ in block]).repartitionByRange("first_key", "last_key").sortWithinPartitions("first_key", "last_key")
    kind = "first_key string, last_key string, section string, blocks array<struct<first_key:string,last_key:string,file:string,at:long,length:long>>"
    table = written(ordered.mapInArrow(sections, kind), "sections")
    near = _searched(keys, table.drop("blocks")).select("key", "section").join(table.select("section", "blocks"), "section")
    here = F.filter("blocks", lambda b: (b["first_key"] <= F.col("key")) & (b["last_key"] >= F.col("key")))
    return near.select("key", F.explode(here).alias("b")).select("key", "b.file", "b.at", "b.length")


def look_up(keys: DataFrame, directory: DataFrame, folder: str) -> DataFrame:
    """(key, page_id, url, payload_bytes, payload_digest, record_type, refers_to) of every capture of the keys (key), each key once.

    The keys of a block come to one task in order; it reads the block once by its range, finds each
    key's lines by binary search and reads the records that they point at by theirs. A response's
    length and digest are those of the payload read; a revisit, which has no payload, gives what its
    fields say. Null keys and keys without captures have no rows.
    """
    kinds = [("key", pa.string()), ("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())]
    schema = pa.schema(kinds)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, _ = fs.FileSystem.from_uri(folder)
        block, lines, name, archive = None, [], None, None
        for batch in batches:
            rows: list[tuple] = []
            for key, *this in zip(*(batch.column(n).to_pylist() for n in ("key", "file", "at", "length"))):
                if this != block:
                    block, lines = this, block_lines(store, *this)
                for _, _, where, begin, n in lines_of(lines, key):
                    if where != name:
                        if archive:
                            archive.close()
                        name, archive = where, store.open_input_file(where)
                    archive.seek(begin)
                    fields, payload = parse(zlib.decompress(archive.read(n), 31))
                    revisit = fields["WARC-Type"] == "revisit"
                    rows.append(
                        (
                            key,
                            json.loads(fields["X-Page"]),
                            fields.get("WARC-Target-URI"),
                            int(fields["X-Payload-Bytes"]) if revisit else len(payload),
                            fields["WARC-Payload-Digest"].removeprefix("sha1:") if revisit else hashlib.sha1(payload).hexdigest(),
                            fields["WARC-Type"],
                            int(fields["X-Refers-To-Page"]) if revisit else None,
                        )
                    )
                    if len(rows) >= BLOCK_LINES:
                        yield batch_of(schema, {f.name: [r[i] for r in rows] for i, f in enumerate(schema)})
                        rows = []
            yield batch_of(schema, {f.name: [r[i] for r in rows] for i, f in enumerate(schema)})
        if archive:
            archive.close()

    asked = blocks_of(keys.where("key is not null").distinct(), directory)
    spread = asked.repartition("file", "at").sortWithinPartitions("file", "at", "key")
    return spread.mapInArrow(read, "key string, page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive_folder(spark: SparkSession) -> str:
    return work_dir(spark, "warc")
