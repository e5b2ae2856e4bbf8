"""Secret scans over an incremental ledger of content-addressed texts.

Every version of a text is a blob, named by the SHA-256 of its UTF-8 bytes. The ledger is a Parquet
table (blob, rules, spans): which blob has been scanned under which version of the rules, and what
was found. A scan takes only the blobs of its input that the ledger lacks under the current version,
each once however many paths carry it, adds them, and joins the findings back to all paths.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, batch_of, let_go, small_batches, text_or_empty, work_dir

SPAN = "array<struct<kind:string,begin:int,end:int>>"
LEDGER = f"blob binary, rules string, spans {SPAN}"

# The base rules.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")  # a run of at least 32 is the same as a run that is then found to be long enough
# Published token formats and the armour of private keys.
MORE = {
    "pem": re.compile(r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----[A-Za-z0-9+/=\s]{32,}?-----END (?:[A-Z]+ )*PRIVATE KEY-----"),
    "forge": re.compile(r"\bgh[pousr]_[A-Za-z0-9]{36,}\b|\bglpat-[A-Za-z0-9_-]{20,}"),
    "chat": re.compile(r"\bxox[abprs]-[A-Za-z0-9-]{10,}"),
    "jwt": re.compile(r"\beyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
}
KINDS = ("assign", "access", "hex", *MORE)
RULES_VERSION = hashlib.sha256("\n".join([ASSIGN.pattern, "8", ACCESS.pattern, "16", HEX.pattern, *(f"{k} {v.pattern}" for k, v in MORE.items())]).encode()).hexdigest()[:16]

KEYWORDS = (b"passw", b"secret", b"token", b"api_key", b"apikey")
#: A text without the one has no match of the other.
NEEDED = {"pem": "-----BEGIN ", "jwt": "eyJ", "chat": "xox"}


def find_secrets(data: bytes) -> list[tuple[str, int, int]]:
    """(kind, begin, end) in code points, by begin and then by kind as KINDS lists them."""
    found, text = [], data.decode("utf-8", "replace")
    low = data.lower()
    if any(k in low for k in KEYWORDS):
        found += [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        found += [("access", *m.span()) for m in ACCESS.finditer(text) if len(m[0]) >= 16]
    found += [("hex", *m.span()) for m in HEX.finditer(text)]
    for kind, pattern in MORE.items():
        if NEEDED.get(kind, "") in text and (kind != "forge" or "gh" in text or "glpat-" in text):
            found += [(kind, *m.span()) for m in pattern.finditer(text)]
    return sorted(found, key=lambda s: (s[1], KINDS.index(s[0]), s[2])) if len(found) > 1 else found


def _once_a_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Drops the texts that this task has sent already: copies meet at most once a task after the shuffle."""
    seen: set[bytes] = set()
    for batch in batches:
        keep = []
        for i, blob in enumerate(batch.column(0).to_pylist()):
            if blob not in seen:
                seen.add(blob)
                keep.append(i)
        yield batch.take(pa.array(keep, pa.int64()))


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("blob", pa.binary()), ("rules", pa.string()), ("spans", pa.list_(pa.struct([("kind", pa.string()), ("begin", pa.int32()), ("end", pa.int32())])))])
    let_go()
    seen: set[bytes] = set()
    for batch in batches:
        blobs, spans = [], []
        for blob, data in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1))):
            if blob not in seen:
                seen.add(blob)
                blobs.append(blob)
                spans.append([{"kind": k, "begin": s, "end": e} for k, s, e in find_secrets(data)])
        yield batch_of(schema, {"blob": blobs, "rules": [RULES_VERSION] * len(blobs), "spans": spans})


def read_ledger(spark: SparkSession, ledger: str) -> DataFrame | None:
    """The ledger at that path, None if there is none yet."""
    path = spark._jvm.org.apache.hadoop.fs.Path(ledger)
    there = path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path)
    return spark.read.schema(LEDGER).parquet(ledger) if there else None


def scan_new(docs: DataFrame, ledger: str, text_col: str = "text") -> int:
    """Scans the blobs of ``docs`` that the ledger lacks under RULES_VERSION and adds them; returns how many.

    Texts move once, by blob, and a blob at most once from each task, so a text with any number of
    copies is no hot key. Null texts are empty ones. Appending is the only write, and a blob that two
    runs add at once is there twice with equal spans, which ``findings`` takes as one.
    """
    small_batches(docs.sparkSession)
    spark = docs.sparkSession
    texts = docs.select(F.unhex(F.sha2(text_or_empty(text_col), 256)).alias("blob"), text_or_empty(text_col).alias("text"))
    before = read_ledger(spark, ledger)
    if before is not None:
        unseen = texts.select("blob").distinct().join(before.where(F.col("rules") == RULES_VERSION).select("blob"), "blob", "left_anti")
        texts = texts.join(unseen, "blob", "left_semi")
    new = texts.mapInArrow(_once_a_task, "blob binary, text string").repartition("blob").mapInArrow(_scan, LEDGER)
    part = work_dir(spark, "scan")  # written apart first, so that a failed scan leaves no half of it
    new.write.parquet(part)
    new = spark.read.schema(LEDGER).parquet(part)
    new.write.mode("append").parquet(ledger)
    return new.count()


def findings(docs: DataFrame, ledger: str, text_col: str = "text") -> DataFrame:
    """``docs`` with ``blob`` and ``spans``, the findings under RULES_VERSION of each row's text.

    Columns of those names in ``docs`` are replaced. Only blobs with findings take part in the join,
    and it is one that Spark can split where a blob has very many rows.
    """
    there = docs.sparkSession.read.schema(LEDGER).parquet(ledger).where((F.col("rules") == RULES_VERSION) & (F.size("spans") > 0)).select("blob", "spans").dropDuplicates(["blob"])
    paths = docs.drop("spans").withColumn("blob", F.unhex(F.sha2(text_or_empty(text_col), 256)))
    return paths.join(there, "blob", "left").withColumn("spans", F.coalesce("spans", F.array().cast(SPAN)))


def scan_secrets(docs: DataFrame, ledger: str | None = None, text_col: str = "text") -> DataFrame:
    """``docs`` with ``blob`` and ``spans``. Without a ledger's path a new ledger is made for this run.

    Null and empty texts have no spans, texts of any length are scanned whole, repeated rows have the same spans each; an empty table gives an empty result.
    """
    ledger = ledger or work_dir(docs.sparkSession, "ledger")
    scan_new(docs, ledger, text_col)
    return findings(docs, ledger, text_col)


def redact(scanned: DataFrame, text_col: str = "text", mark: str = "[secret]") -> DataFrame:
    """``scanned`` without its ``blob`` and ``spans``, each span in the text replaced by ``mark``.

    Overlapping spans are one. A null text stays null, a text without spans is unchanged.
    """
    # (text so far, end of what has been copied): spans come ordered by begin
    done = F.aggregate(
        "spans",
        F.struct(F.lit("").alias("out"), F.lit(0).alias("at")),
        lambda a, s: F.struct(
            F.when(s["begin"] >= a["at"], F.concat(a["out"], F.substring(F.col(text_col), a["at"] + 1, s["begin"] - a["at"]), F.lit(mark))).otherwise(a["out"]).alias("out"),
            F.greatest(a["at"], s["end"]).alias("at"),
        ),
    )
    rest = F.substring(F.col(text_col), done["at"] + 1, F.length(text_col))
    return scanned.withColumn(text_col, F.when(F.size("spans") > 0, F.concat(done["out"], rest)).otherwise(F.col(text_col))).drop("blob", "spans")


def span_string(spans: str = "spans") -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["begin"], s["end"])), ",")
