"""From raw documents to packed training sequences, in five stages.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it kept. All but the
last return the columns of documents. ``run`` writes each stage's rows to the shared folder and reads them again as the
next one's documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ballspark.llm.common import few, forget, mark, written
from ballspark.llm.jaccard import link_components
from ballspark.llm.mixing import mix
from ballspark.llm.packing import pack
from ballspark.llm.quality import keep_good
from ballspark.llm.secret_scan import redact, scan_secrets

TOKENIZER, END_ID = public_tokenizers.path("byte_bpe_50k.json"), 1
#: How often a document may be taken by the mixture, for once that the largest source's are.
MAX_REPETITION = 1.25


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and the perplexity bands keep, unchanged. A null text fails the base rules."""
    return keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents that with the smallest id. Rows without an id are kept, repeated rows both."""
    gone = written(link_components(docs).where("doc_id <> component_id").select("doc_id").distinct(), "gone")
    return docs.join(few(gone), "doc_id", "left_anti").select(docs.columns)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, each secret in their texts replaced by a mark; n_chars follows where a text changed."""
    found = scan_secrets(docs)
    hit = F.size("spans") > 0
    clean = redact(found.withColumn("hit", hit))
    return clean.withColumn("n_chars", F.when(F.col("hit"), F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(docs.columns)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as their source's weight in tokens asks, at least once: small sources are repeated up to MAX_REPETITION."""
    return mix(docs, max_repetition=MAX_REPETITION, tokenizer=TOKENIZER).select(docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in windows, with their ids."""
    return pack(docs, TOKENIZER, END_ID)


STAGES = [("quality rules", quality_rules), ("near duplicates", near_duplicates), ("secret scans", secrets), ("mixing to target weights", mixture), ("packing", packing)]

#: No SQL has the tokenizer or the models; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents. Once a stage's rows are written, its own folders and the stage's before are deleted."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), mark()
    for _, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), "stage")
        forget(spark, before)
    return docs
