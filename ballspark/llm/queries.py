"""The queries of the corpus operators, thin over the operators, and the SQL that some can be held against."""

from __future__ import annotations

from functools import partial

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .dac import read_tokens, token_file_folder, write_tokens
from .jaccard import link_components
from .media import sound_features, store_sounds
from .mixing import mix
from .packing import pack
from .quality import judge
from .secret_scan import scan_secrets, span_string
from .token_counts import count_tokens
from .url_filters import judge_urls
from .warc import archive_folder, look_up, write_archives, write_index

#: The rules of the url query, as (verdict, host, path).
URL_RULES = [
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
]


def op1_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(URL_RULES, "verdict string, host string, path string")
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"), rules)


def _of_kind(kind: str, span: Column) -> Column:
    return span["kind"] == kind


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    base = F.filter("spans", lambda s: s["kind"].isin("assign", "access", "hex"))
    n_of = [F.size(F.filter("spans", partial(_of_kind, k))).cast("long").alias(f"n_{k}") for k in ("assign", "access", "hex")]
    return found.withColumn("base", base).select("doc_id", *n_of, F.sha2(span_string("base"), 256).alias("base_sha256"), span_string("spans").alias("spans"))


def op3_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    sounds = sound_features(store_sounds(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    feature = F.concat_ws(":", F.size("codes"), F.sha2(F.array_join(F.arrays_zip("frames", "codes").cast("array<string>"), ","), 256))
    return sounds.select(F.col("id").alias("doc_id"), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", feature.alias("feature"), "frames", "codes")


#: The tokenizer of the packing, token file and counting queries.
TOKENIZER = public_tokenizers.path("byte_bpe_50k.json")


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), TOKENIZER, end_id=1)
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = token_file_folder(spark)
    manifest = write_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), folder, TOKENIZER, end_id=2)
    return read_tokens(manifest, folder).select(F.col("id").alias("doc_id"), "start", F.col("n").alias("n_tokens"), F.crc32("ids").alias("ids_crc32"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), TOKENIZER)
    return counts.select(F.col("id").alias("doc_id"), "n_bytes", "n_tokens", (F.col("n_tokens") > 1024).alias("over_limit"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"), keep=["doc_id"])
    return judged.select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "log_perplexity")


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    taken = mix(spark.read.parquet(f"{sf_dir}/documents.parquet"), max_repetition=2.0, budget_share=1.5, tokenizer=TOKENIZER)
    return taken.select("doc_id", "source", "mix_tokens", "mix_weight", "mix_epoch", "mix_block", "mix_order")


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = archive_folder(spark)
    lines = write_archives(spark.read.parquet(f"{sf_dir}/pages.parquet"), folder)
    read = look_up(lines.select("key"), write_index(lines, folder), folder)
    return read.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


QUERIES = {
    "op1_url_filters": op1_url_filters,
    "op2_secret_scan": op2_secret_scan,
    "op3_media_columns": op3_media_columns,
    "op4_packing": op4_packing,
    "op5_token_files": op5_token_files,
    "op6_quality_rules": op6_quality_rules,
    "op7_jaccard_join": op7_jaccard_join,
    "op8_mixing": op8_mixing,
    "op9_token_counts": op9_token_counts,
    "op10_warc": op10_warc,
}

_RULES = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in URL_RULES)
ORACLES = {
    "op1_url_filters": f"""
        WITH rules(verdict, rule_host, rule_path) AS (VALUES {_RULES}),
        rest AS (SELECT page_id, url, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS r FROM pages),
        parts AS (SELECT page_id, url,
            translate(regexp_extract(r, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
            regexp_extract(r, '^[^/?#]*([^?#]*)', 1) AS path FROM rest)
        SELECT p.page_id, any_value(p.host) AS host, any_value(p.path) AS path,
            arg_max(rule_host || rule_path, length(rule_host || rule_path)) AS rule,
            coalesce(arg_max(verdict, length(rule_host || rule_path)), 'allow') AS verdict
        FROM parts p LEFT JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path)
        GROUP BY p.page_id""",
    "op10_warc": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
        d AS (SELECT page_id, octet_length(encode(h)) AS payload_bytes, sha1(h) AS payload_digest FROM p),
        f AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS first_page FROM d)
        SELECT page_id, payload_bytes, payload_digest,
            CASE WHEN payload_bytes >= 1000 AND first_page <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
            CASE WHEN payload_bytes >= 1000 AND first_page <> page_id THEN first_page END AS refers_to FROM f""",
}
