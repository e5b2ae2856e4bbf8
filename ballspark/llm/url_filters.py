"""URL filters by hashed host-suffix and path-prefix expressions, all in Spark's own functions.

A rule is (verdict, host, path). It fits a url whose host is the rule's host or a subdomain of it
and whose path starts with the rule's path. Of the rules that fit the longest wins (host and path
together, then the longer host, then allow before block).

Which expressions a url must be expanded into follows from the rules: only their *shapes*, pairs of
label count and path length, can match. Each url gives one expression a shape that it is long enough
for; expressions meet rules by an equi-join on 32-bit prefixes of their SHA-256, and the whole
digests confirm.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Hexadecimal digits of the digest that the join uses.
PREFIX = 8
SALTS = 32


def url_host(url: Column) -> Column:
    """Lower-cased (A-Z) host; empty without ``://`` or for null."""
    return F.translate(F.regexp_extract(_after_scheme(url), r"^([^/?#]*)", 1), UPPER, LOWER)


def url_path(url: Column) -> Column:
    """From the end of the host up to ``?``, ``#`` or the end."""
    return F.regexp_extract(_after_scheme(url), r"^[^/?#]*([^?#]*)", 1)


def _after_scheme(url: Column) -> Column:
    at = F.locate("://", url)
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), path), 256)


def judge_urls(urls: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow", broadcast_bytes: int = 64 << 20) -> DataFrame:
    """(id_col, host, path, rule, verdict) for each row of ``urls``.

    Null urls and urls without a scheme have empty host and path and get ``default``; repeated rows
    stay repeated; other columns of ``urls`` are not read, so their names don't matter. Rules with a
    null or empty host fit nothing; a null path is an empty one. An empty table gives an empty result.

    The rules are broadcast while they take at most ``broadcast_bytes`` (measured), otherwise they
    are joined by shuffle, each url with one of ``SALTS`` copies of the rules, so that an expression
    that a third of all urls share is spread over as many tasks.
    """
    rules = (
        rules.select(F.translate("host", UPPER, LOWER).alias("host"), F.coalesce("path", F.lit("")).alias("path"), (F.col("verdict") == "allow").alias("allow"))
        .where("host <> ''")
        .groupBy("host", "path")
        .agg(F.max("allow").alias("allow"))
        .withColumns({"labels": F.size(F.split("host", r"\.")), "path_length": F.length("path"), "digest": _digest(F.col("host"), F.col("path"))})
    )
    # one row for each label count and path length that occurs, not for each rule
    shapes = [(r.labels, r.path_length) for r in rules.select("labels", "path_length").distinct().collect()]
    by_prefix = rules.groupBy(F.substring("digest", 1, PREFIX).alias("prefix")).agg(F.collect_list(F.struct("digest", "allow")).alias("found"))
    small = (rules.select(F.sum(F.length("host") + F.length("path") + 160)).first()[0] or 0) <= broadcast_bytes

    known = F.array(*[F.struct(F.lit(k).alias("labels"), F.lit(n).alias("length")) for k, n in sorted(shapes)]) if shapes else F.expr("cast(array() as array<struct<labels:int,length:int>>)")
    host, path = F.col("host"), F.col("path")
    n_labels = F.size(F.split(host, r"\."))

    def expression(shape: Column) -> Column:
        suffix, start = F.call_function("substring_index", host, F.lit("."), -shape["labels"]), F.substring(path, F.lit(1), shape["length"])
        return F.struct(
            _digest(suffix, start).alias("digest"),
            # orders rules that fit one url, and has all that tells which rule it was
            ((F.length(suffix) + shape["length"]).cast("long") * 1024 + shape["labels"] * 2).alias("rank"),
        )

    fitting = F.filter(known, lambda s: (s["labels"] <= n_labels) & (s["length"] <= F.length(path)))
    key = [F.col("id"), F.col("url")]
    expanded = (
        urls.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"))
        .withColumns({"host": url_host(F.col("url")), "path": url_path(F.col("url"))})
        .select(*key, F.posexplode_outer(F.transform(fitting, expression)).alias("at", "e"))
        .select(*key, F.coalesce("at", F.lit(0)).alias("at"), F.substring("e.digest", 1, PREFIX).alias("prefix"), F.col("e.digest").alias("digest"), F.col("e.rank").alias("rank"))
    )
    if small:
        met = expanded.join(F.broadcast(by_prefix), "prefix", "left")
    else:
        salted = by_prefix.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        met = expanded.withColumn("salt", F.pmod(F.xxhash64("id", "url"), F.lit(SALTS)).cast("int")).join(salted, ["prefix", "salt"], "left")
    confirmed = F.filter("found", lambda x: x["digest"] == F.col("digest"))
    best = (
        met.withColumn("hit", F.get(confirmed, F.lit(0)))
        .groupBy("id", "url")
        .agg(F.max(F.when(F.col("hit").isNotNull(), F.col("rank") + F.col("hit.allow").cast("int"))).alias("best"), F.sum((F.col("at") == 0).cast("long")).alias("copies"))
        .withColumns({"host": url_host(F.col("url")), "path": url_path(F.col("url"))})
    )
    labels = F.shiftright(F.col("best") % 1024, 1)
    suffix = F.call_function("substring_index", host, F.lit("."), -labels.cast("int"))
    length = F.shiftright("best", 10)
    rule = F.concat(suffix, F.substring(path, F.lit(1), (length - F.length(suffix)).cast("int")))
    verdict = F.when(F.col("best").isNull(), default).when(F.col("best") % 2 == 1, "allow").otherwise("block")
    return best.select(F.col("id").alias(id_col), host, path, rule.alias("rule"), verdict.alias("verdict"), F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("copy")).drop("copy")
