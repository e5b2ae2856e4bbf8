"""Mixing sources to target weights by temperature, and realising them as block permutations.

The weights of sources are their token shares to the power of an exponent, normalised. The exponent
is bisected until the weights' entropy reaches a target or until no source is repeated more often
than a limit. A source's share of the token budget is then so many whole epochs and a part of one.
Each epoch of a source goes through its blocks, bounded groups of its documents; within a block
documents stand in an order that a hash of document and epoch gives, and the last epoch takes from each block the
documents before that part of its tokens. So no source, however large, is ever ordered as a whole.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written
from .token_counts import with_token_counts

#: Exponents that one pass over the sources tries, and passes: 32 ** 5 steps between 0 and 1.
TRIED, PASSES = 32, 5
#: Documents of a block, on average.
BLOCK_DOCS = 512


def token_estimate(text: str = "text") -> Column:
    """Words between white space, at least 1: what the mixture weighs documents by."""
    return F.greatest(F.lit(1), F.size(F.array_remove(F.split(F.coalesce(F.col(text), F.lit("")), r"[\x20\x09-\x0D]+"), ""))).cast("long")


def source_totals(docs: DataFrame, source_col: str = "source", tokens: Column | None = None) -> DataFrame:
    """(source, docs, tokens); null is a source of its own. Summed before the shuffle, so a hot source is one row a task."""
    tokens = token_estimate() if tokens is None else tokens
    return docs.select(F.col(source_col).alias("source"), tokens.alias("t")).groupBy("source").agg(F.count("*").alias("docs"), F.sum("t").alias("tokens"))


def measures(totals: DataFrame, exponents: list[float], budget: float | None) -> list[tuple[float, float]]:
    """(entropy, largest repetition) of the weights at each exponent, in one pass over the sources.

    Without a budget it is that at which the least repeated source is taken once.
    """
    whole = totals.agg(F.sum("tokens")).first()[0]
    p = F.col("tokens") / F.lit(float(whole))
    logs = F.log(p)
    rows = totals.where("tokens > 0")
    aggregates = []
    for i, a in enumerate(exponents):
        w = F.exp(F.lit(a) * logs)
        aggregates += [F.sum(w).alias(f"s{i}"), F.sum(w * logs).alias(f"l{i}"), F.max(w / p).alias(f"x{i}"), F.min(w / p).alias(f"n{i}")]
    r = rows.agg(*aggregates).first()
    out = []
    for i, a in enumerate(exponents):
        entropy = math.log(r[f"s{i}"]) - a * r[f"l{i}"] / r[f"s{i}"]
        out.append((entropy, r[f"x{i}"] / r[f"n{i}"] if budget is None else r[f"x{i}"] / r[f"s{i}"] * budget / whole))
    return out


def find_exponent(totals: DataFrame, target_entropy: float | None = None, max_repetition: float | None = None, budget: float | None = None) -> float:
    """The smallest exponent in [0, 1] whose weights keep to the targets: entropy at most, repetition at most.

    Entropy and repetition both fall as the exponent grows, so each pass keeps the one interval
    between tried exponents that has the border. With no source or no target it is 1; where
    even 1 keeps to no target it is 1, where 0 keeps to all it is 0.
    """
    if (target_entropy is None and max_repetition is None) or totals.where("tokens > 0").isEmpty():
        return 1.0
    low, high = 0.0, 1.0
    for _ in range(PASSES):
        tried = [low + (high - low) * k / TRIED for k in range(TRIED + 1)]
        keeps = [(target_entropy is None or h <= target_entropy + 1e-12) and (max_repetition is None or r <= max_repetition + 1e-12) for h, r in measures(totals, tried, budget)]
        first = next((k for k, ok in enumerate(keeps) if ok), None)
        if first is None:
            return 1.0
        if first == 0:
            return tried[0]
        low, high = tried[first - 1], tried[first]
    return high


def weights(totals: DataFrame, exponent: float, budget: float | None = None) -> DataFrame:
    """(source, docs, tokens, weight, repeats): the share of the budget and how often its tokens go round."""
    whole = totals.agg(F.sum("tokens")).first()[0] or 1
    rows = totals.withColumn("raw", F.exp(F.lit(exponent) * F.log(F.col("tokens") / F.lit(float(whole)))))
    s = rows.agg(F.sum("raw").alias("s"), F.min(F.col("raw") / F.col("tokens")).alias("least")).first()
    per_raw = budget / s.s if budget is not None and s.s else 1 / s.least if s.least else 0.0
    return rows.select("source", "docs", "tokens", (F.col("raw") / F.lit(s.s or 1.0)).alias("weight"), (F.col("raw") * F.lit(per_raw) / F.col("tokens")).alias("repeats"))


def mix(
    docs: DataFrame, target_entropy: float | None = None, max_repetition: float | None = None, budget: float | None = None, seed: int = 17,
    id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", budget_share: float | None = None, tokenizer: str | None = None,
) -> DataFrame:
    """``docs`` with ``mix_tokens``, ``mix_weight``, ``mix_epoch``, ``mix_block`` and ``mix_order``: a row for each time a document is taken.

    Reading by (mix_epoch, mix_block, mix_order) gives the permutation. Tokens are those of the tokenizer
    file ``tokenizer``, with one more for a document's end, or without one words. ``budget`` is in
    tokens, ``budget_share`` in those of all documents; without either nothing is dropped: the least repeated source is
    taken once whole. Null sources are one source, null and empty texts count one token, very long ones are
    whole, rows whose hashes tie stand in the order of their texts' hashes and tokens, repeated
    rows are rows of their own and rows without an id are dealt by their texts; an empty table stays empty. Columns of those names are replaced.

    The weights have a row for each source. They are broadcast if these are at most 100,000
    (counted), else joined by source in a join that Spark can split.
    """
    docs = docs.drop("mix_tokens", "mix_weight", "mix_epoch", "mix_block", "mix_order")
    columns, tokens = docs.columns, token_estimate(text_col)
    if tokenizer is not None:
        docs = written(with_token_counts(docs, tokenizer, "mix_tokens", text_col), "counted")
        tokens = F.col("mix_tokens") + 1
    totals = written(source_totals(docs, source_col, tokens), "sources")
    if budget is None and budget_share is not None:
        budget = budget_share * (totals.agg(F.sum("tokens")).first()[0] or 0)
    exponent = find_exponent(totals, target_entropy, max_repetition, budget)
    shares = weights(totals, exponent, budget).select(F.col("source").alias("of"), F.col("weight").alias("mix_weight"), "repeats", F.ceil(F.col("docs") / BLOCK_DOCS).alias("blocks"))
    if totals.count() <= 100_000:
        shares = F.broadcast(shares)
    # the documents' own columns travel in a struct, so that none can clash with those made here
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("row"), F.col(id_col).alias("id"), F.col(source_col).alias("source"), tokens.alias("mix_tokens"), F.xxhash64(text_col).alias("tie"))
    rows = rows.withColumn("id", F.coalesce(F.col("id").cast("string"), F.concat(F.lit("text "), F.col("tie"))))
    rows = rows.join(shares, F.col("source").eqNullSafe(F.col("of")))
    rows = rows.withColumns({"mix_block": F.pmod(F.xxhash64("id", F.lit(seed)), "blocks"), "whole": F.floor("repeats")})
    rows = rows.withColumn("hash", F.xxhash64("id", "whole", F.lit(seed + 1)))
    block = Window.partitionBy("of", "mix_block")
    # the last epoch takes a document if its middle comes before that part of the block's tokens
    middle = F.sum("mix_tokens").over(block.orderBy("hash", "tie", "mix_tokens").rowsBetween(Window.unboundedPreceding, 0)) - F.col("mix_tokens") / 2
    part = (F.col("repeats") - F.col("whole")) * F.sum("mix_tokens").over(block)
    rows = rows.withColumn("times", F.col("whole") + (middle < part).cast("long")).where("times > 0")
    rows = rows.withColumn("mix_epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.col("times") - 1)))
    rows = rows.withColumn("mix_order", F.xxhash64("id", "mix_epoch", F.lit(seed + 1)))
    return rows.select("row.*", "mix_tokens", "mix_weight", "mix_epoch", "mix_block", "mix_order")
