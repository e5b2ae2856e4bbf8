"""The point views on the given tables, each as one row of facts, for Spark and for the oracles alike."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .points import Points, load, to_points

LINE_PID = "((l_orderkey * 32768 + l_partkey) * 1024 + l_suppkey) * 8 + l_linenumber"


@dataclass(frozen=True)
class View:
    """``spark`` and ``duck`` are the raw coordinates in each dialect; ``where`` keeps some rows in both."""

    table: str
    pid: str
    spark: tuple[str, ...]
    duck: tuple[str, ...] | None = None
    unit: bool = True
    where: str = "true"

    @property
    def dim(self) -> int:
        return len(self.spark)

    @property
    def oracle(self) -> tuple[str, ...]:
        return self.duck or tuple(f"CAST({c} AS DOUBLE)" for c in self.spark)


def _day(c: str) -> tuple[str, str]:
    return f"datediff(to_date({c}), DATE'1995-01-01')", f"CAST(date_diff('day', DATE '1995-01-01', CAST({c} AS DATE)) AS DOUBLE)"


ORDER_DAY, SHIP_DAY = _day("o_orderdate"), _day("l_shipdate")
# whole seconds of a day and of the days before it: the same integers in both dialects
TS = (
    "(datediff(to_date(ts), DATE'1970-01-01') * 86400000000L + cast(round(extract(SECOND FROM ts) * 1000000) as bigint) + extract(MINUTE FROM ts) * 60000000L + extract(HOUR FROM ts) * 3600000000L) / 1e6D",
    "epoch_us(ts) / 1e6",
)
PROP_K = ("cast(get_json_object(props, '$.k') as double)", "CAST(json_extract_string(props, '$.k') AS DOUBLE)")


def _plain(*columns: str) -> tuple[str, ...]:
    return tuple(f"CAST({c} AS DOUBLE)" for c in columns)


VIEWS = {
    "orders2": View("orders", "o_orderkey", (ORDER_DAY[0], "o_totalprice"), (ORDER_DAY[1], *_plain("o_totalprice"))),
    "open_orders2": View("orders", "o_orderkey", (ORDER_DAY[0], "o_totalprice"), (ORDER_DAY[1], *_plain("o_totalprice")), where="o_orderstatus = 'O'"),
    "ship2": View("lineitem", LINE_PID, ("l_extendedprice", SHIP_DAY[0]), (*_plain("l_extendedprice"), SHIP_DAY[1])),
    "latin2": View("orders", "o_orderkey", ("o_orderkey", "o_totalprice")),
    "lattice2": View("part", "p_partkey", ("p_partkey", "p_retailprice")),
    "events_uv2": View("events", "event_id", ("user_id", "value")),
    "events_tv2": View("events", "event_id", (TS[0], "value"), (TS[1], *_plain("value"))),
    "events4": View("events", "event_id", (TS[0], "user_id", "value", PROP_K[0]), (TS[1], *_plain("user_id", "value"), PROP_K[1])),
    "line4": View("lineitem", LINE_PID, ("l_quantity", "l_extendedprice", "l_discount", "l_tax")),
    "dup4": View("lineitem", LINE_PID, ("l_quantity", "l_discount", "l_tax", "l_linenumber")),
    "grid2": View("lineitem", LINE_PID, ("l_discount", "l_tax")),
    "cust2": View("customer", "c_custkey", ("c_nationkey", "c_acctbal")),
    "supp1": View("supplier", "s_suppkey", ("s_acctbal",)),
    "emb64": View("embeddings", "vec_id", tuple(f"embedding[{j}]" for j in range(64)), tuple(f"CAST(embedding[{j + 1}] AS DOUBLE)" for j in range(64)), unit=False),
    "emb2": View("embeddings", "vec_id", ("embedding[0]", "embedding[1]"), _plain("embedding[1]", "embedding[2]"), unit=False),
    "doc2": View("documents", "doc_id", ("ln(n_chars)", "ln(1 + length(text) - length(replace(text, ' ', '')))")),
}


def points(spark: SparkSession, sf_dir: str, name: str) -> Points:
    """The view's points, scaled to the unit cube where the view says so; only its columns are read."""
    v = VIEWS[name]
    columns = [f"x{j}" for j in range(v.dim)]
    rows = load(spark, sf_dir, v.table).where(v.where).select(F.expr(v.pid).cast("long").alias("pid"), *[F.expr(e).cast("double").alias(c) for e, c in zip(v.spark, columns)])
    return to_points(rows, "pid", columns, scale="minmax" if v.unit else "none")


def hash_cut(df: DataFrame, m: int, key: str = "pid") -> DataFrame:
    """The m rows of the smallest key hash, the key breaking ties."""
    return df.withColumn("_h", stable_hash(key)).orderBy("_h", key).limit(m).drop("_h")


def stable_hash(key: str):
    return (F.pmod(F.col(key), F.lit(1000003)) * F.lit(48271)) % F.lit(2147483647)
