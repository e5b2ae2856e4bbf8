"""Streams against an index: queries that arrive, points that arrive, windows over what was answered."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ballspark.operators.index import SpatialIndex, shared_dir
from ballspark.operators.search import constrained_knn


def event_stream(spark: SparkSession, path: str, schema, time_col: str = "ts", watermark: str | None = "1 hour", **options) -> DataFrame:
    """Parquet files as a stream, the event time as a timestamp with the watermark."""
    rows = spark.readStream.schema(schema).options(**options).parquet(path)
    rows = rows.withColumn(time_col, F.col(time_col).cast("timestamp"))
    return rows.withWatermark(time_col, watermark) if watermark else rows


def run_to_end(stream: DataFrame, sink: Callable[[DataFrame, int], None] | None = None, mode: str = "append", key: list[str] | None = None) -> DataFrame | None:
    """Runs a stream over all that is there now. Without a sink its rows come back as a table in the shared folder.

    In update mode a batch has the changed groups only: all rows of a ``key`` are those of the last
    batch that has the key. A batch that is delivered again replaces what it wrote.
    """
    spark = stream.sparkSession
    writer = stream.writeStream.option("checkpointLocation", shared_dir(spark)).trigger(availableNow=True)
    if sink is not None:
        writer.foreachBatch(sink).start().awaitTermination()
        return None
    path = shared_dir(spark)
    if mode == "append":
        writer.outputMode("append").format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    if mode == "complete":  # complete results replace each other: the last batch is the result
        writer.outputMode(mode).foreachBatch(lambda rows, _: rows.write.mode("overwrite").parquet(path)).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    if not key:
        raise ValueError("in update mode key says which rows replace which")
    writer.outputMode(mode).foreachBatch(lambda rows, i: rows.write.mode("overwrite").parquet(f"{path}/batch={i}")).start().awaitTermination()
    spark.createDataFrame([], stream.schema).write.mode("overwrite").parquet(f"{path}/batch=-1")  # a stream without batches has an empty result
    rows = spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.LongType())])).option("basePath", path).parquet(path)
    last = rows.groupBy(*key).agg(F.max("batch").alias("batch"))
    return rows.join(last, [*key, "batch"]).select(stream.columns)


def marked_late(stream: DataFrame, time_col: str = "ts", delay: str = "1 hour") -> DataFrame:
    """All rows of a stream, run to its end, with ``late``: whether they came after the watermark had passed them.

    The watermark of a batch is the latest time of the batches before it less ``delay``; Spark's own
    operators drop such rows and count them only. It is found again from what was written, so a restart goes on from there.
    Rows without a time are not late.
    """
    spark, path = stream.sparkSession, shared_dir(stream.sparkSession)
    schema = T.StructType([*stream.schema.fields, T.StructField("late", T.BooleanType()), T.StructField("batch", T.LongType())])
    spark.createDataFrame([], T.StructType(schema.fields[:-1])).write.parquet(f"{path}/batch=-1")

    def written() -> DataFrame:
        return spark.read.schema(schema).option("basePath", path).parquet(path)

    def mark(rows: DataFrame, i: int) -> None:
        seen = written().where(F.col("batch") < i).agg((F.max(time_col) - F.expr(f"interval {delay}")).alias("watermark"))
        late = F.coalesce(F.col(time_col) < F.col("watermark"), F.lit(False))
        rows.join(F.broadcast(seen)).withColumn("late", late).drop("watermark").write.mode("overwrite").parquet(f"{path}/batch={i}")

    run_to_end(stream, mark)
    return written().drop("batch")


def window_counts(events: DataFrame, kind: str, time_col: str = "ts", value_col: str = "value", key: list[str] | None = None) -> DataFrame:
    """Counts and value sums by tumbling day, sliding six hours of a day, or sessions of 30 minutes by key."""
    windows = {"tumbling": F.window(time_col, "1 day"), "sliding": F.window(time_col, "1 day", "6 hours"), "session": F.session_window(time_col, "30 minutes")}
    grouped = events.groupBy(windows[kind].alias("w"), *(key or []))
    return grouped.agg(F.count("*").alias("n"), F.sum(value_col).alias("total")).select(*(key or []), F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "total")


def deduplicated(events: DataFrame, key: str = "event_id", time_col: str = "ts", delay: str = "1 hour") -> DataFrame:
    """The first of each key within the watermark."""
    return events.withWatermark(time_col, delay).dropDuplicatesWithinWatermark([key])


def stream_constrained(queries: DataFrame, index: SpatialIndex, k: int, r: float) -> DataFrame:
    """Every row of a stream (qid, q) answered against a static index; append only, whatever the batches are."""
    path = shared_dir(index.spark)
    index.spark.createDataFrame([], "qid long, rank int, pid long, dist double").write.parquet(f"{path}/batch=-1")
    run_to_end(queries, lambda batch, i: constrained_knn(index, batch, k, r).write.mode("overwrite").parquet(f"{path}/batch={i}"))
    schema = "qid long, rank int, pid long, dist double"
    return index.spark.read.schema(schema + ", batch long").option("basePath", path).parquet(path).drop("batch")


def stream_append(points: DataFrame, index: SpatialIndex) -> SpatialIndex:
    """A stream of points (pid, x) added to the index batch by batch; a batch that is delivered again changes nothing."""
    state = {"index": index, "last": -1}

    def add(batch: DataFrame, i: int) -> None:
        if i > state["last"]:
            state["index"], state["last"] = state["index"].append(batch), i

    run_to_end(points, add)
    return state["index"]


def standing_nearest(points: DataFrame, queries: DataFrame, k: int, dim: int) -> DataFrame:
    """The best k so far of each standing query over a stream of points; state is k pairs a query.

    Points meet the queries, a small static table, in a broadcast; updates are emitted as they occur.
    """
    from ballspark.functions.geometry import sq_dist

    pairs = points.join(F.broadcast(queries.select("qid", "q"))).select("qid", "pid", sq_dist(F.col("x"), F.col("q"), dim).alias("d2"))

    def keep(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best = list(zip(*state.get)) if state.exists else []
        for b in batches:
            best = sorted({*best, *zip(b["d2"], b["pid"])})[:k]
        state.update(([d for d, _ in best], [p for _, p in best]))
        yield pd.DataFrame({"qid": [key[0]] * len(best), "rank": range(1, len(best) + 1), "pid": [p for _, p in best], "d2": [d for d, _ in best]})

    return pairs.groupBy("qid").applyInPandasWithState(keep, "qid long, rank int, pid long, d2 double", "d2 array<double>, pid array<long>", "update", GroupStateTimeout.NoTimeout)


def nearby_events(errors: DataFrame, purchases: DataFrame, within: str = "60 seconds") -> DataFrame:
    """Stream-stream join: purchases within a time of an error of the same user, both with watermarks on ``ts``."""
    e = errors.select(F.col("event_id").alias("error_id"), F.col("user_id").alias("error_user"), F.col("ts").alias("error_ts"))
    p = purchases.select("event_id", "user_id", "ts")
    span = F.expr(f"interval {within}")
    return p.join(e, (F.col("user_id") == F.col("error_user")) & F.col("ts").between(F.col("error_ts") - span, F.col("error_ts") + span)).select("event_id", "error_id")
