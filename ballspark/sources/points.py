"""Point relations from tables and files, and sinks for results."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_points(spark: SparkSession, path: str, fmt: str, schema: str | T.StructType, **options) -> DataFrame:
    """Rows of a declared schema from csv, json, orc, parquet or text.

    For csv and json, fields that can't be read are null and the whole line is in ``_rejected``.
    """
    reader = spark.read.options(**options)
    if fmt in ("csv", "json"):
        declared = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
        declared = T.StructType([*declared.fields, T.StructField("_rejected", T.StringType())])
        reader = reader.option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_rejected").schema(declared)
    elif fmt != "text":
        reader = reader.schema(schema)
    return reader.format(fmt).load(path)


def write_results(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    """Results as parquet, orc, csv or json; csv takes vectors as JSON texts."""
    if fmt == "csv":
        df = df.select(*[F.to_json(c).alias(c) if isinstance(df.schema[c].dataType, (T.ArrayType, T.StructType, T.MapType)) else F.col(c) for c in df.columns])
    df.write.format(fmt).mode(mode).save(path)


def seconds(c: Column) -> Column:
    """Seconds since 1970 of a timestamp without time zone, whatever the session's zone is."""
    day = F.datediff(F.to_date(c), F.lit("1970-01-01").cast("date")).cast("double")
    part = F.extract(F.lit("SECOND"), c).cast("double") + F.extract(F.lit("MINUTE"), c) * 60 + F.extract(F.lit("HOUR"), c) * 3600
    return day * 86400 + part


def days(c: Column, since: str = "1995-01-01") -> Column:
    return F.datediff(F.to_date(c), F.lit(since).cast("date")).cast("double")


def as_coordinate(df: DataFrame, name: str) -> Column:
    """A column of any numeric, boolean, date, time or interval type as a double."""
    kind, c = df.schema[name].dataType, F.col(name)
    if isinstance(kind, T.BooleanType):
        return c.cast("int").cast("double")
    if isinstance(kind, T.DateType):
        return days(c, "1970-01-01")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return seconds(c)
    if isinstance(kind, T.DayTimeIntervalType):
        return F.extract(F.lit("DAY"), c) * 86400.0 + F.extract(F.lit("HOUR"), c) * 3600.0 + F.extract(F.lit("MINUTE"), c) * 60.0 + F.extract(F.lit("SECOND"), c).cast("double")
    return c.cast("double")


@dataclass(frozen=True)
class Scale:
    """(value - shift) / factor for each dimension; kept with an index and applied to its queries."""

    shift: tuple[float, ...]
    factor: tuple[float, ...]

    def apply(self, x: Column) -> Column:
        return F.array(*[(x[j] - F.lit(a)) / F.lit(b) for j, (a, b) in enumerate(zip(self.shift, self.factor))])


@dataclass
class Points:
    """``df`` (pid, x), the dimension, the scale that was applied, how many rows were left out, and whether ``df`` only reads files that were written of it."""

    df: DataFrame
    dim: int
    scale: Scale | None = None
    rejected: int = 0
    filed: bool = False


def to_points(df: DataFrame, id_col: str, cols: list[str] | None = None, array_col: str | None = None, scale: str = "none", nulls: str = "drop") -> Points:
    """(pid, x) from columns or from one array column.

    scale: ``minmax`` to [0, 1] by dimension, ``zscore``, or ``none``; a constant dimension becomes 0.
    Rows with a null or NaN coordinate, or with an array of another length than most, are left out and
    counted; with ``nulls='error'`` they raise. The bounds are one aggregate over the table.
    """
    if (cols is None) == (array_col is None):
        raise ValueError("either columns or an array column")
    if cols is not None:
        dim, x = len(cols), F.array(*[as_coordinate(df, c) for c in cols])
    else:
        x = F.col(array_col).cast("array<double>")
        sizes = df.select(F.mode(F.size(array_col)).alias("d")).first()
        dim = max(1, (sizes.d if sizes else None) or 1)
    rows = df.select(F.col(id_col).cast("long").alias("pid"), x.alias("x"))
    good = F.col("x").isNotNull() & (F.size("x") == dim) & ~F.exists("x", lambda v: v.isNull() | F.isnan(v))
    bounds = []
    for j in range(dim):
        v = F.when(good, F.col("x")[j])
        bounds += [F.min(v).alias(f"lo{j}"), F.max(v).alias(f"hi{j}")] if scale == "minmax" else [F.avg(v).alias(f"lo{j}"), F.stddev_pop(v).alias(f"hi{j}")] if scale == "zscore" else []
    got = rows.agg(F.count_if(~F.coalesce(good, F.lit(False))).alias("bad"), *bounds).first()
    if got.bad and nulls == "error":
        raise ValueError(f"{got.bad} rows have a null, NaN or missing coordinate")
    rows = rows.where(good)
    if scale == "none" or got["lo0"] is None:
        return Points(rows, dim, None, got.bad)
    spread = [(got[f"hi{j}"] - got[f"lo{j}"]) if scale == "minmax" else got[f"hi{j}"] for j in range(dim)]
    fitted = Scale(tuple(got[f"lo{j}"] for j in range(dim)), tuple(s or 1.0 for s in spread))
    return Points(rows.withColumn("x", fitted.apply(F.col("x"))), dim, fitted, got.bad)
