"""Every registered query against its SQL, on the smallest tables."""

import glob
import os

import duckdb
import pytest

from ballspark import catalogue
from ballspark.plans import workloads

#: Reports whose defaults are the full grids; test_workloads.py runs them with small ones.
SLOW = {"reduction_report", "visit_report", "alpha_sweep", "cvisit_report", "depth_report", "quality_report", *(f"{name}_{family}" for name in ("depth", "visits", "cvisits") for family in workloads.SYNTHETIC)}


@pytest.fixture(scope="session")
def duck(sf_dir):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def _rows(frame):
    columns = sorted(frame.columns)
    plain = frame[columns].astype(object).where(frame[columns].notna(), None)
    return columns, sorted(str([round(v, 6) if isinstance(v, float) else v for v in row]) for row in plain.map(lambda v: float(v) if hasattr(v, "dtype") and v.dtype.kind == "f" else v).values.tolist())


SQL = catalogue.ORACLES


@pytest.mark.parametrize("name", sorted(catalogue.SMALL_ORACLES))
def test_join_equals_all_pairs(spark, duck, sf_dir, name):
    got = catalogue.QUERIES[name](spark, sf_dir).toPandas()
    assert _rows(got) == _rows(duck.sql(catalogue.SMALL_ORACLES[name]).df())


def test_join_sql_is_whole_on_sparse_points(spark, sf_dir, tmp_path):
    """Queries without five points within a cell's side have their five all the same, in the SQL as in the join."""
    con = duckdb.connect()
    for table, some in (("lineitem", "l_orderkey % 400 = 1"), ("orders", "o_orderkey % 20 = 1")):
        con.sql(f"COPY (SELECT * FROM '{sf_dir}/{table}.parquet' WHERE {some}) TO '{tmp_path}/{table}.parquet'")
        con.sql(f"CREATE VIEW {table} AS SELECT * FROM '{tmp_path}/{table}.parquet'")
    whole = con.sql(catalogue.SMALL_ORACLES["knn_join_two_round"]).df()
    assert whole["dist"].max() > catalogue._JOIN_CELL and len(whole) == 5 * whole["qid"].nunique()
    assert _rows(con.sql(SQL["knn_join_two_round"]).df()) == _rows(whole) == _rows(catalogue.QUERIES["knn_join_two_round"](spark, str(tmp_path)).toPandas())


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, duck, sf_dir, name):
    got = catalogue.QUERIES[name](spark, sf_dir).toPandas()
    assert _rows(got) == _rows(duck.sql(SQL[name]).df())


@pytest.mark.parametrize("name", sorted(set(catalogue.QUERIES) - set(SQL) - SLOW))
def test_report_has_rows(spark, sf_dir, name):
    assert catalogue.QUERIES[name](spark, sf_dir).count() > 0


def test_flagship(spark, sf_dir):
    assert catalogue.flagship(spark, sf_dir).count() > 0
