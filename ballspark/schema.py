"""Schemas of the relations that the operators take and give."""

from __future__ import annotations

from pyspark.sql import types as T

VECTOR = T.ArrayType(T.DoubleType(), False)

POINTS = T.StructType([T.StructField("pid", T.LongType()), T.StructField("x", VECTOR)])
QUERIES = T.StructType([T.StructField("qid", T.LongType()), T.StructField("q", VECTOR), T.StructField("k", T.IntegerType()), T.StructField("r", T.DoubleType())])
ANSWERS = T.StructType([T.StructField("qid", T.LongType()), T.StructField("pid", T.LongType()), T.StructField("d2", T.DoubleType())])

NODES = "part_id int, node_id long, parent_id long, lo_id long, hi_id long, depth int, is_leaf boolean, n long, center array<double>, radius double, axis array<double>, cut double, t_min double, t_max double, objective double, box_lo array<double>, box_hi array<double>, pivot_lo array<double>, pivot_hi array<double>"
LEAF_POINTS = "part_id int, leaf_id long, pid long, x array<double>"
#: A part's tree as one row: what routing needs in columns, the tree's arrays in ``tree``.
PARTS = "part_id int, n long, center array<double>, radius double, box_lo array<double>, box_hi array<double>, tree binary"
