"""Times the headline operations at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``measures`` beside the seconds are the tree and search figures that don't depend on the machine.
"""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = os.pathsep.join([HERE, os.environ.get("PYTHONPATH", "")])

from pyspark.sql import SparkSession  # noqa: E402

from ballspark import catalogue  # noqa: E402
from ballspark.config import BuildConfig  # noqa: E402
from ballspark.operators import joins, search, stats  # noqa: E402
from ballspark.operators.index import build_tree  # noqa: E402
from ballspark.plans import workloads  # noqa: E402
from ballspark.sources.generators import generate  # noqa: E402
from ballspark.sources.points import Points  # noqa: E402
from ballspark.sources.queries import uniform_queries  # noqa: E402
from ballspark.sources.views import hash_cut, points  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(CPUS)))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "4g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    measures: dict[str, object] = {}

    def timed(name: str, work):
        began = time.perf_counter()
        out = work()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    timed("start", lambda: spark.range(10).count())
    ship = points(spark, SF_DIR, "ship2")
    ship = Points(hash_cut(ship.df, 500_000).persist(), 2, ship.scale)
    n = timed("read_points", ship.df.count)
    qs = uniform_queries(spark, [(0.0, 1.0)] * 2, workloads.QUERIES).repartition(int(CPUS)).persist()
    qs.count()
    for kind in workloads.KINDS:
        index = timed(f"build_{kind}", lambda: build_tree(ship, BuildConfig(kind=kind, local_rows=10**7), n))
        timed(f"range_{kind}", lambda: search.range_search(index, qs, 0.01).count())
        timed(f"knn_{kind}", lambda: search.knn_search(index, qs, 10).count())
        timed(f"cnn_{kind}", lambda: search.constrained_knn(index, qs, 10, 0.005).count())
        deep = build_tree(ship, BuildConfig(kind=kind, leaf_capacity=1, local_rows=10**7), n)
        measures[f"depth_{kind}"] = round(stats.avg_depth(deep).first().avg_depth, 4)
        for name, trace in (
            ("range", lambda: search.range_search(deep, qs, 0.01, trace=True)),
            ("knn", lambda: search.nearest(deep, qs.drop("r"), 10, trace=True)),
            ("cnn", lambda: search.nearest(deep, qs, 10, 0.005, trace=True)),
        ):
            cost = timed(f"visits_{name}_{kind}", lambda: stats.average_cost(trace()).first())
            measures[f"visits_{name}_{kind}"] = round(cost.avg_entered, 2)
    plain = build_tree(ship, BuildConfig(kind="kdt", kd_bounds="plane", leaf_capacity=1, local_rows=10**7), n)
    cost = timed("visits_range_kdt_plane", lambda: stats.average_cost(search.range_search(plain, qs, 0.01, trace=True)).first())
    measures["visits_range_kdt_plane"] = round(cost.avg_entered, 2)
    for family in ("latin", "highleyman", "lithuanian"):
        made = Points(generate(spark, family, n), 2)
        for kind in workloads.KINDS:
            deep = build_tree(made, BuildConfig(kind=kind, leaf_capacity=1, local_rows=10**7), n)
            measures[f"depth_{family}_{kind}"] = round(stats.avg_depth(deep).first().avg_depth, 4)
    parts = timed("build_two_tier", lambda: build_tree(ship, BuildConfig(parts=16, top="sample", local_rows=10**6), n))
    timed("cnn_two_tier", lambda: search.constrained_knn(parts, qs, 10, 0.005).count())
    asks = hash_cut(points(spark, SF_DIR, "orders2").df, 20_000)
    timed("knn_join", lambda: joins.knn_join(parts, asks.selectExpr("pid AS qid", "x AS q"), 5).count())
    timed("grid_range_join", lambda: joins.grid_range_join(ship.df, qs, 0.005, 2).count())
    for name in ("range_count", "cnn_events4", "pab_level3", "root_section_scan", "attach_orders", "report_cube", "interval_join", "asof_event"):
        timed(name, lambda: catalogue.QUERIES[name](spark, SF_DIR).count())
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "measures": measures, "points": n, "queries_per_set": workloads.QUERIES, "sf": os.path.basename(SF_DIR.rstrip("/")), "cpus": CPUS}))


if __name__ == "__main__":
    main()
