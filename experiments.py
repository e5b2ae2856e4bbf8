"""

``python experiments.py [depth|visits|cvisits|real|scale]...``; all of them without a name. Points of generated sets: EXPERIMENT_POINTS.
"""

from __future__ import annotations

import os
import sys

from pyspark.sql import SparkSession

from ballspark.plans import workloads

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
POINTS = int(os.environ.get("EXPERIMENT_POINTS", workloads.GENERATED))


def main(names: list[str]) -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    def show(name: str, rows) -> None:
        for r in rows.collect():
            print(name, *(f"{k}={v:.6g}" if isinstance(v, float) else f"{k}={v}" for k, v in r.asDict().items()), flush=True)

    for family in workloads.SYNTHETIC:
        one = {"views": (), "families": (family,), "generated": POINTS}
        if "depth" in names:
            show("depth", workloads.depth_report(spark, SF_DIR, **one))
        if "visits" in names:
            show("visits", workloads.visit_report(spark, SF_DIR, capacity=1, rs=(0.1,), ks=(10,), **one))
        if "cvisits" in names:
            show("cvisits", workloads.cvisit_report(spark, SF_DIR, capacity=1, rs=(0.005,), ks=(10,), **one))
    if "real" in names:  # the four-dimensional stand-ins, cut to the published size
        show("real", workloads.real_depths(spark, SF_DIR, 10_000))
    if "scale" in names:
        show("scale", workloads.scale_report(spark, SF_DIR, view=None))


if __name__ == "__main__":
    main(sys.argv[1:] or ["depth", "visits", "cvisits", "real", "scale"])
