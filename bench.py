"""Times of the headline queries: one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from posterior_mesh import experiments as ex
from posterior_mesh.registry import QUERIES


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    headline = {
        "curve_5_2": lambda: ex.paper_curves(spark, 5, 2, runs=ex.RUNS, grid=ex.GRID),
        "curve_40_2": lambda: ex.paper_curves(spark, 40, 2, runs=ex.RUNS, grid=ex.GRID),
        "curve_40_4": lambda: ex.paper_curves(spark, 40, 4, runs=ex.RUNS, grid=ex.GRID),
        **{name: (lambda f=QUERIES[name]: f(spark, sf_dir)) for name in ("linear_subposteriors", "linear_errors", "shard_sizes_exact", "worker_storage", "event_rates", "events_ready_coded_sum_40_4", "coded_order_totals_cyclic_40_4")},
    }
    times = {}
    for name, make in headline.items():
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        times[name] = round(time.time() - began, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir.rstrip("/").rpartition("sf")[2]}))


if __name__ == "__main__":
    main()
