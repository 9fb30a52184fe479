"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line.

Fills report seconds; `us_per_point` and `speedup` beside them compare with the published time per placed point.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.sql.execution.arrow.pyspark.enabled", "true").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from nodefill import catalogue
    from nodefill.operators import spark_fill as fills
    from nodefill.plans import workloads

    seconds, extra = {}, {}

    def timed(name, run):
        t = time.perf_counter()
        n = run()
        seconds[name] = round(time.perf_counter() - t, 3)
        return n

    spark.range(1000).selectExpr("sum(id)").collect()
    region, s = workloads.spacing_of_size("clover2d", 1000)
    fills.fill_sequential(workloads.first_seed(spark, region), region, s).count()
    parts = int(cpus) * 2
    for n in (64_000, 256_000, 1_024_000):
        region, s = workloads.spacing_of_size("clover2d", n)
        seed = workloads.first_seed(spark, region)
        placed = timed(f"fill_sequential_{n}", lambda: fills.fill_sequential(seed, region, s).count())
        # all of the method counts: bootstrap, cells, borders, refill
        many = timed(f"fill_cells_{n}", lambda: fills.fill_from_one_seed(seed, region, s, n, parts).count())
        a, b = seconds[f"fill_sequential_{n}"] / placed, seconds[f"fill_cells_{n}"] / many
        extra[f"us_per_point_sequential_{n}"], extra[f"us_per_point_cells_{n}"] = round(a * 1e6, 2), round(b * 1e6, 2)
        extra[f"speedup_{n}"], extra[f"efficiency_{n}"] = round(a / b, 2), round(a / b / int(cpus), 3)
    headline = ["inside_clover2d", "inside_clover3d", "inside_hare2d", "spacing_clover2d", "assign_cells", "border_distance", "knn_grid", "two_level_knn", "conflict_edges", "thin_part", "thin_grid_ties", "local_regularity", "spmv", "op_range_join_bbox", "op_asof_prev_event", "op_interval_events", "stream_windows_session", "op_window_frames"]
    for name in headline:
        timed(name, lambda q=catalogue.queries()[name]: q(spark, sf_dir).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir.rstrip("/")), **extra}))
    spark.stop()


if __name__ == "__main__":
    main()
