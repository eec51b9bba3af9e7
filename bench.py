"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
os.environ["PYTHONPATH"] = os.pathsep.join(p for p in (HERE, os.environ.get("PYTHONPATH", "")) if p)
sys.path.insert(0, HERE)


def main() -> None:
    from pyspark.sql import SparkSession

    from fedgrid import queries as engine
    from fedgrid.plans import experiments as X

    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    names = [
        "exact_grid_s3", "pair_marginals_grouping_sets", "partition_sketch_long", "complement_union_raw_s2", "simplex_consistency",
        "assign_nearest_fixed", "lloyd_one_step", "lsh_prefix_counts", "grr_debias_s2", "wide_loan_16", "asof_last_event",
        "pipeline_pairwise_gauss", "pipeline_reports_gauss", "central_gauss",
    ]
    took: dict[str, float] = {}
    engine.QUERIES["assign_nearest_fixed"](spark, sf).write.format("noop").mode("overwrite").save()  # warm up
    for name in names:
        began = time.perf_counter()
        engine.QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)
    # the cost table's grid times: 20,000 users, k' = 5 and 8, two and four parties
    grid = {}
    for r in X.x8_costs(spark, sf, k_locals=(5, 8), repeats=(2048, 4096), parties=(2, 4)).collect():
        grid[f"{r.method}_k{r.k_local}_m{r.repeats}_s{r.parties}"] = {"grid_s": round(r.grid_seconds, 4), "bytes": r.bytes}
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took,
                      "sf": os.path.basename(sf.rstrip("/")), "grid": grid}))
    spark.stop()


if __name__ == "__main__":
    main()
