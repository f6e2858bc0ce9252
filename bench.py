"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from walkfold.plans import catalog

HEADLINE = (
    "sssp_part", "hand_sssp", "hops_part", "widest_part", "hand_wp", "wsp_weight_part", "unfused_wsp", "radius_part", "unfused_radius", "drr_cust_supp", "unfused_drr", "trust_users", "unfused_trust",
    "rds_part", "unfused_rds", "cc_cust_supp", "hand_cc", "bfs_cust_supp", "hand_bfs", "pagerank_pages", "path_count_catalog", "edges_part", "two_hop_part",
)

WARM_UP = ("edges_part", "sssp_part", "hand_sssp")


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.cleaner.referenceTracking.cleanCheckpoints", "true")
        .config("spark.checkpoint.dir", os.environ.get("BENCH_TMP", "file:///tmp/walkfold-bench"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    for name in WARM_UP:  # class loading and compilation; not timed, on the smallest tables
        catalog.QUERIES[name](spark, "/root/testdata/sf0.001").write.format("noop").mode("overwrite").save()
    took = {}
    for name in HEADLINE:
        at = time.perf_counter()
        catalog.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - at, 3)
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
