"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from suffixloom.plans.workloads import QUERIES

HEADLINES = ("idx_sa_dna", "mat_sa_dna", "idx_sa_rnd", "mat_sa_rnd", "idx_sa_names", "idx_sa_props", "group_sizes_w10", "self_expansion", "idx_vs_mat_bytes", "boundaries", "range_balance", "shard_load", "accumulate_batches_mid", "app_search", "app_seed_align", "memory_efficiency", "time_model_fit")


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    QUERIES["idx_sa_names"](spark, sf_dir).write.format("noop").mode("overwrite").save()  # code is compiled before times are taken
    times = {}
    for name in HEADLINES:
        began = time.time()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        times[name] = round(time.time() - began, 3)
    print(json.dumps({"metric": "suffix_array_queries_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/"))}))
    spark.stop()


if __name__ == "__main__":
    main()
