"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINE = (
    "triangle_multiway_extend", "triangle_pairwise", "hub_triangle_multiway", "hub_triangle_grid", "lookahead_bag_sizes", "lookahead_variable_marginals",
    "toy_marginals_plain", "toy_marginals_projected", "toy_marginals_pairwise", "toy_marginals_hybrid", "toy_marginals_dense", "toy_marginals_circuit", "toy_marginals_joingraph",
    "star_variable_marginals", "star_marginals_pairwise", "event_chain_marginals", "clique_marginals", "grid_thinned_marginals", "hash_product", "sort_merge_product",
)


def main() -> None:
    from pyspark.sql import SparkSession

    from bagjoin.queries import QUERIES

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").config("spark.sql.autoBroadcastJoinThreshold", "64m").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    QUERIES["toy_marginals_pairwise"](spark, sf_dir).write.format("noop").mode("overwrite").save()  # warm-up
    times = {}
    for name in HEADLINE:
        began = time.perf_counter()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - began, 3)
        print(f"{name}: {times[name]}", file=sys.stderr, flush=True)
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/"))}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
