"""Headline timings: prints one JSON line.  ``BENCH_SF_DIR``, ``BENCH_CPUS``."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from peertrust import registry
from peertrust.queries.workloads import update_speed

QUERIES = (
    "graph_net_edges", "graph_trade_edges", "walks_scores", "power_personal", "w8_ledger_initial", "w9_ledger_update", "update_source_visit", "update_coupling",
    "w3_convergence", "w6_sybil_curves", "w14_stream_replay", "ledger_blocks",
)


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    registry.entry(spark).collect()  # starts workers and compiles
    took = {}
    for name in QUERIES:
        start = time.perf_counter()
        registry.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - start, 3)
    total = sum(took.values())
    # the published experiment: 289 peers and 667,124 blocks; five peers and twenty pairs come late
    for ledger in ("grown", "trades"):
        for r in update_speed(spark, sf_dir, ledger).collect():
            took[f"ledger_{ledger}: {r.way}"] = r.seconds
            took[f"ledger_{ledger}: {r.way}, hops"] = r.hops
    print(json.dumps({"metric": "total_s", "value": round(total, 3), "unit": "sec", "queries": took, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
