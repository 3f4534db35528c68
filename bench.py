"""Runs the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

HEADLINE = [
    "replica_pair_sizes", "phase1_stop", "hybrid_bytes", "cell_stream_result", "parity_result", "sign_sum_estimate", "full_transfer_bytes",
    "filter_semijoin", "lagging_replica_events", "method_times",
]


#: Published or implied bytes by similarity (n = 100,000): metadata of the hybrid, and of all digests' sketch.
KNOWN = {"100": 36_067, "95": 127_757, "85": 171_624, "50": 218_329, "20": 202_276, "0": 158_102}


def main() -> None:
    from pyspark.sql import SparkSession

    folder, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "16g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from setsync import catalogue

    known = catalogue.queries()
    names = sys.argv[1:] or HEADLINE
    spark.range(1000).selectExpr("sum(id)").collect()
    took, measured = {}, {}
    for name in names:
        began = time.perf_counter()
        found = known[name](spark, folder)
        if name == "hybrid_bytes":
            measured["hybrid_metadata_bytes"] = {r.run_id.split("/")[0]: {"measured": int(r.metadata_core_bytes), "expected": KNOWN.get(r.run_id.split("/")[0])} for r in found.collect()}
        elif name == "method_times":
            measured["method_ms"] = {f"{r.method} {r.run_id.split('/')[0]}": [round(r.encode_ms, 1), round(r.decode_ms, 1)] for r in found.collect()}
        else:
            found.write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)
        spark.catalog.clearCache()
    print(json.dumps({"metric": "headline queries, total wall time", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(folder.rstrip("/")).removeprefix("sf"), **measured}))


if __name__ == "__main__":
    main()
