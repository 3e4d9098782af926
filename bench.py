"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from critgraph import queries as core
from critgraph.runtime import materialise

HEADLINE = ("ino_lanes", "lanes_32", "ino_chunked", "breakdown_ino", "frontend_ooo", "vp_critical", "block_formats", "vector_speedup")
#: Run on one written trace, so that no model pays for making it (the paper compares models on given traces).
MODELS = ("bench_ino", "bench_ooo", "bench_ooo_approx", "bench_simulator_ino", "bench_simulator_ooo")


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "16g").config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    core.op_mix(spark, sf_dir).count()  # warm up
    times, speedup = {}, None
    made = core.traces.from_lineitem
    began = time.perf_counter()
    trace = materialise(made(spark, sf_dir), "trace")
    times["trace_written"] = round(time.perf_counter() - began, 3)
    core.traces.from_lineitem = lambda *a, **k: trace
    core.QUERIES["bench_ino"](spark, sf_dir).collect()  # starts the workers
    for name in MODELS:
        began = time.perf_counter()
        core.QUERIES[name](spark, sf_dir).collect()
        times[name] = round(time.perf_counter() - began, 3)
    core.traces.from_lineitem = made
    ratios = {x: round(times[y] / times[x], 3) for x, y in (("bench_ino", "bench_simulator_ino"), ("bench_ooo", "bench_simulator_ooo"), ("bench_ooo_approx", "bench_simulator_ooo"))}
    for name in HEADLINE:
        began = time.perf_counter()
        rows = core.QUERIES[name](spark, sf_dir).collect()
        times[name] = round(time.perf_counter() - began, 3)
        if name == "vector_speedup":
            speedup = {r["lanes"]: r["speedup"] for r in rows}
    total = round(sum(times.values()), 3)
    print(json.dumps({"metric": "total_headline_seconds", "value": total, "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")), "vector_speedup": speedup, "times_faster_than_simulator": ratios}))
    spark.stop()


if __name__ == "__main__":
    main()
