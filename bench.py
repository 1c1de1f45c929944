"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``queries`` are seconds of one warm execution each. ``items_per_sec`` are millions of items a
second of sketch construction over generated streams, by strategy, skew and sketch size, mean of
RUNS; beside them what Spark spends on each construction, and hashing alone by layout.
"""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession

from freqsketch.operators.build import build
from freqsketch.operators.measures import throughput, timed
from freqsketch.sources.generators import power_law_items
from freqsketch.spec import SketchSpec
from freqsketch.workloads import QUERIES, grid

HEADLINE = [
    "build_serial", "build_partials", "build_partials_merged", "build_relational", "build_row_owned", "build_balanced",
    "build_combined", "build_small", "build_medium", "build_large", "ablation_layout", "build_two_stage",
    "point_estimates", "heavy_hitters", "join_size_estimate", "word_heavy_hitters", "relative_error_by_decile",
    "window_sketch_tumbling", "asof_estimate", "dim_enriched_hitters",
]
#: Items and universe of the generated streams: those of the two smaller machines.
N, UNIVERSE = 1 << 25, 1 << 20
RUNS = 3
COSTS = ("seconds", "task_seconds", "shuffle_write_bytes", "spilled_bytes", "peak_execution_bytes")


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(cpus))
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.maxRecordsPerBatch", "262144")
        .config("spark.checkpoint.dir", "file://" + tempfile.mkdtemp())
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds = {}
    for name in HEADLINE:
        timed(lambda q=name: QUERIES[q](spark, sf))
        seconds[name] = round(timed(lambda q=name: QUERIES[q](spark, sf)), 3)
    rates = {}
    folder = tempfile.mkdtemp()
    for label, alpha in (("uniform", 0.0), ("zipf_1.1", 1.1), ("zipf_1.5", 1.5)):
        # the stream is stored first: a sketch reads items, it does not draw them
        power_law_items(spark.range(0, N, 1, cpus), "id", UNIVERSE, alpha).select("item").write.parquet(f"{folder}/{label}")
        items = spark.read.parquet(f"{folder}/{label}")
        for size in ("small", "medium", "large") if label == "zipf_1.1" else ("small",):
            spec = SketchSpec.preset(size)
            plans = {"row_owned": {}, "partials": {"layout": "paired"}, "combine_items": {}}
            if size == "small" and label == "zipf_1.1":
                plans |= {"partials_merged": {"layout": "merged"}, "partials_separate": {"layout": "separate"}, "row_owned_balanced": {}}
            for plan, options in plans.items():
                strategy = "partials" if plan.startswith("partials") else plan
                t = timed(lambda: build(items, "item", spec, strategy, **options), RUNS)
                rates[f"{label}/{size}/{plan}"] = round(throughput(N, t), 2)
            if size == "small" and alpha:
                # all but one worker stand still
                t = timed(lambda: build(items.coalesce(1), "item", spec, "row_owned"))
                rates[f"{label}/{size}/row_owned/one_worker"] = round(throughput(N, t), 2)
    loose = {f"{r.method}/{r.workers}/{r.alpha}": round(r.million_items_per_sec, 2) for r in grid.owned_against_relaxed(spark, runs=RUNS).collect()}
    costs = {f"{r.method}/{r['size']}": {k: round(r[k], 2) for k in COSTS} for r in grid.strategy_costs(spark, sizes=("small", "large")).collect()}
    layouts = {f"{layout}/{depth}": ns for depth, layout, ns in grid.layout_times(runs=RUNS, depths=(8,))}
    began = time.time()
    spark.stop()
    print(
        json.dumps(
            {
                "metric": "sum of headline query seconds",
                "value": round(sum(seconds.values()), 3),
                "unit": "sec",
                "queries": seconds,
                "sf": sf.rsplit("sf", 1)[-1],
                "cpus": cpus,
                "items_per_sec_millions": rates,
                "owned_against_relaxed_millions": loose,
                "costs": costs,
                "hash_ns_per_item": layouts,
                "stop_sec": round(time.time() - began, 2),
            }
        )
    )


if __name__ == "__main__":
    main()
