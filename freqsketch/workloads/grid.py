"""The experiment grids: run time and throughput of constructions over generated streams."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from freqsketch.functions.hashing import columns
from freqsketch.operators.build import build, build_relaxed
from freqsketch.operators.costs import COST_SCHEMA, spark_costs
from freqsketch.operators.measures import memory_bits, throughput, timed
from freqsketch.sources.generators import power_law_items
from freqsketch.sources.storage import scratch
from freqsketch.spec import BATCH, SketchSpec
from freqsketch.streaming.balance import BalancedBuilder

#: The skews and the sketch sizes of the experiments.
ALPHAS = (0.0, 1.1, 1.5)
SIZES = ("small", "medium", "large")
#: Label, strategy and options: tables per worker without and with merged tabulation, one owned
#: table, and the same balanced.
METHODS = {
    "per_worker": ("partials", {"layout": "separate"}),
    "per_worker_merged": ("partials", {"layout": "merged"}),
    "one_table": ("row_owned", {}),
    "one_table_balanced": ("row_owned_balanced", {}),
}


def stored_stream(spark: SparkSession, n: int, universe: int, alpha: float) -> DataFrame:
    """(pos, item), written first: a sketch reads items, it does not draw them."""
    path = scratch(spark, "stream")
    power_law_items(spark.range(n), "id", universe, alpha).write.parquet(path)
    return spark.read.parquet(path)


def time_grid(spark: SparkSession, n: int = 1 << 22, universe: int = 1 << 20, runs: int = 10, alphas=ALPHAS, sizes=SIZES, methods=tuple(METHODS)) -> DataFrame:
    """(method, size, alpha, seconds, million_items_per_sec, memory_bits)."""
    workers = spark.sparkContext.defaultParallelism
    rows = []
    for alpha in alphas:
        items = stored_stream(spark, n, universe, alpha)
        for size in sizes:
            spec = SketchSpec.preset(size)
            for m in methods:
                strategy, options = METHODS[m]
                t = timed(lambda: build(items, "item", spec, strategy, **options), runs)
                bits = memory_bits(spec, n, workers, "partials" if strategy == "partials" else "row_owned", BATCH)
                rows.append((m, size, alpha, t, throughput(n, t), bits))
    return spark.createDataFrame(rows, "method string, size string, alpha double, seconds double, million_items_per_sec double, memory_bits long")


def owned_against_relaxed(spark: SparkSession, n: int = 1 << 20, universe: int = 1 << 16, runs: int = 10, alphas=(1.1, 1.5)) -> DataFrame:
    """(method, workers, alpha, million_items_per_sec): the owned table against the model of the
    table without atomic updates, with one worker and with all."""
    all_ = spark.sparkContext.defaultParallelism
    spec, rows = SketchSpec.preset("small"), []
    for alpha in alphas:
        s = stored_stream(spark, n, universe, alpha)
        for workers in (1, all_):
            owned = timed(lambda: build(s.coalesce(workers), "item", spec, "row_owned"), runs)
            loose = timed(lambda: build_relaxed(s.coalesce(workers), "pos", "item", spec, workers, n), runs)
            rows += [("row_owned", workers, alpha, throughput(n, owned)), ("shared_relaxed", workers, alpha, throughput(n, loose))]
    return spark.createDataFrame(rows, "method string, workers int, alpha double, million_items_per_sec double")


def layout_times(items: int = 1 << 21, runs: int = 10, depths=(1, 4, 8, 16)) -> list[tuple[int, str, float]]:
    """(depth, layout, nanoseconds an item) of hashing alone, on one core."""
    x = np.random.default_rng(0).integers(0, 1 << 32, items)
    out = []
    for depth in depths:
        for layout in ("separate", "merged", "paired"):
            spec = SketchSpec(depth)
            columns(x[:1000], spec, layout)
            spent = []
            for _ in range(runs):
                began = time.perf_counter()
                columns(x, spec, layout)
                spent.append(time.perf_counter() - began)
            out.append((depth, layout, round(1e9 * sum(spent) / runs / items, 1)))
    return out


def strategy_costs(spark: SparkSession, n: int = 1 << 22, universe: int = 1 << 20, alpha: float = 1.1, sizes=SIZES) -> DataFrame:
    """(method, size, COST_SCHEMA): what Spark spends on each construction."""
    s = stored_stream(spark, n, universe, alpha)
    rows = []
    for size in sizes:
        spec = SketchSpec.preset(size)
        for method, strategy in (("per_worker", "partials"), ("one_table", "row_owned"), ("one_table_balanced", "row_owned_balanced"), ("shared_atomic", "shared_atomic"), ("items_first", "combine_items")):
            rows.append((method, size, *spark_costs(build(s, "item", spec, strategy))))
    return spark.createDataFrame(rows, f"method string, size string, {COST_SCHEMA}")


def measured_split(spark: SparkSession, batches: int = 12, batch: int = 1 << 20, pace: dict[str, int] | None = None) -> DataFrame:
    """The trace of controllers that are fed by measured times, with slow workers that do their work
    ``pace`` times over."""
    builder = BalancedBuilder(spark, SketchSpec.preset("small"), batch, pace=pace or {"hash": 4, "update": 2})
    for k in range(batches):
        builder.add(power_law_items(spark.range(k * batch, (k + 1) * batch), "id", 1 << 20, 1.1), "item", k)
    return builder.trace_rows()
