"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.functions.hashing import with_cells
from freqsketch.spec import BATCH, SketchSpec


def bits(n: int) -> int:
    return max(1, math.ceil(math.log2(n)))


def memory_bits(spec: SketchSpec, n: int, workers: int, strategy: str, batch: int = BATCH) -> int:
    """Bits of counters and buffers: a table for each worker, or one table and a batch buffer."""
    if strategy == "partials":
        return spec.depth * spec.width * workers * bits(n)
    return spec.depth * (spec.width * bits(n) + batch * bits(spec.width))


def table_bytes(spec: SketchSpec, counter_bytes: int = 8) -> int:
    return counter_bytes * spec.depth * spec.width


def lookup_cost(spec: SketchSpec, layout: str, entry_bytes: int = 4, line: int = 64) -> tuple[int, int]:
    """(table places, cache lines) that hashing one item touches."""
    if layout == "merged":
        return spec.chars, spec.chars * -(-spec.depth * entry_bytes // line)
    return spec.chars * spec.depth, spec.chars * spec.depth


def sync_cost(strategy: str, spec: SketchSpec, n: int, batch: int, workers: int) -> dict[str, int]:
    """Barriers, atomic updates or locks, and additions of a final merge."""
    out = {"barriers": 0, "atomics": 0, "merge_additions": 0}
    if strategy == "row_owned":
        out["barriers"] = -(-n // batch)
    elif strategy in ("shared_atomic", "shared_locked"):
        out["atomics"] = n * spec.depth
    elif strategy == "partials":
        out["merge_additions"] = spec.depth * spec.width * workers
    return out


def accuracy(joined: DataFrame, spec: SketchSpec, total: Column, eps: float | None = None) -> DataFrame:
    """One row of error measures over (item, estimate, exact)."""
    excess = F.col("estimate") - F.col("exact")
    limit = F.lit(eps if eps is not None else math.e / spec.width) * total
    return joined.agg(
        F.count("*").alias("items"),
        F.sum("exact").alias("n_stream"),
        F.round(F.avg(excess), 6).alias("mean_excess"),
        F.min(excess).alias("min_excess"),
        F.max(excess).alias("max_excess"),
        F.round(F.avg(excess / F.col("exact")), 6).alias("mean_relative"),
        F.round(F.sqrt(F.avg(excess * excess)), 6).alias("rmse"),
        F.sum((excess >= limit).cast("long")).alias("violations"),
        F.sum((excess < 0).cast("long")).alias("under_items"),
    )


def effective_width(cells: DataFrame, share: float = 0.9) -> DataFrame:
    """(sketch_row, counters): fewest counters that hold ``share`` of a row's updates."""
    by_row = W.partitionBy("sketch_row").orderBy(F.desc("cnt"), "sketch_col").rowsBetween(W.unboundedPreceding, -1)
    run = cells.withColumn("_before", F.coalesce(F.sum("cnt").over(by_row), F.lit(0))).withColumn("_all", F.sum("cnt").over(W.partitionBy("sketch_row")))
    return run.where(F.col("_before") < share * F.col("_all")).groupBy("sketch_row").agg(F.count("*").alias("counters"))


def conflicts(df: DataFrame, pos: str, item: str, spec: SketchSpec, lanes: int, n: int, line: int = 16) -> DataFrame:
    """One row: updates, and those that meet another lane's in the same tick on the same counter
    or the same line of counters. With row owners both are 0, as a row has one writer."""
    tick = F.col("pos") % -(-n // lanes)
    c = with_cells(df.select(F.col(pos).alias("pos"), F.col(item).cast("long").alias("item")), "item", spec)
    c = c.select("sketch_row", "sketch_col", F.floor(F.col("sketch_col") / line).alias("_line"), tick.alias("_tick"))
    # two levels of counting instead of two distinct counts over one input
    cells = c.groupBy("_tick", "sketch_row", "_line", "sketch_col").agg(F.count("*").alias("_n"))
    lines = cells.groupBy("_tick", "sketch_row", "_line").agg(F.sum("_n").alias("_n"), F.count("*").alias("_c"))
    return lines.agg(
        F.sum("_n").alias("updates"),
        (F.sum("_n") - F.sum("_c")).alias("cell_conflicts"),
        (F.sum("_n") - F.count("*")).alias("line_conflicts"),
    )


def timed(make, runs: int = 1) -> float:
    """Mean seconds of executing a DataFrame without keeping its rows."""
    spent = []
    for _ in range(runs):
        df = make()
        t = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        spent.append(time.perf_counter() - t)
    return sum(spent) / len(spent)


def throughput(n: int, seconds: float) -> float:
    """Million items a second."""
    return n / seconds / 1e6


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
