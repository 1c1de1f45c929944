"""Estimates from sketches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from freqsketch.functions.hashing import columns_udf, hashes_udf, with_cells
from freqsketch.spec import SketchSpec

#: Cells below this number are sent to every task; more are joined by shuffle. 4 million cells
#: are about 64 MB.
BROADCAST_CELLS = 4_000_000


def small(cells: DataFrame, spec: SketchSpec) -> DataFrame:
    """Cells with a broadcast hint if the spec bounds them: a sketch has depth * width cells
    however long its stream was."""
    return F.broadcast(cells) if spec.depth * spec.width <= BROADCAST_CELLS else cells


def cell_counts(cells: DataFrame, items: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """(item, sketch_row, cnt) with 0 for counters that were never touched."""
    asked = with_cells(items.select(item), item, spec)
    found = asked.join(small(cells, spec), ["sketch_row", "sketch_col"], "left")
    return found.select(item, "sketch_row", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def estimate(cells: DataFrame, items: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """(item, estimate): the least of an item's counters; never below its true count."""
    return cell_counts(cells, items, item, spec).groupBy(item).agg(F.min("cnt").alias("estimate"))


def dense_rows(cells: DataFrame, spec: SketchSpec) -> DataFrame:
    """(sketch_row, counters): one array of ``width`` counters for each row, filled in one pass."""

    def fill(table: pa.Table) -> pa.Table:
        dense = np.zeros(spec.width, np.int64)
        dense[table.column("sketch_col").to_numpy()] = table.column("cnt").to_numpy()
        return pa.table({"sketch_row": pa.array([table.column("sketch_row")[0].as_py()], pa.int32()), "counters": pa.array([dense], pa.list_(pa.int64()))})

    return cells.select("sketch_row", "sketch_col", "cnt").groupBy("sketch_row").applyInArrow(fill, "sketch_row int, counters array<bigint>")


def estimate_dense(rows: DataFrame, items: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """Estimates from dense rows: ``depth`` records, gathered in one array; no shuffle of items.
    A sketch of more than BROADCAST_CELLS cells is joined as cells instead."""
    if spec.depth * spec.width > BROADCAST_CELLS:
        cells = rows.select("sketch_row", F.posexplode("counters").alias("sketch_col", "cnt"))
        return estimate(cells, items, item, spec)
    table = rows.groupBy(F.lit(1).alias("_one")).agg(F.array_sort(F.collect_list(F.struct("sketch_row", "counters"))).alias("_t"))
    asked = items.select(item, columns_udf(spec)(F.col(item)).alias("_c"), F.lit(1).alias("_one"))
    # a row that was never touched has no record: its counters are 0
    picked = F.transform(F.sequence(F.lit(0), F.lit(spec.depth - 1)), lambda r: F.coalesce(
        F.get(F.get(F.filter("_t", lambda t: t["sketch_row"] == r), F.lit(0))["counters"], F.get("_c", r)), F.lit(0)))
    return asked.join(F.broadcast(table), "_one").select(item, F.array_min(picked).cast("long").alias("estimate"))


def with_exact(estimates: DataFrame, counts: DataFrame, item: str) -> DataFrame:
    return estimates.join(counts.withColumnRenamed("cnt", "exact"), item, "left").withColumn("exact", F.coalesce("exact", F.lit(0)))


def exact_counts(df: DataFrame, item: str) -> DataFrame:
    return df.where(F.col(item).isNotNull()).groupBy(F.col(item).cast("long").alias("item")).agg(F.count("*").alias("cnt"))


def heavy_hitters(estimates: DataFrame, total: int | Column, phi: float) -> DataFrame:
    """Items whose estimate reaches phi * total; none that truly does is missed."""
    return estimates.where(F.col("estimate") >= phi * F.lit(total))


def rare_items(estimates: DataFrame, most: int) -> DataFrame:
    """Items whose estimate is ``most`` at most; each of them truly is as rare."""
    return estimates.where(F.col("estimate") <= most)


def inner_product(a: DataFrame, b: DataFrame, spec: SketchSpec) -> DataFrame:
    """One row, ``join_size``: an upper estimate of the rows that an equi-join makes."""
    other = b.withColumnRenamed("cnt", "_cnt")
    per_row = a.join(small(other, spec), ["sketch_row", "sketch_col"]).groupBy("sketch_row").agg(F.sum(F.col("cnt") * F.col("_cnt")).alias("_p"))
    return per_row.agg(F.min("_p").alias("join_size"))


def signed_cells(df: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """(item, sketch_row, sketch_col, sign): the sign is the top bit of the hash value."""
    h = df.select(item, F.posexplode(hashes_udf(spec)(F.col(item))).alias("sketch_row", "_h"))
    sign = 1 - 2 * F.shiftright("_h", 31).bitwiseAND(F.lit(1))
    return h.select(item, "sketch_row", (F.col("_h") % spec.width).cast("int").alias("sketch_col"), sign.alias("sign"))


def estimate_signed(df: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """(item, estimate) by the median over rows of signed counters: unbiased, two-sided."""
    counts = exact_counts(df, item)
    cells = signed_cells(counts, "item", spec)
    table = cells.join(counts, "item").groupBy("sketch_row", "sketch_col").agg(F.sum(F.col("sign") * F.col("cnt")).alias("_s"))
    back = cells.join(small(table, spec), ["sketch_row", "sketch_col"])
    return back.groupBy("item").agg(F.expr("percentile(sign * _s, 0.5)").alias("estimate"))


def estimate_corrected(cells: DataFrame, items: DataFrame, item: str, spec: SketchSpec, total: int | Column) -> DataFrame:
    """(item, estimate): the median over rows of counters less the noise that the rest of the
    stream leaves in a counter on average, and never above the least counter."""
    c = cell_counts(cells, items, item, spec)
    clean = F.col("cnt") - (F.lit(total) - F.col("cnt")) / float(max(1, spec.width - 1))
    agg = c.withColumn("_e", clean).groupBy(item).agg(F.expr("percentile(_e, 0.5)").alias("_m"), F.min("cnt").alias("_least"))
    return agg.select(item, F.least("_m", F.col("_least").cast("double")).alias("estimate"))
