"""Ranks over a whole table, without a task that holds all of it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.sources.storage import stored


def global_ranks(df: DataFrame, order: list[str], name: str = "rank") -> DataFrame:
    """``df`` with ``name``: 0, 1, 2, ... in the order of columns that tell all rows apart. Rows are
    range-partitioned and written; a running sum over the partitions' counts gives each partition
    its first rank."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = stored(df.repartitionByRange(parts, *order).withColumn("_p", F.spark_partition_id()), "ranks")
    # one row for each partition
    before = W.orderBy("_p").rowsBetween(W.unboundedPreceding, -1)
    firsts = rows.groupBy("_p").agg(F.count("*").alias("_c")).select("_p", F.coalesce(F.sum("_c").over(before), F.lit(0)).alias("_first"))
    inside = F.row_number().over(W.partitionBy("_p").orderBy(*order)) - 1
    return rows.join(F.broadcast(firsts), "_p").withColumn(name, F.col("_first") + inside).drop("_p", "_first")


def tiles(df: DataFrame, order: list[str], n: int, name: str) -> DataFrame:
    """``df`` with ``name``: 1 to n, equal parts in order; the first parts hold the rows left over."""
    ranked = global_ranks(df, order, "_rank")
    total = ranked.count()
    size, more = divmod(total, n)
    at: Column = F.col("_rank")
    early = F.floor(at / (size + 1))
    late = more + F.floor((at - more * (size + 1)) / max(size, 1))
    return ranked.withColumn(name, (F.when(at < more * (size + 1), early).otherwise(late) + 1).cast("int")).drop("_rank")
