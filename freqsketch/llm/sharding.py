"""Contiguous byte-balanced shards from global prefix sums (operator 9)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import read_table, settled, written

N_SHARDS = 8


def byte_prefix_shards(
    df: DataFrame,
    order_by: list[Column],
    size: Column,
    n_shards: int,
    keep: dict[str, Column],
    parts: int | None = None,
) -> DataFrame:
    """Deal rows, in the order given, into ``n_shards`` contiguous shards of near-equal size.

    Rows are range-partitioned by the order, each partition's total becomes one row of a
    small table whose running sum gives the partition's global start, and a row belongs to
    the shard in which the middle of its bytes falls; so each cut is at most half a row away
    from its target. ``slot`` counts from 0 in each shard without gaps.

    Only the columns of ``keep`` and the size travel. Rows equal in the order keep a fixed
    but arbitrary order. Null sizes count 0; an empty table gives an empty result; with a
    total of 0 all rows go to shard 0. Input columns of any other name are ignored.
    """
    spark = df.sparkSession
    n_parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    keys = [f"_k{i}" for i in range(len(order_by))]
    rows = df.select(
        *[c.alias(f"_v_{k}") for k, c in keep.items()],
        F.coalesce(size.cast("long"), F.lit(0)).alias("_size"),
        *[c.alias(k) for k, c in zip(keys, order_by)],
        F.monotonically_increasing_id().alias("_tie"),
    )
    rows = written(rows.repartitionByRange(n_parts, *keys, "_tie").withColumn("_part", F.spark_partition_id()), "ranges", keep=True)
    before = W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    totals = (
        rows.groupBy("_part")
        .agg(F.sum("_size").alias("_bytes"), F.count("*").alias("_rows"))
        .select(
            "_part",
            F.coalesce(F.sum("_bytes").over(before), F.lit(0)).alias("_bytes0"),
            F.coalesce(F.sum("_rows").over(before), F.lit(0)).alias("_rows0"),
            F.sum("_bytes").over(W.partitionBy(F.lit(0))).alias("_total"),
        )
    )
    inside = W.partitionBy("_part").orderBy(*keys, "_tie").rowsBetween(W.unboundedPreceding, -1)
    # one row for each partition: bounded by the partition count, whatever the table's size
    placed = rows.join(F.broadcast(totals), "_part").select(
        *[F.col(f"_v_{k}").alias(k) for k in keep],
        F.col("_size").alias("size"),
        (F.col("_rows0") + F.count("*").over(inside)).alias("_index"),
        (F.col("_bytes0") + F.coalesce(F.sum("_size").over(inside), F.lit(0))).alias("start"),
        "_total",
    )
    shard = F.when(F.col("_total") == 0, F.lit(0)).otherwise(
        F.least(F.lit(n_shards - 1), F.expr(f"(start * 2 + size) * {n_shards} div (_total * 2)"))
    )
    placed = placed.withColumn("shard", shard.cast("int"))
    firsts = placed.groupBy("shard").agg(F.min("_index").alias("_first"))
    return placed.join(F.broadcast(firsts), "shard").select(
        *keep, "size", "start", "shard", (F.col("_index") - F.col("_first")).alias("slot")
    )


@settled
def op9_byte_prefix_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shard and slot of every document, in order of ``doc_id``; see ``byte_prefix_shards``."""
    docs = read_table(spark, sf_dir, "documents")
    utf8 = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    keep = {"doc_id": F.col("doc_id"), "text_crc32": F.crc32(utf8)}
    out = byte_prefix_shards(docs, [F.col("doc_id")], F.length(utf8) + 1, N_SHARDS, keep)
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )


#: Fixed value: the reversed polynomial of CRC-32; the table of 256 remainders follows from it.
CRC32_POLYNOMIAL = 0xEDB88320

#: The whole query in SQL, for tables whose ``doc_id`` is unique.
OP9_SQL = f"""
WITH RECURSIVE bit(k, n, v) AS (
  SELECT 0, range::BIGINT, range::BIGINT FROM range(256)
  UNION ALL SELECT k + 1, n, CASE WHEN v & 1 = 1 THEN xor(v >> 1, {CRC32_POLYNOMIAL}) ELSE v >> 1 END FROM bit WHERE k < 8),
remainders AS (SELECT list(v ORDER BY n) AS r FROM bit WHERE k = 8),
b AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
c AS (SELECT doc_id, (length(h) // 2 + 1)::BIGINT AS size,
    xor(4294967295, list_reduce(list_prepend(4294967295::BIGINT, list_transform(regexp_extract_all(h, '..'), lambda x: ('0x' || x)::BIGINT)),
      lambda x, y: xor(x >> 8, r[(xor(x, y) & 255) + 1])))::BIGINT AS text_crc32
  FROM b, remainders),
p AS (SELECT *, sum(size) OVER (ORDER BY doc_id NULLS FIRST)::BIGINT - size AS start, (SELECT sum(size) FROM c)::BIGINT AS total FROM c),
s AS (SELECT *, least({N_SHARDS - 1}, (start * 2 + size) * {N_SHARDS} // (total * 2))::INTEGER AS shard FROM p)
SELECT doc_id, size, text_crc32, 'bytes' AS law, shard,
  row_number() OVER (PARTITION BY shard ORDER BY start) - 1 AS slot, NULL::INTEGER AS grown_shard
FROM s
"""
