"""Sketches of windows; every stream has a batch twin as its oracle."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.functions.hashing import with_cells
from freqsketch.operators.build import build, build_by_group
from freqsketch.oracles import cells_sql, hashed_cte, table_cte
from freqsketch.sources.storage import csv_copy, rate_stream, scratch, stored, stream, table
from freqsketch.streaming.windows import deduplicated, drain, event_time, merge_into_table, session_cells, window_cells
from freqsketch.workloads.common import STRESS, catalogue

CATALOGUE, register = catalogue()
_HASH = f"{table_cte(STRESS)}, ev AS (SELECT ts, event_type, user_id AS item FROM events), {hashed_cte('ev', STRESS)}"
_DAYS = f"WITH {_HASH} SELECT date_trunc('day', ts)::TIMESTAMP AS win_start, sketch_row, sketch_col, count(*)::BIGINT AS cnt FROM ev JOIN hashed USING (item) GROUP BY ALL"


@register("window_sketch_tumbling", _DAYS)
def window_sketch_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return drain(window_cells(stream(spark, sf, "events"), "ts", "user_id", STRESS, "1 day"), "tumbling")


@register(
    "window_sketch_sliding",
    f"""WITH {_HASH}, s AS (SELECT item, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01') - k.range * INTERVAL 6 HOUR AS win_start FROM ev, range(4) k)
  SELECT win_start::TIMESTAMP AS win_start, sketch_row, sketch_col, count(*)::BIGINT AS cnt FROM s JOIN hashed USING (item) GROUP BY ALL""",
)
def window_sketch_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return drain(window_cells(stream(spark, sf, "events"), "ts", "user_id", STRESS, "1 day", "6 hours"), "sliding")


@register(
    "window_sketch_session",
    f"""WITH {_HASH}, g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM ev WINDOW w AS (PARTITION BY event_type ORDER BY ts)),
  s AS (SELECT *, sum(fresh) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g),
  v AS (SELECT event_type, item, min(ts) OVER (PARTITION BY event_type, n)::TIMESTAMP AS win_start FROM s)
  SELECT event_type, win_start, sketch_row, sketch_col, count(*)::BIGINT AS cnt FROM v JOIN hashed USING (item) GROUP BY ALL""",
)
def window_sketch_session(spark: SparkSession, sf: str) -> DataFrame:
    return session_cells(table(spark, sf, "events"), "ts", "user_id", "event_type", STRESS, "30 minutes")


@register("daily_sketch", _DAYS)
def daily_sketch(spark: SparkSession, sf: str) -> DataFrame:
    ev = table(spark, sf, "events").withColumn("win_start", F.date_trunc("day", "ts").cast("timestamp_ntz"))
    return build_by_group(ev, ["win_start"], "user_id", STRESS)


@register("stream_equals_batch", "SELECT (SELECT count(DISTINCT date_trunc('day', ts)) FROM events)::BIGINT AS windows, 0::BIGINT AS different")
def stream_equals_batch(spark: SparkSession, sf: str) -> DataFrame:
    s, b = window_sketch_tumbling(spark, sf), daily_sketch(spark, sf).withColumnRenamed("cnt", "_b")
    both = s.join(b, ["win_start", "sketch_row", "sketch_col"], "full")
    different = F.sum((~F.col("cnt").eqNullSafe(F.col("_b"))).cast("long"))
    return both.agg(F.countDistinct("win_start").alias("windows"), different.alias("different"))


_ARRIVAL = "event_id + ('0x' || substr(md5('late:' || event_id), 1, 8))::BIGINT % 200"


@register(
    "late_data_effect",
    f"""WITH a AS (SELECT ts, {_ARRIVAL} AS arrival, event_id FROM events), o AS (SELECT ts, max(ts) OVER (ORDER BY arrival, event_id ROWS UNBOUNDED PRECEDING) AS seen FROM a)
  SELECT h::INTEGER AS delay_hours, count(*)::BIGINT AS n_events, count(*) FILTER (ts < seen - h * INTERVAL 1 HOUR)::BIGINT AS n_late FROM o, (VALUES (1), (3), (6), (12)) t(h) GROUP BY h""",
)
def late_data_effect(spark: SparkSession, sf: str) -> DataFrame:
    """Events that a watermark of each delay would call late, had they arrived in a fixed shuffled
    order. The running maximum is taken per block of arrivals, then over the blocks before."""
    ev = table(spark, sf, "events")
    arrival = F.col("event_id") + F.conv(F.substring(F.md5(F.concat(F.lit("late:"), F.col("event_id"))), 1, 8), 16, 10).cast("long") % 200
    a = ev.select("ts", arrival.alias("arrival"), "event_id").withColumn("_b", F.floor(F.col("arrival") / 4096))
    inside = F.max("ts").over(W.partitionBy("_b").orderBy("arrival", "event_id").rowsBetween(W.unboundedPreceding, 0))
    before = a.groupBy("_b").agg(F.max("ts").alias("_m")).select("_b", F.max("_m").over(W.orderBy("_b").rowsBetween(W.unboundedPreceding, -1)).alias("_before"))
    seen = a.withColumn("_in", inside).join(before, "_b").withColumn("seen", F.greatest("_in", "_before"))
    hours = seen.withColumn("delay_hours", F.explode(F.array(*[F.lit(h) for h in (1, 3, 6, 12)])))
    late = F.col("ts") < F.col("seen") - F.make_dt_interval(hours=F.col("delay_hours"))
    return hours.groupBy("delay_hours").agg(F.count("*").alias("n_events"), F.sum(late.cast("long")).alias("n_late"))


_USERS_CELLS = cells_sql("SELECT user_id AS item FROM events", STRESS)


@register("stream_merged_into_table", _USERS_CELLS)
def stream_merged_into_table(spark: SparkSession, sf: str) -> DataFrame:
    """A stored sketch that micro-batches of a folder of files are added to."""
    folder = scratch(spark, "event-files")
    table(spark, sf, "events").repartition(3, "event_id").write.parquet(folder)
    schema = table(spark, sf, "events").schema
    return merge_into_table(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder), "user_id", STRESS, "stored-sketch")


@register("stream_without_repeats", _USERS_CELLS)
def stream_without_repeats(spark: SparkSession, sf: str) -> DataFrame:
    """Every event comes twice and counts once."""
    folder = scratch(spark, "event-files")
    ev = table(spark, sf, "events")
    ev.unionByName(ev).write.parquet(folder)
    once = deduplicated(spark.readStream.schema(ev.schema).parquet(folder), "ts", ["event_id"], "60 days")
    cells = with_cells(once.select(F.col("user_id").cast("long").alias("_item")), "_item", STRESS)
    return drain(cells.select("sketch_row", "sketch_col"), "once", "append").groupBy("sketch_row", "sketch_col").agg(F.count("*").alias("cnt"))


_BATCHES = 5


@register(
    "watermark_drops",
    f"""WITH a AS (SELECT ts, {_ARRIVAL} AS arrival, event_id FROM events), n AS (SELECT max(arrival) + 1 AS n FROM a),
  b AS (SELECT ts, arrival * {_BATCHES} // n AS batch FROM a, n),
  m AS (SELECT batch, max(max(ts)) OVER (ORDER BY batch ROWS BETWEEN UNBOUNDED PRECEDING AND 2 PRECEDING) - INTERVAL 1 HOUR AS mark FROM b GROUP BY batch)
  SELECT date_trunc('hour', ts)::TIMESTAMP AS win_start, count(*)::BIGINT AS cnt FROM b JOIN m USING (batch)
  WHERE mark IS NULL OR date_trunc('hour', ts) + INTERVAL 1 HOUR > date_trunc('milliseconds', mark) GROUP BY 1""",
)
def watermark_drops(spark: SparkSession, sf: str) -> DataFrame:
    """Hourly counts of a stream that arrives out of order, with a watermark of an hour: events whose
    window has closed are dropped by Spark. It judges lateness by the watermark that the batch
    before went by, which rests on the batches before that one."""
    folder = scratch(spark, "late-files")
    ev = table(spark, sf, "events")
    arrival = F.col("event_id") + F.conv(F.substring(F.md5(F.concat(F.lit("late:"), F.col("event_id"))), 1, 8), 16, 10).cast("long") % 200
    a = stored(ev.select("ts", arrival.alias("arrival")), "arrivals")
    n = a.agg(F.max("arrival")).first()[0] + 1
    placed = a.withColumn("batch", F.floor(F.col("arrival") * _BATCHES / n))
    for k in range(_BATCHES):  # one file after the other: a file source takes them by age
        placed.where(F.col("batch") == k).select("ts").coalesce(1).write.mode("append").parquet(folder)
        time.sleep(0.05)
    late = event_time(spark.readStream.schema("ts timestamp_ntz").option("maxFilesPerTrigger", 1).parquet(folder), "ts").withWatermark("ts", "1 hour")
    counts = late.groupBy(F.window("ts", "1 hour").alias("_w")).agg(F.count("*").alias("cnt"))
    out = drain(counts.select(F.col("_w.start").cast("timestamp_ntz").alias("win_start"), "cnt"), "late", "update")
    return out.groupBy("win_start").agg(F.max("cnt").alias("cnt"))


@register("rate_source_sketch", cells_sql("SELECT range AS item FROM range(1000)", STRESS))
def rate_source_sketch(spark: SparkSession, sf: str) -> DataFrame:
    """Cells of the first micro-batch of a generated stream."""
    cells = with_cells(rate_stream(spark, 1000).where("value < 1000").select(F.col("value").alias("_item")), "_item", STRESS)
    return drain(cells.groupBy("sketch_row", "sketch_col").agg(F.count("*").alias("cnt")), "rate")


@register("csv_source_sketch", cells_sql("SELECT l_partkey AS item FROM lineitem", STRESS))
def csv_source_sketch(spark: SparkSession, sf: str) -> DataFrame:
    return build(csv_copy(table(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_returnflag")), "l_partkey", STRESS)
