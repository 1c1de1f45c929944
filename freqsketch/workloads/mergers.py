"""Merged, grouped, subtracted and reshaped sketches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.operators import algebra as A
from freqsketch.operators.build import build, build_by_group
from freqsketch.operators.query import dense_rows as dense_rows_of
from freqsketch.oracles import cells_sql, hashed_cte, sketch_ctes, table_cte
from freqsketch.sources.storage import scratch, table
from freqsketch.workloads.common import PARTS_SQL, SPEC, STRESS, USERS_SQL, catalogue, parts

CATALOGUE, register = catalogue()


def _grouped(select: str, keys: str, spec=STRESS) -> str:
    """counts with keys, then cells with keys."""
    return f"""{table_cte(spec)}, counts AS ({select}), {hashed_cte('counts', spec)},
  cells AS (SELECT {keys}, sketch_row, sketch_col, sum(cnt)::BIGINT AS cnt FROM counts JOIN hashed USING (item) GROUP BY {keys}, sketch_row, sketch_col)"""


_BY_FLAG = _grouped("SELECT l_returnflag, l_linestatus, l_partkey AS item, count(*) AS cnt FROM lineitem GROUP BY ALL", "l_returnflag, l_linestatus")
_BY_DAY = _grouped("SELECT date_trunc('day', ts)::TIMESTAMP AS day, user_id AS item, count(*) AS cnt FROM events GROUP BY ALL", "day")


def _flags(spark: SparkSession, sf: str) -> DataFrame:
    return build_by_group(table(spark, sf, "lineitem"), ["l_returnflag", "l_linestatus"], "l_partkey", STRESS)


def _days(spark: SparkSession, sf: str) -> DataFrame:
    return build_by_group(table(spark, sf, "events").withColumn("day", F.date_trunc("day", "ts").cast("timestamp_ntz")), ["day"], "user_id", STRESS)


@register("merge_by_flag", f"WITH {_BY_FLAG} SELECT l_returnflag, sketch_row, sketch_col, sum(cnt)::BIGINT AS cnt FROM cells GROUP BY ALL")
def merge_by_flag(spark: SparkSession, sf: str) -> DataFrame:
    return A.merge_groups(_flags(spark, sf), ["l_returnflag"])


@register("merge_by_day", cells_sql(USERS_SQL, STRESS))
def merge_by_day(spark: SparkSession, sf: str) -> DataFrame:
    """Daily sketches added up are the sketch of the whole stream."""
    return A.merge_groups(_days(spark, sf), [])


@register("sketch_per_group", f"WITH {_BY_FLAG} SELECT l_returnflag, l_linestatus, sketch_row, sketch_col, cnt FROM cells")
def sketch_per_group(spark: SparkSession, sf: str) -> DataFrame:
    return _flags(spark, sf)


@register(
    "rollup_sketch_totals",
    f"WITH {_BY_FLAG} SELECT l_returnflag, l_linestatus, sum(cnt)::BIGINT AS total, count(*)::BIGINT AS cells FROM cells GROUP BY ROLLUP (l_returnflag, l_linestatus)",
)
def rollup_sketch_totals(spark: SparkSession, sf: str) -> DataFrame:
    return _flags(spark, sf).rollup("l_returnflag", "l_linestatus").agg(F.sum("cnt").alias("total"), F.count("*").alias("cells"))


_FLAG = "SELECT l_partkey AS item FROM lineitem WHERE l_returnflag = '{}'"


def _flag(spark: SparkSession, sf: str, flag: str) -> DataFrame:
    return build(table(spark, sf, "lineitem").where(F.col("l_returnflag") == flag), "l_partkey", SPEC)


@register(
    "sketch_diff",
    f"""WITH {sketch_ctes(_FLAG.format('A'), SPEC, 'a')}, {sketch_ctes(_FLAG.format('R'), SPEC, 'r')}
  SELECT sketch_row, sketch_col, coalesce(acells.cnt, 0)::BIGINT AS left_cnt, coalesce(rcells.cnt, 0)::BIGINT AS right_cnt
  FROM acells FULL JOIN rcells USING (sketch_row, sketch_col) WHERE coalesce(acells.cnt, 0) <> coalesce(rcells.cnt, 0)""",
)
def sketch_diff(spark: SparkSession, sf: str) -> DataFrame:
    return A.difference(_flag(spark, sf, "A"), _flag(spark, sf, "R"))


@register("subtract_window", cells_sql("SELECT user_id AS item FROM events WHERE ts >= TIMESTAMP '2024-01-08'", SPEC))
def subtract_window(spark: SparkSession, sf: str) -> DataFrame:
    """The first week expires: it is taken away from the whole."""
    ev = table(spark, sf, "events")
    week = ev.where(F.col("ts") < F.lit("2024-01-08").cast("timestamp_ntz"))
    return A.subtract(build(ev, "user_id", SPEC), build(week, "user_id", SPEC))


@register("row_totals_invariant", "SELECT range::INTEGER AS sketch_row, (SELECT count(*) FROM lineitem)::BIGINT AS total FROM range(8)")
def row_totals_invariant(spark: SparkSession, sf: str) -> DataFrame:
    return A.row_totals(build(parts(spark, sf), "item", SPEC))


@register(
    "dense_rows",
    f"""WITH {sketch_ctes(PARTS_SQL, STRESS)} SELECT r.range::INTEGER AS sketch_row, string_agg(coalesce(cnt, 0)::VARCHAR, ',' ORDER BY c.range) AS counters
  FROM range({STRESS.depth}) r CROSS JOIN range({STRESS.width}) c LEFT JOIN cells ON sketch_row = r.range AND sketch_col = c.range GROUP BY r.range""",
)
def dense_rows(spark: SparkSession, sf: str) -> DataFrame:
    rows = dense_rows_of(build(parts(spark, sf), "item", STRESS), STRESS)
    return rows.select("sketch_row", F.array_join(F.col("counters").cast("array<string>"), ",").alias("counters"))


@register(
    "pivot_rows",
    f"""WITH {sketch_ctes(PARTS_SQL, STRESS)} SELECT sketch_col, {', '.join(f'sum(cnt) FILTER (sketch_row = {r})::BIGINT AS row_{r}' for r in range(4))} FROM cells GROUP BY sketch_col""",
)
def pivot_rows(spark: SparkSession, sf: str) -> DataFrame:
    p = build(parts(spark, sf), "item", STRESS).groupBy("sketch_col").pivot("sketch_row", [0, 1, 2, 3]).sum("cnt")
    return p.select("sketch_col", *[F.col(str(r)).alias(f"row_{r}") for r in range(4)])


@register("sketch_roundtrip", cells_sql(PARTS_SQL, SPEC))
def sketch_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    path = scratch(spark, "cells")
    A.write_cells(build(parts(spark, sf), "item", SPEC), path)
    return spark.read.parquet(path).select("sketch_row", "sketch_col", "cnt")


