"""Streams and specs that the workloads share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.functions.keys import fingerprint, words
from freqsketch.sources.generators import zipf_stream
from freqsketch.sources.storage import table
from freqsketch.spec import SketchSpec

SPEC = SketchSpec()
#: Narrow tables, in which items collide.
STRESS = SketchSpec(4, 257)
ZIPF_N = 1024
LANES = 8
PARTS_SQL = "SELECT l_partkey AS item FROM lineitem"
USERS_SQL = "SELECT user_id AS item FROM events"

Query = Callable[[SparkSession, str], DataFrame]


def catalogue() -> tuple[dict, Callable]:
    found: dict[str, tuple[Query, str | None]] = {}

    def register(name: str, sql: str | None = None):
        def keep(f: Query) -> Query:
            found[name] = (f, sql)
            return f

        return keep

    return found, register


def parts(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").select(F.col("l_partkey").alias("item"))


def count_parts(spark: SparkSession, sf: str) -> int:
    return parts(spark, sf).agg(F.count("item")).first()[0]


def users(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select(F.col("event_id").alias("pos"), F.col("user_id").alias("item"))


def zipf(spark: SparkSession, sf: str, alpha: float) -> DataFrame:
    return zipf_stream(table(spark, sf, "events"), "event_id", ZIPF_N, alpha)


def word_counts(spark: SparkSession, sf: str, *keys: str) -> DataFrame:
    docs = table(spark, sf, "documents").select(*keys, F.explode(words(F.col("text"))).alias("word"))
    return docs.groupBy(*keys, "word").agg(F.count("*").alias("cnt"))


def keyed(df: DataFrame, column: str = "word") -> DataFrame:
    return df.withColumn("item", fingerprint(F.col(column)))
