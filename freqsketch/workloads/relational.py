"""Joins, windows, set operations, keys and formats around sketches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.functions.hashing import with_cells
from freqsketch.functions.keys import fingerprint, item_key, url_host
from freqsketch.operators import query as Q
from freqsketch.operators.build import build, build_by_group
from freqsketch.oracles import cells_sql, estimates_cte, hashed_cte, sketch_ctes, table_cte, word_key
from freqsketch.sources.storage import scratch, table
from freqsketch.workloads.common import PARTS_SQL, SPEC, STRESS, catalogue, parts

CATALOGUE, register = catalogue()
_SHIPPED = "SELECT l_partkey AS item FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'"


def _shipped(spark: SparkSession, sf: str) -> DataFrame:
    day = lambda s: F.lit(s).cast("timestamp_ntz")
    return table(spark, sf, "lineitem").where((F.col("l_shipdate") >= day("1995-01-01")) & (F.col("l_shipdate") < day("1996-01-01")))


@register("filter_then_sketch", cells_sql(_SHIPPED, SPEC))
def filter_then_sketch(spark: SparkSession, sf: str) -> DataFrame:
    """The range reaches the scan; two columns are read."""
    return build(_shipped(spark, sf), "l_partkey", SPEC)


@register("sketch_expr_key", cells_sql("SELECT (l_orderkey * 7 + l_linenumber) % 1000 AS item FROM lineitem", SPEC))
def sketch_expr_key(spark: SparkSession, sf: str) -> DataFrame:
    key = F.pmod(F.col("l_orderkey") * 7 + F.col("l_linenumber"), F.lit(1000))
    return build(table(spark, sf, "lineitem").select(key.alias("k")), "k", SPEC)


@register(
    "url_hosts",
    f"""WITH w AS (SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, count(*)::BIGINT AS cnt FROM pages GROUP BY 1),
  {sketch_ctes(f"SELECT {word_key('host')} AS item FROM (SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host FROM pages)", STRESS)}, {estimates_cte('counts', STRESS)}
  SELECT host, estimate, w.cnt AS exact FROM w JOIN est ON est.item = {word_key('host')}""",
)
def url_hosts(spark: SparkSession, sf: str) -> DataFrame:
    pages = table(spark, sf, "pages").select(url_host(F.col("url")).alias("host"))
    keyed = pages.withColumn("item", item_key(pages, "host"))
    est = Q.estimate(build(keyed, "item", STRESS), keyed.select("item").distinct(), "item", STRESS)
    counts = keyed.groupBy("host", "item").agg(F.count("*").alias("exact"))
    return counts.join(est, "item").select("host", "estimate", "exact")


_JSON = "(props->>'$.k')"


@register(
    "json_key_sketch",
    f"""WITH w AS (SELECT {_JSON} AS k, count(*)::BIGINT AS cnt FROM events GROUP BY 1),
  {sketch_ctes(f"SELECT {word_key('k')} AS item FROM (SELECT {_JSON} AS k FROM events)", STRESS)}, {estimates_cte('counts', STRESS)}
  SELECT k, estimate, w.cnt AS exact FROM w JOIN est ON est.item = {word_key('k')}""",
)
def json_key_sketch(spark: SparkSession, sf: str) -> DataFrame:
    ev = table(spark, sf, "events").select(F.get_json_object("props", "$.k").alias("k")).where("k is not null")
    keyed = ev.withColumn("item", fingerprint(F.col("k")))
    est = Q.estimate(build(keyed, "item", STRESS), keyed.select("item").distinct(), "item", STRESS)
    return keyed.groupBy("k", "item").agg(F.count("*").alias("exact")).join(est, "item").select("k", "estimate", "exact")


_HOT_PARTS = f"{sketch_ctes(PARTS_SQL, SPEC)}, {estimates_cte('counts', SPEC)}, hot AS (SELECT item FROM est WHERE estimate >= 1.4 * (SELECT avg(cnt) FROM counts))"


@register(
    "dim_enriched_hitters",
    f"""WITH {_HOT_PARTS} SELECT r_name, n_name, p_brand, count(*)::BIGINT AS n_rows, round(sum(l_quantity), 2)::DOUBLE AS quantity FROM lineitem
  JOIN hot ON l_partkey = hot.item JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ALL""",
)
def dim_enriched_hitters(spark: SparkSession, sf: str) -> DataFrame:
    """Line items of parts 40 % above the mean, with their dimensions."""
    t = lambda n: table(spark, sf, n)
    exact = Q.exact_counts(parts(spark, sf), "item")
    mean = exact.agg(F.avg("cnt")).first()[0]
    hot = Q.estimate(build(parts(spark, sf), "item", SPEC), exact, "item", SPEC).where(F.col("estimate") >= 1.4 * mean)
    li = t("lineitem").join(hot.select(F.col("item").alias("l_partkey")), "l_partkey", "left_semi")
    star = (
        li.join(t("part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
        .join(t("supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), "l_suppkey")
        .join(t("nation").select(F.col("n_nationkey").alias("s_nationkey"), "n_name", "n_regionkey"), "s_nationkey")
        .join(t("region").select(F.col("r_regionkey").alias("n_regionkey"), "r_name"), "n_regionkey")
    )
    return star.groupBy("r_name", "n_name", "p_brand").agg(F.count("*").alias("n_rows"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@register(
    "theta_counter_pairs",
    f"""WITH {sketch_ctes(PARTS_SQL, STRESS)} SELECT a.sketch_row AS row_a, b.sketch_row AS row_b, count(*) FILTER (a.cnt > b.cnt)::BIGINT AS larger, count(*)::BIGINT AS shared
  FROM cells a JOIN cells b ON a.sketch_col = b.sketch_col AND a.sketch_row < b.sketch_row GROUP BY ALL""",
)
def theta_counter_pairs(spark: SparkSession, sf: str) -> DataFrame:
    c = build(parts(spark, sf), "item", STRESS)
    a = c.select(F.col("sketch_row").alias("row_a"), "sketch_col", F.col("cnt").alias("ca"))
    b = c.select(F.col("sketch_row").alias("row_b"), "sketch_col", F.col("cnt").alias("cb"))
    j = a.join(b, "sketch_col").where("row_a < row_b")
    return j.groupBy("row_a", "row_b").agg(F.sum((F.col("ca") > F.col("cb")).cast("long")).alias("larger"), F.count("*").alias("shared"))


_DAY_CELLS = f"""{table_cte(STRESS)}, ev AS (SELECT event_id, ts, user_id AS item, date_trunc('day', ts)::TIMESTAMP AS day FROM events), {hashed_cte('ev', STRESS)},
  cells AS (SELECT day, sketch_row, sketch_col, count(*)::BIGINT AS cnt FROM ev JOIN hashed USING (item) GROUP BY ALL)"""


def _events_by_day(spark: SparkSession, sf: str) -> DataFrame:
    ev = table(spark, sf, "events")
    return ev.select("event_id", "ts", F.col("user_id").alias("item"), F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"))


@register(
    "asof_estimate",
    f"""WITH {_DAY_CELLS}, days AS (SELECT DISTINCT day AS made FROM ev),
  a AS (SELECT e.event_id, e.item, d.made FROM ev e ASOF JOIN days d ON e.day > d.made)
  SELECT event_id, made AS asof_day, min(coalesce(c.cnt, 0))::BIGINT AS estimate FROM a JOIN hashed USING (item) LEFT JOIN cells c ON c.day = a.made AND c.sketch_row = hashed.sketch_row AND c.sketch_col = hashed.sketch_col GROUP BY ALL""",
)
def asof_estimate(spark: SparkSession, sf: str) -> DataFrame:
    """For each event the user's count in the latest daily sketch before the event's day. Days
    are few: each learns its predecessor, and the as-of join becomes an equi-join."""
    ev = _events_by_day(spark, sf)
    cells = build_by_group(ev, ["day"], "item", STRESS)
    days = ev.select("day").distinct().withColumn("asof_day", F.lag("day").over(W.orderBy("day"))).where("asof_day is not null")
    asked = with_cells(ev.join(days, "day").select("event_id", "item", "asof_day"), "item", STRESS)
    found = asked.join(cells.withColumnRenamed("day", "asof_day"), ["asof_day", "sketch_row", "sketch_col"], "left")
    return found.groupBy("event_id", "asof_day").agg(F.min(F.coalesce("cnt", F.lit(0))).alias("estimate"))


@register(
    "interval_join",
    """SELECT a.event_type AS first_type, b.event_type AS next_type, count(*)::BIGINT AS pairs FROM events a JOIN events b
  ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY ALL""",
)
def interval_join(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs of a user's events within an hour: by user and hour, each event also asks the next
    hour, so that no user's whole history meets in one task."""
    ev = table(spark, sf, "events").select("user_id", "ts", "event_type").withColumn("_h", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000))
    a = ev.select("user_id", F.col("ts").alias("_t"), F.col("event_type").alias("first_type"), F.explode(F.array("_h", F.col("_h") + 1)).alias("_h"))
    b = ev.withColumnRenamed("event_type", "next_type")
    hit = a.join(b, ["user_id", "_h"]).where((F.col("ts") > F.col("_t")) & (F.col("ts") <= F.col("_t") + F.expr("interval 1 hour")))
    return hit.groupBy("first_type", "next_type").agg(F.count("*").alias("pairs"))


def _flag_ctes(flag: str, p: str) -> str:
    stream = f"SELECT l_suppkey AS item FROM lineitem WHERE l_returnflag = '{flag}'"
    return f"{sketch_ctes(stream, SPEC, p)}, {estimates_cte(f'{p}counts', SPEC, p, f'{p}est')}, {p}hot AS (SELECT item FROM {p}est WHERE estimate >= (SELECT avg(cnt) FROM {p}counts))"


def _flag_hot(spark: SparkSession, sf: str, flag: str) -> DataFrame:
    li = table(spark, sf, "lineitem").where(F.col("l_returnflag") == flag).select(F.col("l_suppkey").alias("item"))
    exact = Q.exact_counts(li, "item")
    mean = exact.agg(F.avg("cnt")).first()[0] or 0.0
    return Q.estimate(build(li, "item", SPEC), exact, "item", SPEC).where(F.col("estimate") >= mean).select("item")


_SETS = f"WITH {_flag_ctes('A', 'a')}, {_flag_ctes('R', 'r')} SELECT item FROM ahot {{}} SELECT item FROM rhot"


@register("hitters_intersect", _SETS.format("INTERSECT"))
def hitters_intersect(spark: SparkSession, sf: str) -> DataFrame:
    return _flag_hot(spark, sf, "A").intersect(_flag_hot(spark, sf, "R"))


@register("hitters_except", _SETS.format("EXCEPT"))
def hitters_except(spark: SparkSession, sf: str) -> DataFrame:
    return _flag_hot(spark, sf, "A").exceptAll(_flag_hot(spark, sf, "R"))


@register(
    "frequency_anomalies",
    f"""WITH {_DAY_CELLS}, u AS (SELECT DISTINCT day, item FROM ev),
  e AS (SELECT u.day, u.item, min(c.cnt)::BIGINT AS estimate FROM u JOIN hashed USING (item) JOIN cells c ON c.day = u.day AND c.sketch_row = hashed.sketch_row AND c.sketch_col = hashed.sketch_col GROUP BY ALL),
  m AS (SELECT *, avg(estimate) OVER (PARTITION BY item ORDER BY day RANGE BETWEEN INTERVAL 7 DAY PRECEDING AND INTERVAL 1 DAY PRECEDING) AS usual FROM e)
  SELECT day, item, estimate, round(usual, 6) AS usual FROM m WHERE estimate > 3 * usual""",
)
def frequency_anomalies(spark: SparkSession, sf: str) -> DataFrame:
    """Days on which a user's estimate is over three times the mean of the week before."""
    ev = _events_by_day(spark, sf)
    cells = build_by_group(ev, ["day"], "item", STRESS)
    asked = with_cells(ev.select("day", "item").distinct(), "item", STRESS)
    e = asked.join(cells, ["day", "sketch_row", "sketch_col"]).groupBy("day", "item").agg(F.min("cnt").alias("estimate"))
    number = F.datediff("day", F.lit("2024-01-01"))
    week = W.partitionBy("item").orderBy("_n").rangeBetween(-7, -1)
    m = e.withColumn("_n", number).withColumn("usual", F.avg("estimate").over(week))
    return m.where("estimate > 3 * usual").select("day", "item", "estimate", F.round("usual", 6).alias("usual"))


@register("scan_parquet", "SELECT l_returnflag, count(*)::BIGINT AS n_rows, min(l_partkey) AS least, max(l_partkey) AS most FROM lineitem WHERE l_quantity > 25 GROUP BY 1")
def scan_parquet(spark: SparkSession, sf: str) -> DataFrame:
    li = table(spark, sf, "lineitem").where("l_quantity > 25")
    return li.groupBy("l_returnflag").agg(F.count("*").alias("n_rows"), F.min("l_partkey").alias("least"), F.max("l_partkey").alias("most"))


@register("scan_json_roundtrip", "SELECT event_type, count(*)::BIGINT AS n_rows, sum(user_id)::BIGINT AS users FROM events GROUP BY 1")
def scan_json_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    ev = table(spark, sf, "events").select("event_id", "user_id", "event_type")
    path = scratch(spark, "json")
    ev.write.json(path)
    back = spark.read.schema(ev.schema).json(path)
    return back.groupBy("event_type").agg(F.count("*").alias("n_rows"), F.sum("user_id").alias("users"))
