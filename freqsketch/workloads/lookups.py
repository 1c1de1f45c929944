"""Point, heavy-hitter, rare-item and join-size queries; extensions."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.operators import query as Q
from freqsketch.operators.build import build, build_by_group
from freqsketch.oracles import WORDS_SQL, cells_cte, estimates_cte, hashed_cte, sketch_ctes, table_cte, word_key, zipf_sql
from freqsketch.sources.storage import table
from freqsketch.workloads.common import PARTS_SQL, SPEC, STRESS, ZIPF_N, catalogue, keyed, parts, word_counts, zipf

CATALOGUE, register = catalogue()
_ZIPF = f"SELECT item FROM ({zipf_sql(ZIPF_N, 1.1)})"
_HEAVY = 0.01


def _point(spec) -> str:
    return f"WITH {sketch_ctes(PARTS_SQL, spec)}, {estimates_cte('counts', spec)} SELECT item, estimate, cnt AS exact FROM est JOIN counts USING (item)"


def _points(spark: SparkSession, sf: str, spec) -> DataFrame:
    exact = Q.exact_counts(parts(spark, sf), "item")
    cells = build(parts(spark, sf), "item", spec)
    return Q.with_exact(Q.estimate(cells, exact, "item", spec), exact, "item")


@register("point_estimates", _point(STRESS))
def point_estimates(spark: SparkSession, sf: str) -> DataFrame:
    return _points(spark, sf, STRESS)


_SINGLE = replace(SPEC, depth=1)


@register("single_row_estimates", _point(_SINGLE))
def single_row_estimates(spark: SparkSession, sf: str) -> DataFrame:
    return _points(spark, sf, _SINGLE)


@register(
    "point_estimates_absent",
    f"WITH {sketch_ctes(PARTS_SQL, STRESS)}, gone AS (SELECT DISTINCT l_partkey + 1000000 AS item FROM lineitem), {estimates_cte('gone', STRESS)} SELECT item, estimate, 0::BIGINT AS exact FROM est",
)
def point_estimates_absent(spark: SparkSession, sf: str) -> DataFrame:
    gone = parts(spark, sf).distinct().select((F.col("item") + 1_000_000).alias("item"))
    return Q.estimate(build(parts(spark, sf), "item", STRESS), gone, "item", STRESS).withColumn("exact", F.lit(0).cast("long"))


@register("array_min_query", f"WITH {sketch_ctes(PARTS_SQL, STRESS)}, {estimates_cte('counts', STRESS)} SELECT item, estimate FROM est")
def array_min_query(spark: SparkSession, sf: str) -> DataFrame:
    rows = Q.dense_rows(build(parts(spark, sf), "item", STRESS), STRESS)
    return Q.estimate_dense(rows, parts(spark, sf).distinct(), "item", STRESS)


def _zipf_points(spark: SparkSession, sf: str) -> DataFrame:
    s = zipf(spark, sf, 1.1)
    exact = Q.exact_counts(s, "item")
    return Q.with_exact(Q.estimate(build(s, "item", SPEC), exact, "item", SPEC), exact, "item")


_ZIPF_POINTS = f"{sketch_ctes(_ZIPF, SPEC)}, {estimates_cte('counts', SPEC)}, pts AS (SELECT item, estimate, cnt AS exact FROM est JOIN counts USING (item))"


@register("heavy_hitters", f"WITH {_ZIPF_POINTS} SELECT * FROM pts WHERE estimate >= {_HEAVY} * (SELECT count(*) FROM stream)")
def heavy_hitters(spark: SparkSession, sf: str) -> DataFrame:
    return Q.heavy_hitters(_zipf_points(spark, sf), table(spark, sf, "events").count(), _HEAVY)


@register("rare_items", f"WITH {_ZIPF_POINTS} SELECT * FROM pts WHERE estimate <= 2")
def rare_items(spark: SparkSession, sf: str) -> DataFrame:
    return Q.rare_items(_zipf_points(spark, sf), 2)


@register("topk_estimated", f"WITH {_ZIPF_POINTS} SELECT item, estimate FROM pts ORDER BY estimate DESC, item LIMIT 20")
def topk_estimated(spark: SparkSession, sf: str) -> DataFrame:
    return _zipf_points(spark, sf).select("item", "estimate").orderBy(F.desc("estimate"), "item").limit(20)


@register("topk_exact", f"SELECT item, count(*)::BIGINT AS exact FROM ({_ZIPF}) GROUP BY item ORDER BY exact DESC, item LIMIT 20")
def topk_exact(spark: SparkSession, sf: str) -> DataFrame:
    return Q.exact_counts(zipf(spark, sf, 1.1), "item").select("item", F.col("cnt").alias("exact")).orderBy(F.desc("exact"), "item").limit(20)


_SUPPLIERS = "SELECT l_suppkey AS item FROM lineitem"


@register(
    "heavy_hitter_rows",
    f"""WITH {sketch_ctes(_SUPPLIERS, SPEC)}, {estimates_cte('counts', SPEC)}, hot AS (SELECT item FROM est WHERE estimate >= 1.02 * (SELECT avg(cnt) FROM counts))
  SELECT l_returnflag, count(*)::BIGINT AS n_rows FROM lineitem WHERE l_suppkey IN (SELECT item FROM hot) GROUP BY l_returnflag""",
)
def heavy_hitter_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of the suppliers whose estimate is 2 % above the mean: a semi join with estimates."""
    li = table(spark, sf, "lineitem")
    items = li.select(F.col("l_suppkey").alias("item"))
    exact = Q.exact_counts(items, "item")
    mean = exact.agg(F.avg("cnt")).first()[0]
    hot = Q.estimate(build(items, "item", SPEC), exact, "item", SPEC).where(F.col("estimate") >= 1.02 * mean)
    return li.join(hot.select(F.col("item").alias("l_suppkey")), "l_suppkey", "left_semi").groupBy("l_returnflag").agg(F.count("*").alias("n_rows"))


@register(
    "absent_items",
    f"""WITH {sketch_ctes("SELECT o_custkey AS item FROM orders", SPEC)}, asked AS (SELECT c_custkey AS item FROM customer), {estimates_cte('asked', SPEC)}
  SELECT item FROM est WHERE estimate = 0""",
)
def absent_items(spark: SparkSession, sf: str) -> DataFrame:
    """Customers that have certainly never ordered: no counter of theirs was left at 0 else."""
    orders = table(spark, sf, "orders").select(F.col("o_custkey").alias("item"))
    asked = table(spark, sf, "customer").select(F.col("c_custkey").alias("item"))
    return Q.estimate(build(orders, "item", SPEC), asked, "item", SPEC).where("estimate = 0").select("item")


@register(
    "topk_per_lang",
    f"""WITH w AS (SELECT lang, word, {word_key()} AS item, count(*)::BIGINT AS cnt FROM (SELECT lang, unnest(string_split_regex(lower(text), '[^a-z]+')) AS word FROM documents) WHERE word <> '' GROUP BY ALL),
  counts AS (SELECT lang, item, sum(cnt)::BIGINT AS cnt FROM w GROUP BY ALL), {table_cte(SPEC)}, {hashed_cte('counts', SPEC)}, {cells_cte(SPEC, keys='lang')},
  e AS (SELECT lang, item, min(c.cnt)::BIGINT AS estimate FROM counts JOIN hashed USING (item) JOIN cells c USING (lang, sketch_row, sketch_col) GROUP BY ALL)
  SELECT lang, word, estimate, rank FROM (SELECT lang, word, estimate, row_number() OVER (PARTITION BY lang ORDER BY estimate DESC, word)::INTEGER AS rank
    FROM w JOIN e USING (lang, item)) WHERE rank <= 5""",
)
def topk_per_lang(spark: SparkSession, sf: str) -> DataFrame:
    w = keyed(word_counts(spark, sf, "lang"))
    cells = build_by_group(w, ["lang"], "item", SPEC, F.col("cnt"))
    from freqsketch.functions.hashing import with_cells

    asked = with_cells(w.select("lang", "word", "item"), "item", SPEC)
    e = asked.join(cells, ["lang", "sketch_row", "sketch_col"]).groupBy("lang", "word").agg(F.min("cnt").alias("estimate"))
    ranked = e.withColumn("rank", F.row_number().over(W.partitionBy("lang").orderBy(F.desc("estimate"), "word")))
    return ranked.where("rank <= 5")


_JOIN = "SELECT {} AS item FROM {}"


@register(
    "join_size_estimate",
    f"""WITH {sketch_ctes(_JOIN.format('l_orderkey', 'lineitem'), SPEC, 'a')}, {sketch_ctes(_JOIN.format('o_orderkey', 'orders'), SPEC, 'b')}
  SELECT min(p)::BIGINT AS join_size FROM (SELECT sketch_row, sum(acells.cnt * bcells.cnt) AS p FROM acells JOIN bcells USING (sketch_row, sketch_col) GROUP BY sketch_row)""",
)
def join_size_estimate(spark: SparkSession, sf: str) -> DataFrame:
    a = build(table(spark, sf, "lineitem"), "l_orderkey", SPEC)
    return Q.inner_product(a, build(table(spark, sf, "orders"), "o_orderkey", SPEC), SPEC)


@register("join_size_exact", "SELECT count(*)::BIGINT AS join_size FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def join_size_exact(spark: SparkSession, sf: str) -> DataFrame:
    a = Q.exact_counts(table(spark, sf, "lineitem"), "l_orderkey")
    b = Q.exact_counts(table(spark, sf, "orders"), "o_orderkey").withColumnRenamed("cnt", "_c")
    return a.join(b, "item").agg(F.sum(F.col("cnt") * F.col("_c")).alias("join_size"))


@register(
    "signed_sketch_estimates",
    f"""WITH {sketch_ctes(PARTS_SQL, STRESS)}, s AS (SELECT item, sketch_row, sketch_col, 1 - 2 * (hv >> 31) AS sign FROM hashed),
  t AS (SELECT sketch_row, sketch_col, sum(sign * cnt) AS v FROM s JOIN counts USING (item) GROUP BY ALL)
  SELECT item, median(sign * v)::DOUBLE AS estimate FROM s JOIN t USING (sketch_row, sketch_col) GROUP BY item""",
)
def signed_sketch_estimates(spark: SparkSession, sf: str) -> DataFrame:
    return Q.estimate_signed(parts(spark, sf), "item", STRESS)


@register(
    "noise_corrected_estimates",
    f"""WITH {sketch_ctes(PARTS_SQL, STRESS)}, n AS (SELECT count(*) AS n FROM stream)
  SELECT item, round(least(median(c.cnt - (n - c.cnt) / {STRESS.width - 1}.0::DOUBLE), min(c.cnt)), 6)::DOUBLE AS estimate
  FROM hashed JOIN cells c USING (sketch_row, sketch_col), n GROUP BY item""",
)
def noise_corrected_estimates(spark: SparkSession, sf: str) -> DataFrame:
    """Each counter less what the other items leave in a counter on average; our reading of the
    mean-corrected family of estimators."""
    p = parts(spark, sf)
    out = Q.estimate_corrected(build(p, "item", STRESS), p.distinct(), "item", STRESS, p.count())
    return out.select("item", F.round("estimate", 6).alias("estimate"))


@register(
    "builtin_sketch_header",
    """SELECT 1::BIGINT AS version, count(l_partkey)::BIGINT AS total, ceil(-ln(1 - 0.997::DOUBLE) / ln(2))::BIGINT AS "rows",
    ceil(2 / 0.001::DOUBLE)::BIGINT AS "columns" FROM lineitem""",
)
def builtin_sketch_header(spark: SparkSession, sf: str) -> DataFrame:
    """Sizes of Spark's own count-min sketch of the same column, read from its binary form."""
    s = parts(spark, sf).agg(F.count_min_sketch("item", F.lit(1e-3), F.lit(0.997), F.lit(42)).alias("s"))
    word = lambda at, n: F.conv(F.hex(F.substring("s", at, n)), 16, 10).cast("long")
    return s.select(word(1, 4).alias("version"), word(5, 8).alias("total"), word(13, 4).alias("rows"), word(17, 4).alias("columns"))


@register("word_tokens", WORDS_SQL)
def word_tokens(spark: SparkSession, sf: str) -> DataFrame:
    return word_counts(spark, sf)
