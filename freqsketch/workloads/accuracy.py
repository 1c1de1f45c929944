"""Errors of estimates, on streams in which items collide."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.functions.keys import fingerprint
from freqsketch.operators import query as Q
from freqsketch.operators.build import build
from freqsketch.operators.measures import accuracy, union_all
from freqsketch.operators.ranks import tiles
from freqsketch.oracles import WORDS_SQL, estimates_cte, hashed_cte, sketch_ctes, table_cte, word_key
from freqsketch.sources.storage import stored
from freqsketch.spec import SketchSpec
from freqsketch.workloads.common import PARTS_SQL, SPEC, STRESS, catalogue, parts, word_counts

CATALOGUE, register = catalogue()
_PTS = f"{sketch_ctes(PARTS_SQL, STRESS)}, {estimates_cte('counts', STRESS)}, pts AS (SELECT item, estimate, cnt AS exact FROM est JOIN counts USING (item))"


def _points(spark: SparkSession, sf: str, spec: SketchSpec = STRESS) -> DataFrame:
    exact = Q.exact_counts(parts(spark, sf), "item")
    return Q.with_exact(Q.estimate(build(parts(spark, sf), "item", spec), exact, "item", spec), exact, "item")


@register("exact_counts", "SELECT l_partkey AS item, count(*)::BIGINT AS cnt FROM lineitem GROUP BY 1")
def exact_counts(spark: SparkSession, sf: str) -> DataFrame:
    return Q.exact_counts(parts(spark, sf), "item")


@register("one_sided_check", f"WITH {_PTS} SELECT count(*)::BIGINT AS items, min(estimate - exact)::BIGINT AS min_excess, count(*) FILTER (estimate < exact)::BIGINT AS under_items FROM pts")
def one_sided_check(spark: SparkSession, sf: str) -> DataFrame:
    excess = F.col("estimate") - F.col("exact")
    return _points(spark, sf).agg(F.count("*").alias("items"), F.min(excess).alias("min_excess"), F.sum((excess < 0).cast("long")).alias("under_items"))


_SPECS = {"preset_small": (SPEC, 1e-3), "rows_4_width_257": (STRESS, 0.01), "rows_2_width_31": (SketchSpec(2, 31), 0.1)}


def _guarantee_sql(name: str, spec: SketchSpec, eps: float) -> str:
    return f"""SELECT * FROM (WITH {sketch_ctes(PARTS_SQL, spec)}, {estimates_cte('counts', spec)}
  SELECT '{name}' AS sketch, {eps}::DOUBLE AS eps, count(*)::BIGINT AS items, count(*) FILTER (estimate >= cnt + {eps} * (SELECT count(*) FROM stream))::BIGINT AS violations,
    round(pow(1 / ({eps} * {spec.width}), {spec.depth}), 9) AS delta_bound FROM est JOIN counts USING (item))"""


@register("guarantee_check", " UNION ALL ".join(_guarantee_sql(k, *v) for k, v in _SPECS.items()))
def guarantee_check(spark: SparkSession, sf: str) -> DataFrame:
    """Items that exceed eps * N, beside the share that the width and depth allow."""
    n = parts(spark, sf).count()
    out = []
    for name, (spec, eps) in _SPECS.items():
        bad = (F.col("estimate") >= F.col("exact") + eps * n).cast("long")
        one = _points(spark, sf, spec).agg(F.count("*").alias("items"), F.sum(bad).alias("violations"))
        out.append(one.select(F.lit(name).alias("sketch"), F.lit(eps).alias("eps"), "items", "violations", F.lit(round(spec.delta_bound(eps), 9)).alias("delta_bound")))
    return union_all(out)


@register(
    "accuracy_summary",
    f"""WITH {_PTS} SELECT count(*)::BIGINT AS items, sum(exact)::BIGINT AS n_stream, round(avg(estimate - exact), 6) AS mean_excess, min(estimate - exact)::BIGINT AS min_excess,
    max(estimate - exact)::BIGINT AS max_excess, round(avg((estimate - exact) / exact), 6) AS mean_relative, round(sqrt(avg((estimate - exact) * (estimate - exact))), 6) AS rmse,
    count(*) FILTER (estimate - exact >= exp(1) / {STRESS.width} * (SELECT count(*) FROM stream))::BIGINT AS violations, count(*) FILTER (estimate < exact)::BIGINT AS under_items FROM pts""",
)
def accuracy_summary(spark: SparkSession, sf: str) -> DataFrame:
    return accuracy(_points(spark, sf), STRESS, F.lit(parts(spark, sf).count()))


@register(
    "error_quantiles",
    f"WITH {_PTS} SELECT round(quantile_cont(estimate - exact, 0.5), 6)::DOUBLE AS p50, round(quantile_cont(estimate - exact, 0.9), 6)::DOUBLE AS p90, round(quantile_cont(estimate - exact, 0.99), 6)::DOUBLE AS p99 FROM pts",
)
def error_quantiles(spark: SparkSession, sf: str) -> DataFrame:
    e = _points(spark, sf).select((F.col("estimate") - F.col("exact")).alias("e"))
    return e.agg(*[F.round(F.expr(f"percentile(e, {q})"), 6).alias(f"p{int(100 * q)}") for q in (0.5, 0.9, 0.99)])


@register(
    "error_deciles",
    f"WITH {_PTS}, d AS (SELECT *, ntile(10) OVER (ORDER BY exact, item)::INTEGER AS decile FROM pts) SELECT decile, count(*)::BIGINT AS items, min(exact)::BIGINT AS least, round(avg(estimate - exact), 6) AS mean_excess FROM d GROUP BY decile",
)
def error_deciles(spark: SparkSession, sf: str) -> DataFrame:
    d = tiles(_points(spark, sf), ["exact", "item"], 10, "decile")
    return d.groupBy("decile").agg(F.count("*").alias("items"), F.min("exact").alias("least"), F.round(F.avg(F.col("estimate") - F.col("exact")), 6).alias("mean_excess"))


_WORD_PTS = f"""w AS ({WORDS_SQL}), counts AS (SELECT {word_key()} AS item, sum(cnt)::BIGINT AS cnt FROM w GROUP BY 1), {table_cte(SPEC)}, {hashed_cte('counts', SPEC)},
  cells AS (SELECT sketch_row, sketch_col, sum(cnt)::BIGINT AS cnt FROM counts JOIN hashed USING (item) GROUP BY ALL),
  est AS (SELECT item, min(c.cnt)::BIGINT AS estimate FROM hashed JOIN cells c USING (sketch_row, sketch_col) GROUP BY item),
  pts AS (SELECT word, estimate, cnt AS exact FROM w JOIN est ON est.item = {word_key()})"""


def word_points(spark: SparkSession, sf: str) -> DataFrame:
    """(word, estimate, exact): keys are fingerprints, so equal fingerprints add to the error."""
    w = stored(word_counts(spark, sf).withColumn("item", fingerprint(F.col("word"))), "words")
    cells = build(w, "item", SPEC, weight=F.col("cnt"))
    est = Q.estimate(cells, w.select("item").distinct(), "item", SPEC)
    return w.join(est, "item").select("word", "estimate", F.col("cnt").alias("exact"))


@register(
    "relative_error_by_decile",
    f"WITH {_WORD_PTS}, d AS (SELECT *, ntile(10) OVER (ORDER BY exact, word)::INTEGER AS decile FROM pts) SELECT decile, count(*)::BIGINT AS words, max(exact)::BIGINT AS most, round(avg(estimate / exact), 6) AS mean_ratio FROM d GROUP BY decile",
)
def relative_error_by_decile(spark: SparkSession, sf: str) -> DataFrame:
    d = tiles(word_points(spark, sf), ["exact", "word"], 10, "decile")
    return d.groupBy("decile").agg(F.count("*").alias("words"), F.max("exact").alias("most"), F.round(F.avg(F.col("estimate") / F.col("exact")), 6).alias("mean_ratio"))


@register("rank_frequency", f"SELECT row_number() OVER (ORDER BY cnt DESC, word)::INTEGER AS rank, word, cnt FROM ({WORDS_SQL}) ORDER BY rank LIMIT 100")
def rank_frequency(spark: SparkSession, sf: str) -> DataFrame:
    top = word_counts(spark, sf).orderBy(F.desc("cnt"), "word").limit(100)
    return top.select(F.row_number().over(W.orderBy(F.desc("cnt"), "word")).alias("rank"), "word", "cnt")


@register(
    "word_sketch",
    f"WITH {_WORD_PTS} SELECT sketch_row, sketch_col, cnt FROM cells",
)
def word_sketch(spark: SparkSession, sf: str) -> DataFrame:
    w = word_counts(spark, sf).withColumn("item", fingerprint(F.col("word")))
    return build(w, "item", SPEC, weight=F.col("cnt"))


@register("word_heavy_hitters", f"WITH {_WORD_PTS} SELECT word, estimate, exact FROM pts WHERE estimate >= 0.005 * (SELECT sum(cnt) FROM w)")
def word_heavy_hitters(spark: SparkSession, sf: str) -> DataFrame:
    pts = stored(word_points(spark, sf), "word-points")
    return Q.heavy_hitters(pts, pts.agg(F.sum("exact")).first()[0], 0.005)
