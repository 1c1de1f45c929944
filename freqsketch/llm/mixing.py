"""Mixing sources to target weights by capped water-filling (operator 4, native)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import read_table, settled, written

#: Weights in the order of the sources, share of all sizes, epoch limit.
WEIGHTS = (3, 1, 2)
SHARE = 1.5
MAX_EPOCHS = 2
SEED = 20_24
#: Rows are ordered by a seeded hash; its leading hex digits name one of 16^3 stripes.
STRIPE_DIGITS = 3


def word_count(text: Column) -> Column:
    """Number of maximal runs of characters other than space and tab to carriage return."""
    plain = F.translate(text, "\t\n\x0b\x0c\r", "     ")
    n = F.size(F.split(F.trim(plain), " +"))
    return F.when(text.isNull() | (F.trim(plain) == ""), F.lit(0)).otherwise(n).cast("long")


def fill_targets(sources: DataFrame, share: float, max_epochs: float) -> DataFrame:
    """Targets of (source, size, weight) rows: weight * level, at most ``max_epochs`` * size.

    Handing a clamped source's excess to the others in proportion to weight, again and again,
    ends at one common level. It is found without a loop: with sources in the order of
    cap / weight, level k assumes that just the first k are clamped, and the smallest level
    that clamps no further source is the answer. Sources of weight 0 get 0.
    """
    # without weight a source is clamped last and takes no part in the level
    order = W.partitionBy(F.lit(0)).orderBy(F.try_divide("cap", "weight").asc_nulls_last(), F.col("rank"))
    s = (
        sources.withColumn("cap", F.col("size") * F.lit(float(max_epochs)))
        .withColumn("want", F.sum("size").over(W.partitionBy(F.lit(0))) * F.lit(float(share)))
        .withColumn("cap_before", F.sum("cap").over(order) - F.col("cap"))
        .withColumn("w_left", F.sum("weight").over(W.partitionBy(F.lit(0))) - F.sum("weight").over(order) + F.col("weight"))
        .withColumn("level", F.try_divide(F.col("want") - F.col("cap_before"), F.col("w_left")))
        .withColumn("open", (F.col("weight") > 0) & (F.col("level") * F.col("weight") <= F.col("cap")))
        .withColumn("answer", F.min(F.when(F.col("open"), F.struct("cap_before", "level"))).over(W.partitionBy(F.lit(0))))
    )
    return s.withColumn(
        "target", F.when(F.col("weight") > 0, F.least(F.col("cap"), F.coalesce(F.col("answer.level") * F.col("weight"), F.col("cap")))).otherwise(0.0)
    ).select("source", "rank", "size", "weight", "target")


def mix_repetitions(
    docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, max_epochs: float = MAX_EPOCHS, seed: int = SEED, row: str | None = None
) -> DataFrame:
    """(doc_id, source, size) rows to how often each is taken; ``row`` names a column of row numbers
    that is passed on.

    Every row is taken floor(target / source size) times; the rest of the target is filled
    with the rows of smallest seeded hash, the last of them by the part that is still missing.
    Rows of one source are ordered through stripes of the hash: only the one stripe in which
    the target ends is ordered row by row, so a source with most of the rows meets in no task.

    Returns doc_id, source, size, source_size, target, taken (words), whole (repetitions,
    the last one rounded to all or nothing). Null sources form one source, the last; size 0
    takes nothing; equal rows share the hash and are told apart by an arbitrary number. Null ids
    share one hash and are ordered by size. Other columns are ignored; an empty table gives no rows.
    """
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit("?"))))
    own = [row] if row else []
    rows = docs.select("doc_id", "source", "size", *own, digest.alias("_h"))
    stripes = rows.groupBy("source", F.substring("_h", 1, STRIPE_DIGITS).alias("_s")).agg(F.sum("size").alias("_words"))
    sizes = stripes.groupBy("source").agg(F.sum("_words").alias("size"))
    ranked = sizes.withColumn(
        "rank", F.row_number().over(W.partitionBy(F.lit(0)).orderBy(F.col("source").isNull(), F.col("source"))) - 1
    )
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("rank") % len(weights) + 1).cast("int"))
    targets = fill_targets(ranked.withColumn("weight", weight), share, max_epochs)
    targets = targets.select(
        "source",
        F.col("size").alias("source_size"),
        "target",
        F.floor(F.when(F.col("size") > 0, F.col("target") / F.col("size")).otherwise(0.0)).alias("_full"),
    ).withColumn("_rest", F.round(F.col("target") - F.col("_full") * F.col("source_size")).cast("long"))
    running = W.partitionBy("source").orderBy("_s").rowsBetween(W.unboundedPreceding, -1)
    t = targets.withColumnRenamed("source", "_src")
    plan = (
        stripes.join(t, F.col("source").eqNullSafe(F.col("_src")))
        .drop("_src")
        .withColumn("_before", F.coalesce(F.sum("_words").over(running), F.lit(0)))
        .withColumn(
            "_kind",
            F.when(F.col("_before") + F.col("_words") <= F.col("_rest"), F.lit("all"))
            .when(F.col("_before") >= F.col("_rest"), F.lit("none"))
            .otherwise(F.lit("edge")),
        )
        .select(F.col("source").alias("_src"), F.col("_s").alias("_st"), "source_size", "target", "_full", "_rest", "_before", "_kind")
    )
    joined = rows.join(
        plan, F.col("source").eqNullSafe(F.col("_src")) & (F.substring("_h", 1, STRIPE_DIGITS) == F.col("_st"))
    )
    # rows of stripes that are clear get a key of their own: the window orders edge stripes alone
    edge = joined.where(F.col("_kind") == "edge").withColumn("_tie", F.monotonically_increasing_id())
    inside = W.partitionBy("_src", "_st").orderBy("_h", "doc_id", "size", "_tie").rowsBetween(W.unboundedPreceding, -1)
    edge = edge.withColumn("_at", F.col("_before") + F.coalesce(F.sum("size").over(inside), F.lit(0))).withColumn(
        "_part", F.greatest(F.lit(0), F.least(F.col("size"), F.col("_rest") - F.col("_at")))
    )
    clear = joined.where(F.col("_kind") != "edge").withColumn(
        "_part", F.when(F.col("_kind") == "all", F.col("size")).otherwise(F.lit(0))
    )
    return clear.unionByName(edge.drop("_at", "_tie")).select(
        "doc_id",
        "source",
        "size",
        *own,
        "source_size",
        "target",
        (F.col("_full") * F.col("size") + F.col("_part")).cast("long").alias("taken"),
        (F.col("_full") + F.when(F.col("_part") * 2 >= F.greatest(F.col("size"), F.lit(1)), 1).otherwise(0)).cast("int").alias("whole"),
    )


@settled
def op4_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that the mix takes of every document; see ``mix_repetitions``."""
    docs = read_table(spark, sf_dir, "documents")
    sized = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"))
    # the texts are read once; what is used again is narrow
    return mix_repetitions(written(sized, "sizes")).select("doc_id", "size", "source_size", "target", "taken")


#: The whole query in SQL, with an ordering of all rows where the operator orders stripes.
OP4_SQL = f"""
WITH d AS (
  SELECT doc_id, source, CASE WHEN text IS NULL THEN 0 ELSE len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')) END::BIGINT AS size,
    md5('{SEED}:' || coalesce(doc_id::VARCHAR, '?')) AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS size FROM d GROUP BY source),
r AS (SELECT *, row_number() OVER (ORDER BY source IS NULL, source) - 1 AS rank FROM s),
w AS (SELECT *, [{", ".join(f"{float(x)}" for x in WEIGHTS)}][rank % {len(WEIGHTS)} + 1]::DOUBLE AS weight, size * {float(MAX_EPOCHS)}::DOUBLE AS cap,
    (SELECT sum(size) FROM s) * {SHARE}::DOUBLE AS want FROM r),
o AS (SELECT *, sum(cap) OVER x - cap AS cap_before, (SELECT sum(weight) FROM w) - sum(weight) OVER x + weight AS w_left FROM w WINDOW x AS (ORDER BY cap / weight, rank ROWS UNBOUNDED PRECEDING)),
l AS (SELECT (want - cap_before) / w_left AS level FROM o WHERE (want - cap_before) / w_left * weight <= cap ORDER BY cap_before LIMIT 1),
t AS (SELECT source, size AS source_size, least(cap, coalesce((SELECT level FROM l) * weight, cap)) AS target FROM w),
f AS (SELECT *, floor(CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END)::BIGINT AS whole FROM t),
g AS (SELECT *, round(target - whole * source_size)::BIGINT AS rest FROM f),
c AS (SELECT d.*, source_size, target, whole, rest, coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY h, doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target, (whole * size + greatest(0, least(size, rest - before)))::BIGINT AS taken FROM c
"""
