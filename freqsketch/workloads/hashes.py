"""Sizing and hashing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.functions.hashing import hash_table_df, merged_cells, separate_cells, with_cells
from freqsketch.functions.keys import byte_columns
from freqsketch.oracles import hashed_cte, table_cte, xor_sql
from freqsketch.sources.storage import table
from freqsketch.spec import DELTA, DEPTH_RULES, PRESET_EPS, WIDTH_RULES, SketchSpec
from freqsketch.workloads.common import SPEC, catalogue, count_parts, parts

CATALOGUE, register = catalogue()
_PAIRS = "SELECT DISTINCT l_orderkey * 4294967296 + l_partkey AS item FROM lineitem"
_WIDE = SketchSpec(item_bits=64)


@register(
    "spec_catalog",
    """WITH e AS (SELECT * FROM (VALUES (0.001::DOUBLE, 2003), (0.0001, 20071), (0.00001, 200003)) t(eps, preset)),
  primes AS (SELECT e.eps, min(p.range) AS prime FROM e, range(2000, 200200) p
    WHERE p.range > round(2 / e.eps) AND p.range < round(2 / e.eps) + 120
      AND NOT EXISTS (SELECT 1 FROM range(2, 450) q WHERE q.range * q.range <= p.range AND p.range % q.range = 0) GROUP BY e.eps),
  d AS (SELECT * FROM (VALUES ('ln', ceil(ln(1 / 0.003))), ('log2', ceil(log2(1 / 0.003))), ('inverse', ceil(1 / 0.003)), ('fixed', 8)) t(depth_rule, depth)),
  w AS (SELECT eps, 'e_over_eps' AS width_rule, ceil(exp(1) / eps) AS width FROM e
    UNION ALL SELECT eps, 'prime_2_over_eps', prime FROM primes UNION ALL SELECT eps, 'fixed', preset FROM e)
  SELECT eps, 0.003::DOUBLE AS delta, depth_rule, width_rule, depth::INTEGER AS depth, width::INTEGER AS width,
    round(pow(1 / (eps * width), depth), 9) AS delta_bound, n AS n_stream, round(eps * n, 6)::DOUBLE AS excess_bound
  FROM d, w, (SELECT count(l_partkey) AS n FROM lineitem)""",
)
def spec_catalog(spark: SparkSession, sf: str) -> DataFrame:
    """Sizes for error targets, and the excess that a target allows over the parts of all line items."""
    n, rows = count_parts(spark, sf), []
    for eps in PRESET_EPS.values():
        for dr in DEPTH_RULES:
            for wr in WIDTH_RULES:
                s = SketchSpec.from_error(eps, DELTA, dr, wr)
                rows.append((eps, DELTA, dr, wr, s.depth, s.width, round(s.delta_bound(), 9), n, round(eps * n, 6)))
    return spark.createDataFrame(rows, "eps double, delta double, depth_rule string, width_rule string, depth int, width int, delta_bound double, n_stream long, excess_bound double")


@register(
    "hash_table",
    f"""WITH {table_cte(SPEC)}, u AS (SELECT c.range AS char_pos, (l_partkey >> (8 * c.range)) & 255 AS char_val, count(*) AS lookups
    FROM lineitem, range({SPEC.chars}) c WHERE l_partkey IS NOT NULL GROUP BY ALL)
  SELECT hash_id::INTEGER AS hash_id, char_pos::INTEGER AS char_pos, char_val::INTEGER AS char_val, rnd, coalesce(lookups, 0)::BIGINT AS lookups
  FROM tab LEFT JOIN u USING (char_pos, char_val)""",
)
def hash_table(spark: SparkSession, sf: str) -> DataFrame:
    """Every entry of the random tables, and how often the parts of all line items look it up."""
    items = parts(spark, sf).where("item is not null").groupBy("item").agg(F.count("*").alias("n"))
    each = items.select("n", F.posexplode(F.array(*byte_columns(F.col("item"), SPEC.chars))).alias("char_pos", "char_val"))
    used = each.groupBy("char_pos", "char_val").agg(F.sum("n").alias("lookups"))
    out = hash_table_df(spark, SPEC).join(F.broadcast(used), ["char_pos", "char_val"], "left")
    return out.select("hash_id", "char_pos", "char_val", "rnd", F.coalesce("lookups", F.lit(0)).cast("long").alias("lookups"))


@register(
    "byte_split",
    """SELECT DISTINCT l_partkey AS item, (l_partkey & 255)::INTEGER AS b0, ((l_partkey >> 8) & 255)::INTEGER AS b1,
  ((l_partkey >> 16) & 255)::INTEGER AS b2, ((l_partkey >> 24) & 255)::INTEGER AS b3 FROM lineitem""",
)
def byte_split(spark: SparkSession, sf: str) -> DataFrame:
    return parts(spark, sf).distinct().select("item", *[b.alias(f"b{i}") for i, b in enumerate(byte_columns(F.col("item"), 4))])


_PART_HASHES = f"WITH {table_cte(SPEC)}, items AS (SELECT DISTINCT l_partkey AS item FROM lineitem), {hashed_cte('items', SPEC)} SELECT item, sketch_row, sketch_col FROM hashed"


@register("tabulation_hash_naive", _PART_HASHES)
def tabulation_hash_naive(spark: SparkSession, sf: str) -> DataFrame:
    return separate_cells(spark, parts(spark, sf).distinct(), "item", SPEC)


@register("tabulation_hash_merged", _PART_HASHES)
def tabulation_hash_merged(spark: SparkSession, sf: str) -> DataFrame:
    return merged_cells(spark, parts(spark, sf).distinct(), "item", SPEC)


@register(
    "tabulation_hash_64",
    xor_sql(_PAIRS, _WIDE),
)
def tabulation_hash_64(spark: SparkSession, sf: str) -> DataFrame:
    items = table(spark, sf, "lineitem").select((F.col("l_orderkey") * F.lit(1 << 32) + F.col("l_partkey")).alias("item")).distinct()
    return with_cells(items, "item", _WIDE)


@register(
    "hash_collision_rate",
    f"""WITH {table_cte(SPEC)}, items AS (SELECT DISTINCT l_partkey AS item FROM lineitem), {hashed_cte('items', SPEC)},
  c AS (SELECT sketch_row, sketch_col, count(*) AS n FROM hashed GROUP BY ALL)
  SELECT sketch_row, sum(n)::BIGINT AS items, round(sum(n * (n - 1)) / (sum(n) * (sum(n) - 1)), 12)::DOUBLE AS rate FROM c GROUP BY sketch_row""",
)
def hash_collision_rate(spark: SparkSession, sf: str) -> DataFrame:
    cells = with_cells(parts(spark, sf).distinct(), "item", SPEC).groupBy("sketch_row", "sketch_col").agg(F.count("*").alias("n"))
    pairs, n = F.sum(F.col("n") * (F.col("n") - 1)), F.sum("n")
    return cells.groupBy("sketch_row").agg(n.alias("items"), F.round(pairs / (n * (n - 1)), 12).alias("rate"))
