"""SQL functions, and the flagship query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.operators import query as Q
from freqsketch.operators.build import build
from freqsketch.oracles import cells_sql, estimates_cte, sketch_ctes
from freqsketch.sources.storage import table
from freqsketch.sqlapi import register as register_functions
from freqsketch.sqlapi import sketch_per_group
from freqsketch.workloads.common import PARTS_SQL, SPEC, STRESS, catalogue, parts

CATALOGUE, register = catalogue()


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """(item, exact, estimate, excess) of every part key."""
    exact = Q.exact_counts(parts(spark, sf), "item")
    est = Q.estimate(build(parts(spark, sf), "item", SPEC), exact, "item", SPEC)
    return Q.with_exact(est, exact, "item").select("item", "exact", "estimate", (F.col("estimate") - F.col("exact")).alias("excess"))


@register("sql_surface_estimate", f"WITH {sketch_ctes(PARTS_SQL, STRESS)}, {estimates_cte('counts', STRESS)} SELECT item, estimate FROM est")
def sql_surface_estimate(spark: SparkSession, sf: str) -> DataFrame:
    register_functions(spark, "parts", build(parts(spark, sf), "item", STRESS), STRESS)
    table(spark, sf, "lineitem").createOrReplaceTempView("_sketch_lineitem")
    return spark.sql("SELECT item, parts_estimate(item) AS estimate FROM (SELECT DISTINCT l_partkey AS item FROM _sketch_lineitem)")


@register("udaf_equals_relational", "SELECT l_returnflag, 0::BIGINT AS different FROM lineitem GROUP BY 1")
def udaf_equals_relational(spark: SparkSession, sf: str) -> DataFrame:
    from freqsketch.operators.build import build_by_group
    from freqsketch.sqlapi import CellsOf

    li = table(spark, sf, "lineitem")
    packed = sketch_per_group(li, ["l_returnflag"], "l_partkey", STRESS)
    spark.udtf.register("sketch_cells", CellsOf)
    packed.createOrReplaceTempView("_packed_sketches")
    cells = spark.sql("SELECT l_returnflag, c.* FROM _packed_sketches, LATERAL sketch_cells(sketch) c")
    plain = build_by_group(li, ["l_returnflag"], "l_partkey", STRESS).withColumnRenamed("cnt", "_b")
    both = cells.join(plain, ["l_returnflag", "sketch_row", "sketch_col"], "full")
    return both.groupBy("l_returnflag").agg(F.sum((~F.col("cnt").eqNullSafe(F.col("_b"))).cast("long")).alias("different"))


@register("udtf_cells", cells_sql(PARTS_SQL, STRESS))
def udtf_cells(spark: SparkSession, sf: str) -> DataFrame:
    from freqsketch.sqlapi import CellsOf

    whole = parts(spark, sf).withColumn("all", F.lit(1))
    sketch_per_group(whole, ["all"], "item", STRESS).createOrReplaceTempView("_packed_parts")
    spark.udtf.register("sketch_cells", CellsOf)
    return spark.sql("SELECT c.* FROM _packed_parts, LATERAL sketch_cells(sketch) c")
