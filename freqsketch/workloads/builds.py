"""Constructions, the buffer, and the loss model."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.functions.hashing import modular_factors, with_cells
from freqsketch.operators import build as B
from freqsketch.operators.measures import conflicts, union_all
from freqsketch.operators.query import estimate, exact_counts
from freqsketch.oracles import cells_sql, counts_cte, hashed_cte, sketch_ctes, table_cte, zipf_sql
from freqsketch.plans.planner import build_planned
from freqsketch.sources.storage import stream, table
from freqsketch.spec import BATCH, SketchSpec
from freqsketch.streaming.balance import balanced_stream
from freqsketch.streaming.windows import drain, row_owned_stream, unpack_rows
from freqsketch.workloads.common import LANES, PARTS_SQL, SPEC, USERS_SQL, ZIPF_N, catalogue, parts, users, zipf

CATALOGUE, register = catalogue()
_PARTS = cells_sql(PARTS_SQL, SPEC)
_USERS = cells_sql(USERS_SQL, SPEC)
ALPHAS = {"uniform": 0.0, "11": 1.1, "15": 1.5}


def _simple(name: str, strategy: str, spec: SketchSpec = SPEC, sql: str = _PARTS, **options) -> None:
    register(name, sql)(lambda spark, sf: B.build(parts(spark, sf), "item", spec, strategy, **options))


_simple("build_serial", "serial")
_simple("build_partials", "partials", layout="separate")
_simple("build_partials_merged", "partials", layout="merged")
_simple("build_relational", "shared_atomic")
_simple("build_row_owned", "row_owned", batch=BATCH)
_simple("ablation_layout", "row_owned", layout="separate")
_simple("build_balanced", "row_owned_balanced")
_simple("build_combined", "combine_items")
for _size in ("small", "medium", "large"):
    _spec = SketchSpec.preset(_size)
    _simple(f"build_{_size}", "row_owned", _spec, cells_sql(PARTS_SQL, _spec), segments=4)

_LARGE = cells_sql(PARTS_SQL, SketchSpec.preset("large"))
_MOD = SketchSpec(hash_family="modular")
_FACTORS = ", ".join(f"({r}, {a}::BIGINT, {b}::BIGINT)" for r, (a, b) in enumerate(modular_factors(8, 42)))
_simple(
    "build_affine",
    "partials",
    _MOD,
    f"""WITH f AS (SELECT * FROM (VALUES {_FACTORS}) t(r, a, b)), {counts_cte('(' + PARTS_SQL + ')')}
  SELECT r::INTEGER AS sketch_row, (((a * item + b) % 4294967311) % {_MOD.width})::INTEGER AS sketch_col, sum(cnt)::BIGINT AS cnt FROM counts, f GROUP BY ALL""",
)


@register("build_two_stage", _USERS)
def build_two_stage(spark: SparkSession, sf: str) -> DataFrame:
    return B.build_two_stage(users(spark, sf), "pos", "item", SPEC, fast=658, slow=366)


@register("build_balanced_stream", _USERS)
def build_balanced_stream(spark: SparkSession, sf: str) -> DataFrame:
    """Micro-batches whose shares follow the times that the batches before have taken."""
    return balanced_stream(stream(spark, sf, "events"), "user_id", SPEC).cells()


@register("build_large_segments", _LARGE)
def build_large_segments(spark: SparkSession, sf: str) -> DataFrame:
    """A table that no task could hold under the planner's budget, which is set low here: owners hold
    a column range of a row each."""
    return build_planned(parts(spark, sf), "item", SketchSpec.preset("large"), task_budget=1 << 20)[0]


@register("build_row_owned_stream", _USERS)
def build_row_owned_stream(spark: SparkSession, sf: str) -> DataFrame:
    return unpack_rows(drain(row_owned_stream(stream(spark, sf, "events"), "user_id", SPEC), "row-owned", "update"))


@register(
    "insert_trace",
    f"""WITH {table_cte(SPEC)}, s AS (SELECT event_id AS pos, user_id AS item FROM events), {hashed_cte('s', SPEC)}
  SELECT pos, item, sketch_row, sketch_col FROM s JOIN hashed USING (item)""",
)
def insert_trace(spark: SparkSession, sf: str) -> DataFrame:
    """What every insertion touches."""
    return with_cells(users(spark, sf), "item", SPEC)


@register(
    "batch_buffer",
    f"""WITH {table_cte(SPEC)}, s AS (SELECT event_id AS pos, user_id AS item FROM events), {hashed_cte('s', SPEC)}
  SELECT pos // {BATCH} AS batch_id, pos, sketch_row, sketch_col FROM s JOIN hashed USING (item)""",
)
def batch_buffer(spark: SparkSession, sf: str) -> DataFrame:
    return B.batch_buffer(users(spark, sf), "pos", "item", SPEC)


def _relaxed(alpha: float) -> str:
    return f"""s AS ({zipf_sql(ZIPF_N, alpha)}), {table_cte(SPEC)}, {hashed_cte('s', SPEC)},
  n AS (SELECT (count(*) + {LANES - 1}) // {LANES} AS block FROM s),
  relaxed AS (SELECT sketch_row, sketch_col, count(DISTINCT pos % block)::BIGINT AS cnt FROM s JOIN hashed USING (item), n GROUP BY sketch_row, sketch_col)"""


@register("build_relaxed", f"WITH {_relaxed(1.1)} SELECT sketch_row, sketch_col, cnt FROM relaxed")
def build_relaxed(spark: SparkSession, sf: str) -> DataFrame:
    s = zipf(spark, sf, 1.1)
    return B.build_relaxed(s, "pos", "item", SPEC, LANES, s.count())


def _damage_sql(alpha: float) -> str:
    return f"""SELECT * FROM (WITH {_relaxed(alpha)}, {counts_cte('s')},
  est AS (SELECT item, min(cnt) AS estimate FROM hashed JOIN relaxed USING (sketch_row, sketch_col) GROUP BY item)
  SELECT {alpha}::DOUBLE AS alpha, ((SELECT count(*) FROM s) * {SPEC.depth} - (SELECT sum(cnt) FROM relaxed))::BIGINT AS lost_updates,
    (SELECT count(*) FROM est JOIN counts USING (item) WHERE estimate < cnt)::BIGINT AS under_items)"""


@register("relaxed_damage", " UNION ALL ".join(_damage_sql(a) for a in ALPHAS.values()))
def relaxed_damage(spark: SparkSession, sf: str) -> DataFrame:
    out = []
    n = table(spark, sf, "events").count()
    for alpha in ALPHAS.values():
        s = zipf(spark, sf, alpha)
        cells = B.build_relaxed(s, "pos", "item", SPEC, LANES, n)
        exact = exact_counts(s, "item")
        under = estimate(cells, exact, "item", SPEC).join(exact, "item").agg(F.sum((F.col("estimate") < F.col("cnt")).cast("long")).alias("under_items"))
        lost = cells.agg((F.lit(n * SPEC.depth) - F.sum("cnt")).alias("lost_updates"))
        # two one-row tables
        out.append(lost.crossJoin(under).select(F.lit(alpha).alias("alpha"), "lost_updates", "under_items"))
    return union_all(out)


def _conflict_sql(alpha: float) -> str:
    return f"""SELECT * FROM (WITH s AS ({zipf_sql(ZIPF_N, alpha)}), {table_cte(SPEC)}, {hashed_cte('s', SPEC)},
  n AS (SELECT (count(*) + {LANES - 1}) // {LANES} AS block FROM s),
  u AS (SELECT pos % block AS tick, sketch_row, sketch_col FROM s JOIN hashed USING (item), n)
  SELECT {alpha}::DOUBLE AS alpha, count(*)::BIGINT AS updates,
    (count(*) - count(DISTINCT (tick, sketch_row, sketch_col)))::BIGINT AS cell_conflicts,
    (count(*) - count(DISTINCT (tick, sketch_row, sketch_col // 16)))::BIGINT AS line_conflicts, 0::BIGINT AS owned_conflicts FROM u)"""


@register("conflict_count", " UNION ALL ".join(_conflict_sql(a) for a in ALPHAS.values()))
def conflict_count(spark: SparkSession, sf: str) -> DataFrame:
    n = table(spark, sf, "events").count()
    one = lambda a: conflicts(zipf(spark, sf, a), "pos", "item", SPEC, LANES, n)
    return union_all([one(a).select(F.lit(a).alias("alpha"), "*", F.lit(0).cast("long").alias("owned_conflicts")) for a in ALPHAS.values()])


for _name, _alpha in ALPHAS.items():
    register(f"zipf_stream_{_name}", f"SELECT pos AS event_id, item FROM ({zipf_sql(ZIPF_N, _alpha)})")(
        lambda spark, sf, a=_alpha: zipf(spark, sf, a).withColumnRenamed("pos", "event_id")
    )


def strategy_cells(spark: SparkSession, sf: str) -> dict[str, DataFrame]:
    """The sketch of one ordered stream by every strategy."""
    s = users(spark, sf)
    out = {k: B.build(s, "item", SPEC, k) for k in ("serial", "partials", "shared_atomic", "row_owned", "combine_items", "row_owned_balanced")}
    return out | {"two_stage": B.build_two_stage(s, "pos", "item", SPEC, 512, 512)}


@register(
    "strategies_equal",
    f"""WITH {sketch_ctes(USERS_SQL, SPEC)} SELECT unnest(['combine_items', 'partials', 'row_owned', 'row_owned_balanced', 'shared_atomic', 'two_stage']) AS strategy,
    (SELECT count(*) FROM cells)::BIGINT AS cells, 0::BIGINT AS different""",
)
def strategies_equal(spark: SparkSession, sf: str) -> DataFrame:
    made = strategy_cells(spark, sf)
    base = made.pop("serial").withColumnRenamed("cnt", "_base")
    out = []
    for name, cells in made.items():
        both = cells.join(base, ["sketch_row", "sketch_col"], "full")
        different = F.sum((~F.col("cnt").eqNullSafe(F.col("_base"))).cast("long"))
        out.append(both.agg(F.count("cnt").alias("cells"), different.alias("different")).select(F.lit(name).alias("strategy"), "cells", "different"))
    return union_all(out)
