"""Schedules, the split controller, and cost models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from freqsketch.operators.build import build
from freqsketch.operators.measures import effective_width as effective_width_of
from freqsketch.operators.measures import lookup_cost as lookup_cost_of
from freqsketch.operators.measures import memory_bits, table_bytes, union_all
from freqsketch.operators.measures import sync_cost as sync_cost_of
from freqsketch.oracles import sketch_ctes, zipf_sql
from freqsketch.plans import balance as P
from freqsketch.sources.storage import table
from freqsketch.spec import BATCH, PRESET_WIDTHS, SketchSpec
from freqsketch.workloads.common import SPEC, ZIPF_N, catalogue, count_parts, zipf

CATALOGUE, register = catalogue()
WORKERS = 3
FAST, SLOW = 658, 366
PACES, CHUNKS = [1, 4], 64
N_MEMORY, TAU = 1 << 30, 8


@register(
    "static_schedule",
    f"""WITH b AS (SELECT batch_id, w.range AS worker_id, least({BATCH}, n - batch_id * {BATCH}) AS size
    FROM (SELECT n, unnest(range((n + {BATCH - 1}) // {BATCH})) AS batch_id FROM (SELECT count(l_partkey) AS n FROM lineitem)), range({WORKERS}) w)
  SELECT * FROM (SELECT 'hash' AS phase, batch_id, worker_id::INTEGER AS worker_id, batch_id * {BATCH} + size * worker_id // {WORKERS} AS first,
    batch_id * {BATCH} + size * (worker_id + 1) // {WORKERS} - 1 AS last FROM b
  UNION ALL SELECT 'update', batch_id, worker_id::INTEGER, 8 * worker_id // {WORKERS}, 8 * (worker_id + 1) // {WORKERS} - 1 FROM b) WHERE first <= last""",
)
def static_schedule(spark: SparkSession, sf: str) -> DataFrame:
    """Parts of a construction over the parts of ``lineitem``."""
    n = table(spark, sf, "lineitem").agg(F.count("l_partkey")).first()[0]
    return P.static_plan(spark, n, BATCH, SPEC.depth, WORKERS)


@register(
    "dynamic_schedule",
    f"""WITH RECURSIVE c AS (SELECT row_number() OVER (ORDER BY k) - 1 AS chunk, n FROM (
      SELECT l_orderkey % {CHUNKS} AS k, count(l_partkey) AS n FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY 1)),
  t AS (
    SELECT chunk, 0 AS worker_id, 0::BIGINT AS begin_at, n * {PACES[0]} AS end_at, n * {PACES[0]} AS f0, 0::BIGINT AS f1 FROM c WHERE chunk = 0
    UNION ALL
    SELECT c.chunk, CASE WHEN f0 <= f1 THEN 0 ELSE 1 END, least(f0, f1),
      CASE WHEN f0 <= f1 THEN f0 + n * {PACES[0]} ELSE f1 + n * {PACES[1]} END,
      CASE WHEN f0 <= f1 THEN f0 + n * {PACES[0]} ELSE f0 END, CASE WHEN f0 <= f1 THEN f1 ELSE f1 + n * {PACES[1]} END
    FROM t JOIN c ON c.chunk = t.chunk + 1)
  SELECT chunk::INTEGER AS chunk, worker_id::INTEGER AS worker_id, begin_at::BIGINT AS begin_at, end_at::BIGINT AS end_at FROM t""",
)
def dynamic_schedule(spark: SparkSession, sf: str) -> DataFrame:
    """``CHUNKS`` chunks of ``lineitem`` by order; a line item costs one unit."""
    chunk = (F.col("l_orderkey") % CHUNKS).alias("k")
    costs = table(spark, sf, "lineitem").where("l_orderkey is not null").groupBy(chunk).agg(F.count("l_partkey").alias("n")).orderBy("k").collect()
    return spark.createDataFrame(P.dynamic_plan(len(costs), [r.n for r in costs], PACES), "chunk int, worker_id int, begin_at long, end_at long")


@register(
    "two_stage_plan",
    f"""SELECT b.range AS batch_id, s.range::INTEGER AS stage,
    ((r.range // 2) * 2 + CASE WHEN (s.range = 1) = (r.range % 2 = 0) THEN 0 ELSE 1 END)::INTEGER AS worker_id, r.range::INTEGER AS sketch_row,
    CASE WHEN s.range = 1 THEN 0 WHEN r.range % 2 = 0 THEN {FAST} ELSE {SLOW} END::BIGINT AS from_pos,
    CASE WHEN s.range = 2 THEN {FAST + SLOW} WHEN r.range % 2 = 0 THEN {FAST} ELSE {SLOW} END::BIGINT AS to_pos
  FROM range(10) b, range(1, 3) s, range(8) r""",
)
def two_stage_plan(spark: SparkSession, sf: str) -> DataFrame:
    return P.two_stage_plan(spark, 10, FAST, SLOW, SPEC.depth)


@register(
    "schedule_makespan",
    """WITH ph AS (SELECT * FROM (VALUES ('hash', 4.0::DOUBLE), ('update', 1.8)) t(phase, s)),
  pools AS (SELECT phase, 'eight_equal' AS pool, 1.0::DOUBLE AS speed, 8 AS k FROM ph UNION ALL SELECT phase, 'four_equal', 1.0, 4 FROM ph
    UNION ALL SELECT phase, 'four_fast', s, 4 FROM ph UNION ALL SELECT phase, 'four_fast_four_slow', s, 4 FROM ph UNION ALL SELECT phase, 'four_fast_four_slow', 1.0, 4 FROM ph),
  g AS (SELECT phase, pool, sum(k) AS n, sum(k * speed) AS total, min(speed) AS slowest, sum(k / speed) AS inv FROM pools GROUP BY ALL),
  f AS (SELECT l_returnflag, count(*)::DOUBLE AS work FROM lineitem WHERE l_partkey IS NOT NULL GROUP BY 1)
  SELECT l_returnflag, phase, pool, round(work / n / slowest, 6)::DOUBLE AS static_time, round(work / total, 6)::DOUBLE AS balanced_time,
    abs(round(1 - (work / n * inv) / (n * (work / n / slowest)), 6))::DOUBLE AS static_idle, round((work / n / slowest) / (work / total), 6)::DOUBLE AS gain FROM g, f""",
)
def schedule_makespan(spark: SparkSession, sf: str) -> DataFrame:
    """Time of a phase over the line items of a flag under equal and under balanced parts, for each pool of workers."""
    rows = []
    for flag, work in parts_by_flag(spark, sf):
        for phase, ratio in P.BEST_SPLIT.items():
            for pool, speeds in P.POOLS.items():
                static, idle = P.makespan(work, speeds(ratio), False)
                balanced, _ = P.makespan(work, speeds(ratio), True)
                rows.append((flag, phase, pool, round(static, 6), round(balanced, 6), abs(round(idle, 6)), round(static / balanced, 6)))
    return spark.createDataFrame(rows, "l_returnflag string, phase string, pool string, static_time double, balanced_time double, static_idle double, gain double")


def parts_by_flag(spark: SparkSession, sf: str) -> list:
    return table(spark, sf, "lineitem").where("l_partkey is not null").groupBy("l_returnflag").count().collect()


#: Orders in a batch of about ``BATCH`` line items.
_ORDERS = 256
#: What a line item costs beside its share: the mean place that a phase walks to in its table. Hashing reads the
#: same tables for every width.
_PLACES = {("hash", "small"): ("hash", "l_partkey & 255", 255), ("hash", "medium"): ("hash", "l_partkey & 255", 255)} | {
    ("update", s): (s, f"l_partkey % {PRESET_WIDTHS[s]}", PRESET_WIDTHS[s] - 1) for s in ("small", "medium")
}
_SUMS = {k: e for k, e, _ in _PLACES.values()}
_LANES = {"fast": "l_linenumber % 2 = 0", "slow": "l_linenumber % 2 <> 0"}
_WHOLE = "l_orderkey IS NOT NULL AND l_partkey IS NOT NULL AND l_linenumber IS NOT NULL"
_LANE_SUMS = [f"sum(CASE WHEN {cond} THEN {e} ELSE 0 END)" for cond in _LANES.values() for e in ("1", *_SUMS.values())]
_LANE_NAMES = [f"{k}_{who}" for who in _LANES for k in ("n", *_SUMS)]
_BATCHES = f"""b AS (SELECT l_orderkey // {_ORDERS} AS b, {', '.join(f'{e}::BIGINT AS {n}' for e, n in zip(_LANE_SUMS, _LANE_NAMES))}
    FROM lineitem WHERE {_WHOLE} GROUP BY 1)"""


def batches(spark: SparkSession, sf: str) -> DataFrame:
    """(b, n, hash, small, medium of the fast and of the slow lane): line items of batches of orders; even
    lines are the fast worker's."""
    rows = table(spark, sf, "lineitem").where(_WHOLE).withColumn("b", F.expr(f"l_orderkey div {_ORDERS}"))
    return rows.groupBy("b").agg(*[F.expr(e).cast("long").alias(n) for e, n in zip(_LANE_SUMS, _LANE_NAMES)])


def _speed_sql(phase: str, place: str, top: int, who: str) -> str:
    ratio = P.BEST_SPLIT[phase] if who == "fast" else 1.0
    return f"CASE WHEN n_{who} > 0 THEN {ratio}::DOUBLE * (1 + ({place}_{who}::DOUBLE / (n_{who} * {top})::DOUBLE - 0.5::DOUBLE) * 0.1::DOUBLE) ELSE {ratio}::DOUBLE END AS v{who[0]}"


_TRACE = f"""{_BATCHES},
  v AS ({' UNION ALL '.join(f"SELECT '{p}' AS phase, '{s}' AS sketch, b, {_speed_sql(p, k, top, 'fast')}, {_speed_sql(p, k, top, 'slow')} FROM b" for (p, s), (k, _, top) in _PLACES.items())}),
  o AS (SELECT phase, sketch, row_number() OVER w - 1 AS batch_id, lag(vf) OVER w AS pf, lag(vs) OVER w AS ps FROM v WINDOW w AS (PARTITION BY phase, sketch ORDER BY b)),
  trace AS (SELECT phase, sketch, batch_id, CASE WHEN batch_id = 0 THEN 512 ELSE greatest(1024 * pf / (pf + ps), 512) END::DOUBLE AS fast FROM o)"""


def trace(spark: SparkSession, sf: str, warmup: int | None = None) -> DataFrame:
    """Closed loops over the batches of ``lineitem``, whose content disturbs the declared speeds."""

    def speed(phase: str, place: str, top: int, who: str):
        ratio, n = P.BEST_SPLIT[phase] if who == "fast" else 1.0, F.col(f"n_{who}")
        off = F.col(f"{place}_{who}").cast("double") / (n * top).cast("double") - 0.5
        return F.when(n > 0, F.lit(ratio) * (1 + off * 0.1)).otherwise(F.lit(ratio)).alias(f"v_{who}")

    kinds = F.explode(F.array(*[
        F.struct(F.lit(p).alias("phase"), F.lit(s).alias("sketch"), *[speed(p, k, top, who) for who in _LANES]) for (p, s), (k, _, top) in _PLACES.items()
    ])).alias("_s")
    return P.observed_trace(batches(spark, sf).select("b", kinds).select("b", "_s.*"), BATCH, warmup)


@register(
    "rebalance_step",
    f"""WITH {_BATCHES} SELECT batch_id, fast, slow, t_fast, t_slow, round(n, 6)::DOUBLE AS new_fast, round(fast + slow - n, 6)::DOUBLE AS new_slow FROM (
  SELECT *, CASE WHEN t_fast > 0 AND t_slow > 0 THEN greatest((fast + slow) * (fast / t_fast) / (fast / t_fast + slow / t_slow), (fast + slow) / 2) ELSE fast END AS n
  FROM (SELECT b AS batch_id, n_fast::DOUBLE AS fast, n_slow::DOUBLE AS slow, hash_fast::DOUBLE AS t_fast, hash_slow::DOUBLE AS t_slow FROM b))""",
)
def rebalance_step(spark: SparkSession, sf: str) -> DataFrame:
    """One step from the shares and times that each batch of ``lineitem`` has had."""
    names = {"fast": "n_fast", "slow": "n_slow", "t_fast": "hash_fast", "t_slow": "hash_slow"}
    df = batches(spark, sf).select(F.col("b").alias("batch_id"), *[F.col(c).cast("double").alias(k) for k, c in names.items()])
    safe = lambda c: F.when(F.col(c) > 0, F.col(c))
    fast, slow = P.rebalance_columns(F.col("fast"), F.col("slow"), safe("t_fast"), safe("t_slow"))
    return df.select("*", F.round(fast, 6).alias("new_fast"), F.round(slow, 6).alias("new_slow"))


@register(
    "rebalance_trace",
    f"WITH {_TRACE} SELECT phase, sketch, batch_id, round(fast, 6) AS fast, round(1024 - fast, 6) AS slow, round(fast / (1024 - fast), 6) AS f2s FROM trace",
)
def rebalance_trace(spark: SparkSession, sf: str) -> DataFrame:
    t = trace(spark, sf)
    return t.select("phase", "sketch", "batch_id", *[F.round(c, 6).alias(c) for c in ("fast", "slow", "f2s")])


@register(
    "f2s_frozen",
    f"""WITH {_TRACE}, r AS (SELECT phase, sketch, batch_id, avg(fast) OVER (PARTITION BY phase, sketch ORDER BY batch_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run FROM trace WHERE batch_id BETWEEN 1 AND 30)
  SELECT t.phase, t.sketch, t.batch_id, round(r.run / (1024 - r.run), 6) AS f2s FROM trace t JOIN r ON r.phase = t.phase AND r.sketch = t.sketch AND r.batch_id = least(t.batch_id, 30) WHERE t.batch_id >= 1""",
)
def f2s_frozen(spark: SparkSession, sf: str) -> DataFrame:
    """Controllers that adjust for thirty batches and then keep the mean of what they saw."""
    t = trace(spark, sf, warmup=30).where("batch_id >= 1")
    return t.select("phase", "sketch", "batch_id", F.round(F.col("mean") / (BATCH - F.col("mean")), 6).alias("f2s"))


@register(
    "f2s_by_phase",
    f"WITH {_TRACE} SELECT phase, round(avg(fast) / (1024 - avg(fast)), 4)::DOUBLE AS f2s, round(min(fast / (1024 - fast)), 4)::DOUBLE AS lowest, round(max(fast / (1024 - fast)), 4)::DOUBLE AS highest FROM trace WHERE batch_id > 30 GROUP BY phase",
)
def f2s_by_phase(spark: SparkSession, sf: str) -> DataFrame:
    t = trace(spark, sf).where("batch_id > 30")
    mean = F.avg("fast")
    return t.groupBy("phase").agg(F.round(mean / (BATCH - mean), 4).alias("f2s"), F.round(F.min("f2s"), 4).alias("lowest"), F.round(F.max("f2s"), 4).alias("highest"))


@register(
    "f2s_convergence",
    f"""WITH {_TRACE} SELECT phase, sketch, batch_id, round(fast / (1024 - fast), 6) AS f2s,
    round(fast / (1024 - fast) - lag(fast / (1024 - fast)) OVER (PARTITION BY phase, sketch ORDER BY batch_id), 6) AS change FROM trace""",
)
def f2s_convergence(spark: SparkSession, sf: str) -> DataFrame:
    w = W.partitionBy("phase", "sketch").orderBy("batch_id")
    t = trace(spark, sf)
    return t.select("phase", "sketch", "batch_id", F.round("f2s", 6).alias("f2s"), F.round(F.col("f2s") - F.lag("f2s").over(w), 6).alias("change"))


@register(
    "memory_model",
    f"""WITH n AS (SELECT greatest(1, ceil(log2(greatest(count(l_partkey), 1)))) AS k FROM lineitem), t AS (SELECT * FROM (VALUES (2003), (20071), (200003)) t(w))
  SELECT 'partials' AS strategy, w::INTEGER AS width, (8 * w * {TAU} * k)::BIGINT AS bits, (32 * w)::BIGINT AS bytes_4, (64 * w)::BIGINT AS bytes_8 FROM t, n
  UNION ALL SELECT 'single_table', w, (8 * (w * k + {BATCH} * ceil(log2(w))))::BIGINT, 32 * w, 64 * w FROM t, n""",
)
def memory_model(spark: SparkSession, sf: str) -> DataFrame:
    """Memory of sketches whose counters can count every line item."""
    n = max(1, count_parts(spark, sf))
    rows = []
    for w in PRESET_WIDTHS.values():
        s = SketchSpec(8, w)
        for name in ("partials", "single_table"):
            rows.append((name, w, memory_bits(s, n, TAU, name), table_bytes(s, 4), table_bytes(s)))
    return spark.createDataFrame(rows, "strategy string, width int, bits long, bytes_4 long, bytes_8 long")


@register(
    "lookup_cost",
    """SELECT layout, depth, locations, lines, n AS items, n * locations AS all_locations, n * lines AS all_lines FROM (
    SELECT layout, d::INTEGER AS depth, CASE WHEN layout = 'merged' THEN 4 ELSE 4 * d END::INTEGER AS locations,
      CASE WHEN layout = 'merged' THEN 4 * ceil(4 * d / 64.0) ELSE 4 * d END::INTEGER AS lines FROM (VALUES ('separate'), ('merged')) l(layout), (VALUES (1), (4), (8), (16), (32)) t(d)),
    (SELECT count(l_partkey) AS n FROM lineitem)""",
)
def lookup_cost(spark: SparkSession, sf: str) -> DataFrame:
    """What hashing one item touches, and what hashing the parts of all line items touches."""
    n = count_parts(spark, sf)
    costs = [(layout, d, *lookup_cost_of(SketchSpec(d), layout)) for layout in ("separate", "merged") for d in (1, 4, 8, 16, 32)]
    rows = [(*c, n, n * c[2], n * c[3]) for c in costs]
    return spark.createDataFrame(rows, "layout string, depth int, locations int, lines int, items long, all_locations long, all_lines long")


_STRATEGIES = ("partials", "row_owned", "shared_atomic", "shared_locked", "shared_relaxed")


@register(
    "sync_cost",
    f"""SELECT s AS strategy, tau::INTEGER AS workers, CASE WHEN s = 'row_owned' THEN (n + {BATCH - 1}) // {BATCH} ELSE 0 END::BIGINT AS barriers,
    CASE WHEN s IN ('shared_atomic', 'shared_locked') THEN n * 8 ELSE 0 END::BIGINT AS atomics, CASE WHEN s = 'partials' THEN 8 * 2003 * tau ELSE 0 END::BIGINT AS merge_additions
  FROM (VALUES {', '.join(f"('{s}')" for s in _STRATEGIES)}) a(s), (VALUES (1), (4), (8)) b(tau), (SELECT {N_MEMORY}::BIGINT AS n)""",
)
def sync_cost(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(s, t, *sync_cost_of(s, SPEC, N_MEMORY, BATCH, t).values()) for s in _STRATEGIES for t in (1, 4, 8)]
    return spark.createDataFrame(rows, "strategy string, workers int, barriers long, atomics long, merge_additions long")


def _width_sql(alpha: float) -> str:
    return f"""SELECT * FROM (WITH {sketch_ctes(f"SELECT item FROM ({zipf_sql(ZIPF_N, alpha)})", SPEC)},
  r AS (SELECT *, coalesce(sum(cnt) OVER (PARTITION BY sketch_row ORDER BY cnt DESC, sketch_col ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS b, sum(cnt) OVER (PARTITION BY sketch_row) AS n FROM cells)
  SELECT {alpha}::DOUBLE AS alpha, sketch_row, count(*)::BIGINT AS counters FROM r WHERE b < 0.9 * n GROUP BY sketch_row)"""


@register("effective_width", " UNION ALL ".join(_width_sql(a) for a in (0.0, 1.1, 1.5)))
def effective_width(spark: SparkSession, sf: str) -> DataFrame:
    one = lambda a: effective_width_of(build(zipf(spark, sf, a), "item", SPEC)).select(F.lit(a).alias("alpha"), "sketch_row", "counters")
    return union_all([one(a) for a in (0.0, 1.1, 1.5)])
