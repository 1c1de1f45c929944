"""Choice of a construction strategy from a small look at the data."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from freqsketch.operators.build import build, items_of
from freqsketch.spec import SketchSpec


@dataclass(frozen=True)
class BuildPlan:
    strategy: str
    reason: str
    tasks: int
    table_bytes: int
    exchange_bytes: int
    distinct_share: float


def choose(df: DataFrame, item: str, spec: SketchSpec, sample_rows: int = 100_000, task_budget: int = 256 << 20) -> BuildPlan:
    """Strategy for a sketch of a column.

    Distinct items among the first ``sample_rows`` say whether counting items first pays; the
    answer changes speed, never the result. Else each task keeps a table while that fits the
    budget; beyond it, rows are owned in segments.
    """
    items = items_of(df, item)
    seen = items.limit(sample_rows).agg(F.count("*").alias("n"), F.approx_count_distinct("item").alias("d")).first()
    share = seen["d"] / max(1, seen["n"])
    tasks = items.rdd.getNumPartitions()
    bytes_ = spec.depth * spec.width * 8
    exchange = tasks * spec.depth * spec.width * 16
    if bytes_ > task_budget:
        return BuildPlan("row_owned", "the table is too large for a task", tasks, bytes_, exchange, share)
    if seen["n"] == sample_rows and share < 0.05 or seen["d"] * 4 < spec.width:
        return BuildPlan("combine_items", "few distinct items", tasks, bytes_, exchange, share)
    return BuildPlan("partials", "a task holds the whole table", tasks, bytes_, exchange, share)


def build_planned(df: DataFrame, item: str, spec: SketchSpec, task_budget: int = 256 << 20) -> tuple[DataFrame, BuildPlan]:
    """The sketch by the strategy that ``choose`` names. Beyond the budget, segments keep an owner's
    counters within a quarter of it."""
    plan = choose(df, item, spec, task_budget=task_budget)
    more = {"segments": -(-4 * plan.table_bytes // (spec.depth * task_budget))} if plan.strategy == "row_owned" else {}
    return build(df, item, spec, plan.strategy, **more), plan


def explain_build(plan: BuildPlan) -> str:
    """The choice in words, with what it would hold and exchange."""
    return (
        f"{plan.strategy}: {plan.reason}; {plan.tasks} tasks, {plan.table_bytes} bytes of table each, "
        f"at most {plan.exchange_bytes} bytes exchanged, {plan.distinct_share:.3f} distinct items a row"
    )
