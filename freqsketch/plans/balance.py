"""Work plans for equal and unequal workers, and the controller that splits batches."""

from __future__ import annotations

import hashlib
import heapq
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def rebalance(fast: float, slow: float, t_fast: float, t_slow: float) -> tuple[float, float]:
    """Shares of the next batch from the times of this one.

    Both parts end together if shares are in proportion to the speeds share / time; the sum
    stays. The slow share never exceeds the fast one. Without a usable time nothing changes.
    """
    if t_fast <= 0 or t_slow <= 0 or fast + slow <= 0:
        return fast, slow
    v_fast, v_slow = fast / t_fast, slow / t_slow
    if v_fast + v_slow == 0:
        return fast, slow
    total = fast + slow
    new = max(total * v_fast / (v_fast + v_slow), total / 2)
    return new, total - new


def rebalance_columns(fast: Column, slow: Column, t_fast: Column, t_slow: Column) -> tuple[Column, Column]:
    """The same as expressions."""
    v_fast, v_slow, total = fast / t_fast, slow / t_slow, fast + slow
    usable = (t_fast > 0) & (t_slow > 0) & (v_fast + v_slow > 0)
    new = F.when(usable, F.greatest(total * v_fast / (v_fast + v_slow), total / 2)).otherwise(fast)
    return new, total - new


@dataclass
class SplitController:
    """Split of one phase: adjusts for ``warmup`` batches, then keeps the mean of what it saw."""

    batch: int
    warmup: int = 30
    fast: float = field(init=False)
    slow: float = field(init=False)
    seen: list[float] = field(default_factory=list)

    def __post_init__(self):
        self.fast = self.slow = self.batch / 2

    @property
    def frozen(self) -> bool:
        return len(self.seen) >= self.warmup

    def observe(self, t_fast: float, t_slow: float) -> None:
        if self.frozen:
            return
        self.fast, self.slow = rebalance(self.fast, self.slow, t_fast, t_slow)
        self.seen.append(self.fast)
        if self.frozen:
            self.fast = sum(self.seen) / len(self.seen)
            self.slow = self.batch - self.fast

    def share(self) -> tuple[int, int]:
        f = round(self.fast)
        return f, self.batch - f


@dataclass
class PhaseControllers:
    """Hashing and counter updates differ in their best split, so each has a controller."""

    batch: int
    warmup: int = 30
    hashing: SplitController = field(init=False)
    updating: SplitController = field(init=False)

    def __post_init__(self):
        self.hashing, self.updating = SplitController(self.batch, self.warmup), SplitController(self.batch, self.warmup)

    def of(self, phase: str) -> SplitController:
        return {"hash": self.hashing, "update": self.updating}[phase]


def static_plan(spark: SparkSession, n: int, batch: int, depth: int, workers: int) -> DataFrame:
    """(phase, batch_id, worker_id, first, last): items of each batch in near-equal stretches for
    hashing, sketch rows for updating; remainders are allowed, empty stretches left out."""
    batches = -(-n // batch)
    b = spark.range(batches).select(F.col("id").alias("batch_id"), F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker_id"))
    size = F.least(F.lit(batch), F.lit(n) - F.col("batch_id") * batch)
    lo = F.col("batch_id") * batch + F.floor(size * F.col("worker_id") / workers)
    hi = F.col("batch_id") * batch + F.floor(size * (F.col("worker_id") + 1) / workers)
    hashing = b.select(F.lit("hash").alias("phase"), "batch_id", "worker_id", lo.cast("long").alias("first"), (hi - 1).cast("long").alias("last"))
    r0, r1 = F.floor(depth * F.col("worker_id") / workers), F.floor(depth * (F.col("worker_id") + 1) / workers)
    updating = b.select(F.lit("update").alias("phase"), "batch_id", "worker_id", r0.cast("long").alias("first"), (r1 - 1).cast("long").alias("last"))
    return hashing.unionByName(updating).where("first <= last")


def dynamic_plan(chunks: int, cost: int | list[int], paces: list[int]) -> list[tuple[int, int, int, int]]:
    """(chunk, worker, begin, end): each chunk goes to the worker that is free first; ``paces``
    are times per unit of cost, ties go to the lower worker. ``cost``: of every chunk, or of each."""
    free = [(0, w) for w in range(len(paces))]
    out = []
    for c in range(chunks):
        t, w = heapq.heappop(free)
        end = t + (cost if isinstance(cost, int) else cost[c]) * paces[w]
        out.append((c, w, t, end))
        heapq.heappush(free, (end, w))
    return out


def two_stage_plan(spark: SparkSession, batches: int, fast: int, slow: int, depth: int) -> DataFrame:
    """(batch_id, stage, worker_id, sketch_row, from_pos, to_pos), ends exclusive, places in the
    batch. Workers 2k are fast, 2k+1 slow; rows 2k and 2k+1 are theirs. In stage 1 the fast one
    is on the even row; then they exchange rows, each going on where its mate stopped. An odd last
    row is the fast worker's alone. Empty stretches are left out."""
    rows = spark.range(batches).select(
        F.col("id").alias("batch_id"), F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("sketch_row")
    ).withColumn("stage", F.explode(F.array(F.lit(1), F.lit(2))))
    even = F.col("sketch_row") % 2 == 0
    lone = even & (F.col("sketch_row") == depth - 1)
    total, one = fast + slow, F.col("stage") == 1
    cut = F.when(even, fast).otherwise(slow)
    lo = F.when(one, 0).otherwise(cut)
    hi = F.when(one, cut).otherwise(total)
    by_fast = F.when(one, even).otherwise(~even) | lone
    return rows.select(
        "batch_id", "stage",
        (F.floor(F.col("sketch_row") / 2) * 2 + F.when(by_fast, 0).otherwise(1)).cast("int").alias("worker_id"),
        "sketch_row", lo.cast("long").alias("from_pos"), hi.cast("long").alias("to_pos"),
    ).where("from_pos < to_pos")


def makespan(work: float, speeds: list[float], balanced: bool) -> tuple[float, float]:
    """(time, idle share) of one phase on workers of these speeds: equal parts for all, or parts
    in proportion to speed."""
    k, total = len(speeds), sum(speeds)
    times = [work / total] * k if balanced else [work / k / s for s in speeds]
    end = max(times)
    return end, 1 - sum(times) / (k * end)


#: Best fast-to-slow shares of the two phases.
BEST_SPLIT = {"hash": 4.0, "update": 1.8}
#: Declared speeds of the four worker pools, per phase.
POOLS = {
    "eight_equal": lambda s: [1.0] * 8,
    "four_equal": lambda s: [1.0] * 4,
    "four_fast": lambda s: [s] * 4,
    "four_fast_four_slow": lambda s: [s] * 4 + [1.0] * 4,
}


def jitter(text: str) -> float:
    """A fixed disturbance in [-5 %, 5 %) from the digits of a text."""
    return (int(hashlib.md5(text.encode()).hexdigest()[:8], 16) / 2**32 - 0.5) * 0.1


def closed_loop(batches: int = 256, batch: int = 1024, seed: int = 42, warmup: int | None = None) -> list[tuple]:
    """(phase, sketch, batch_id, fast, slow, mean) of controllers that see, batch after batch, the times
    that their present shares take at declared speeds with a fixed disturbance. Without
    ``warmup`` they never freeze. ``mean``: of the fast shares seen so far, held once frozen."""
    rows = []
    for sketch in ("small", "medium"):
        control = PhaseControllers(batch, batches if warmup is None else warmup)
        for phase, ratio in BEST_SPLIT.items():
            c = control.of(phase)
            for k in range(batches):
                rows.append((phase, sketch, k, c.fast, c.slow, sum(c.seen) / len(c.seen) if c.seen else None))
                speed = {who: v * (1 + jitter(f"{seed}:{phase}:{sketch}:{k}:{who}")) for who, v in (("fast", ratio), ("slow", 1.0))}
                c.observe(c.fast / speed["fast"], c.slow / speed["slow"])
    return rows


def observed_trace(speeds: DataFrame, batch: int, warmup: int | None = None) -> DataFrame:
    """The columns of ``rebalance_trace`` for given speeds: (phase, sketch, b, v_fast, v_slow), a controller
    for each phase and sketch, which sees its batches in the order of ``b``; ``batch_id`` counts them from 0."""
    schema = "phase string, sketch string, batch_id long, fast double, slow double, mean double"

    def follow(t):
        import pandas as pd

        t = t.sort_values("b")
        phase, sketch = t["phase"].iloc[0], t["sketch"].iloc[0]
        c = SplitController(batch, len(t) + 1 if warmup is None else warmup)
        rows, total, n = [], 0.0, 0
        for k, (v_fast, v_slow) in enumerate(zip(t["v_fast"], t["v_slow"])):
            rows.append((phase, sketch, k, c.fast, c.slow, total / n if n else None))
            if not c.frozen:
                c.observe(c.fast / v_fast, c.slow / v_slow)
                total, n = total + c.seen[-1], n + 1
        return pd.DataFrame(rows, columns=["phase", "sketch", "batch_id", "fast", "slow", "mean"])

    return speeds.groupBy("phase", "sketch").applyInPandas(follow, schema).withColumn("f2s", F.col("fast") / F.col("slow"))


def rebalance_trace(spark: SparkSession, batches: int = 256, batch: int = 1024, seed: int = 42, warmup: int | None = None) -> DataFrame:
    """(phase, sketch, batch_id, fast, slow, mean, f2s) of ``closed_loop``."""
    rows = closed_loop(batches, batch, seed, warmup)
    t = spark.createDataFrame(rows, "phase string, sketch string, batch_id long, fast double, slow double, mean double")
    return t.withColumn("f2s", F.col("fast") / F.col("slow"))
