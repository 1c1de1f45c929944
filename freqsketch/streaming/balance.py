"""A balanced construction that measures itself: shares of micro-batches follow measured times.

Tasks cannot be bound to fast or slow cores, so the class of a worker is declared. Where all cores are
alike, ``pace`` makes the slow class do its work so many times over, which takes real time; what
the controllers see is measured, never assumed.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.functions.hashing import columns
from freqsketch.operators.build import summed
from freqsketch.plans.balance import PhaseControllers
from freqsketch.sources.storage import scratch
from freqsketch.spec import SketchSpec

_FIELDS = pa.schema([("worker", pa.int32()), ("sketch_row", pa.int32()), ("part", pa.int32()), ("cols", pa.binary()), ("seconds", pa.float64())])
_DDL = "worker int, sketch_row int, part int, cols binary, seconds double"
TRACE = "batch_id long, phase string, fast double, slow double, t_fast double, t_slow double, f2s double"


class BalancedBuilder:
    """Cells of a stream, batch by batch, on pairs of a fast and a slow worker.

    Hashing: the items of a batch are dealt to the workers in the shares of the hashing controller.
    Updating: each pair owns two sketch rows. In the first stage the fast worker takes its share of
    the batch on the even row and the slow one its share on the odd row, then they exchange rows.
    The table written between the phases is the barrier. Both phases time every worker's kernel
    and hand the mean times of the two classes to their controller, which sets the next batch's shares."""

    def __init__(self, spark: SparkSession, spec: SketchSpec, batch: int, warmup: int = 30, pace: dict[str, int] | None = None):
        self.spark, self.spec = spark, spec
        self.workers = spec.depth + spec.depth % 2
        self.control = PhaseControllers(batch, warmup)
        self.pace = {"hash": 1, "update": 1} | (pace or {})
        self.out = scratch(spark, "balanced")
        self.batches: list[int] = []
        self.trace: list[tuple] = []

    def _observe(self, number: int, phase: str, times: dict[int, float]) -> None:
        control = self.control.of(phase)
        fast, slow = (float(np.mean([t for w, t in times.items() if w % 2 == k] or [0.0])) for k in (0, 1))
        before = control.fast, control.slow
        control.observe(fast, slow)
        self.trace.append((number, phase, *map(float, before), fast, slow, float(before[0] / before[1])))

    def add(self, batch: DataFrame, item: str, number: int) -> None:
        """Hash and update one batch, then learn from its times. A batch may come again."""
        spec, workers, slow_pace = self.spec, self.workers, dict(self.pace)
        fast, slow = self.control.hashing.fast, self.control.hashing.slow
        share = np.cumsum(np.tile([fast, slow], workers // 2) / (workers / 2 * (fast + slow)))
        up_fast, up_slow = self.control.updating.fast, self.control.updating.slow
        u = F.xxhash64(F.monotonically_increasing_id()).bitwiseAND((1 << 30) - 1) / float(1 << 30)
        slot = sum((F.when(u >= float(e), 1).otherwise(0) for e in share[:-1]), F.lit(0))
        dealt = batch.where(F.col(item).isNotNull()).select(slot.alias("_slot"), F.col(item).cast("long").alias("_item"))

        def hash_items(table: pa.Table) -> pa.Table:
            worker = table.column("_slot")[0].as_py()
            x = table.column("_item").to_numpy()
            began = time.perf_counter()
            for _ in range(slow_pace["hash"] if worker % 2 else 1):
                cols = columns(x, spec)
            spent = time.perf_counter() - began
            rows = [{"worker": worker, "sketch_row": -1, "part": 0, "cols": None, "seconds": spent}]
            for r in range(spec.depth):
                even, lone = r % 2 == 0, r % 2 == 0 and r == spec.depth - 1
                mid = round(len(x) * (up_fast if even else up_slow) / (up_fast + up_slow))
                first = r - r % 2 + (0 if even else 1)
                second = first if lone else r - r % 2 + (1 if even else 0)
                for part, (owner, lo, hi) in enumerate(((first, 0, mid), (second, mid, len(x)))):
                    rows.append({"worker": owner, "sketch_row": r, "part": part, "cols": cols[lo:hi, r].astype("<i4").tobytes(), "seconds": None})
            return pa.Table.from_pylist(rows, _FIELDS)

        path = f"{self.out}/hashed={number}"
        dealt.groupBy("_slot").applyInArrow(hash_items, _DDL).write.mode("overwrite").parquet(path)
        buffer = self.spark.read.schema(_DDL).parquet(path)
        self._observe(number, "hash", {r.worker: r.seconds for r in buffer.where("sketch_row < 0").collect()})

        def update(table: pa.Table) -> pa.Table:
            worker = table.column("worker")[0].as_py()
            own: dict[int, np.ndarray] = {}
            spent = 0.0
            for part in (0, 1):  # the stages, one after the other
                for r in table.to_pylist():
                    if r["part"] != part:
                        continue
                    cols = np.frombuffer(r["cols"], "<i4")
                    began = time.perf_counter()
                    for _ in range(slow_pace["update"] if worker % 2 else 1):
                        counts = np.bincount(cols, minlength=spec.width)
                    spent += time.perf_counter() - began
                    own[r["sketch_row"]] = own.get(r["sketch_row"], 0) + counts
            rows = [(worker, -1, -1, 0, spent)]
            for row, counts in own.items():
                at = np.flatnonzero(counts)
                rows += [(worker, row, int(c), int(n), None) for c, n in zip(at, counts[at])]
            kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.float64()]
            return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], ["worker", "sketch_row", "sketch_col", "cnt", "seconds"])

        ddl = "worker int, sketch_row int, sketch_col int, cnt long, seconds double"
        done = f"{self.out}/updated={number}"
        buffer.where("sketch_row >= 0").groupBy("worker").applyInArrow(update, ddl).write.mode("overwrite").parquet(done)
        times = self.spark.read.schema(ddl).parquet(done).where("sketch_row < 0").collect()
        self._observe(number, "update", {r.worker: r.seconds for r in times})
        if number not in self.batches:
            self.batches.append(number)

    def cells(self) -> DataFrame:
        ddl = "worker int, sketch_row int, sketch_col int, cnt long, seconds double"
        if not self.batches:
            return self.spark.createDataFrame([], "sketch_row int, sketch_col int, cnt long")
        parts = self.spark.read.schema(ddl).parquet(*[f"{self.out}/updated={n}" for n in self.batches])
        return summed(parts.where("sketch_row >= 0"))

    def trace_rows(self) -> DataFrame:
        return self.spark.createDataFrame(self.trace, TRACE)


def balanced_stream(stream: DataFrame, item: str, spec: SketchSpec, batch: int = 1024, pace: dict[str, int] | None = None) -> BalancedBuilder:
    """Run a stream to its present end through a ``BalancedBuilder``; a micro-batch is a batch."""
    builder = BalancedBuilder(stream.sparkSession, spec, batch, pace=pace)
    q = (
        stream.writeStream.option("checkpointLocation", scratch(stream.sparkSession, "balanced-state"))
        .trigger(availableNow=True)
        .foreachBatch(lambda df, n: builder.add(df, item, n))
        .start()
    )
    q.awaitTermination()
    return builder
