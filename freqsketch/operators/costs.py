"""What Spark spends on a plan: shuffle, spill and memory, from the stages it has run."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession

COST_SCHEMA = "seconds double, stages int, tasks int, shuffle_write_bytes long, shuffle_read_bytes long, spilled_bytes long, peak_execution_bytes long, task_seconds double"


def _stages(spark: SparkSession) -> dict:
    sc = spark.sparkContext
    store = sc._jsc.sc().statusStore()
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    none = sc._gateway.new_array(sc._jvm.double, 0)
    found = store.stageList(sc._jvm.java.util.ArrayList(), False, False, none, sc._jvm.java.util.ArrayList())
    return {(found.apply(i).stageId(), found.apply(i).attemptId()): found.apply(i) for i in range(found.size())}


def spark_costs(df: DataFrame) -> tuple:
    """Values of COST_SCHEMA for executing ``df`` without keeping its rows."""
    spark = df.sparkSession
    before = set(_stages(spark))
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    seconds = time.perf_counter() - began
    new = [s for k, s in _stages(spark).items() if k not in before and s.numCompleteTasks() > 0]
    add = lambda f: sum(int(f(s)) for s in new)
    return (
        seconds, len(new), add(lambda s: s.numCompleteTasks()), add(lambda s: s.shuffleWriteBytes()), add(lambda s: s.shuffleReadBytes()),
        add(lambda s: s.memoryBytesSpilled()), max((int(s.peakExecutionMemory()) for s in new), default=0), add(lambda s: s.executorRunTime()) / 1000.0,
    )
