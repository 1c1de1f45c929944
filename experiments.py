"""The experiments at this machine's size; prints Markdown. ``python experiments.py [runs]``"""

from __future__ import annotations

import os
import sys
import tempfile
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import DataFrame, SparkSession

from freqsketch.workloads import grid


def show(title: str, columns: list[str], rows: list) -> None:
    text = lambda v: f"{v:.3g}" if isinstance(v, float) else str(v)
    print(f"\n## {title}\n\n| {' | '.join(columns)} |\n|{' --- |' * len(columns)}")
    for r in rows:
        print(f"| {' | '.join(map(text, r))} |", flush=True)


def table(title: str, df: DataFrame) -> None:
    show(title, df.columns, df.collect())


def main() -> None:
    runs = int(sys.argv[1]) if len(sys.argv) > 1 else 10
    cpus = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(cpus))
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.execution.arrow.maxRecordsPerBatch", "262144")
        .config("spark.checkpoint.dir", "file://" + tempfile.mkdtemp())
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    show("Hashing alone, one core, nanoseconds an item", ["depth", "layout", "ns"], grid.layout_times(runs=runs))
    table("Split by measured times; slow workers hash four times and update twice over", grid.measured_split(spark))
    table("Costs of a construction in Spark, N = 2^22, skew 1.1", grid.strategy_costs(spark))
    table(f"Owned table against the relaxed model, N = 2^20, mean of {runs}", grid.owned_against_relaxed(spark, runs=runs))
    table(f"Run time, N = 2^22, mean of {runs}", grid.time_grid(spark, runs=runs))
    spark.stop()


if __name__ == "__main__":
    main()
