"""Sketches over streams: windows, sessions, and one table that micro-batches update."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from freqsketch.functions.hashing import with_cells
from freqsketch.sources.storage import scratch
from freqsketch.spec import SketchSpec


def event_time(df: DataFrame, ts: str) -> DataFrame:
    """Watermarks want TIMESTAMP; the tables hold TIMESTAMP_NTZ, read as UTC."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def window_cells(df: DataFrame, ts: str, item: str, spec: SketchSpec, size: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """(win_start, sketch_row, sketch_col, cnt): one sketch for each window. The same plan serves
    a table and a stream; items are counted as they come, state is the windows' cells."""
    d = event_time(df, ts)
    if watermark:
        d = d.withWatermark(ts, watermark)
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    cells = with_cells(d.where(F.col(item).isNotNull()).select(ts, F.col(item).cast("long").alias("_item")), "_item", spec)
    out = cells.groupBy(w.alias("_w"), "sketch_row", "sketch_col").agg(F.count("*").alias("cnt"))
    return out.select(F.col("_w.start").cast("timestamp_ntz").alias("win_start"), "sketch_row", "sketch_col", "cnt")


def session_cells(df: DataFrame, ts: str, item: str, key: str, spec: SketchSpec, gap: str) -> DataFrame:
    """(key, win_start, sketch_row, sketch_col, cnt): one sketch for each session of a key.

    Sessions' bounds are aggregated first, without their items; an item then finds its session
    among those of its key and hour. No task gathers a session, however long it is."""
    d = event_time(df, ts).where(F.col(item).isNotNull())
    s = d.groupBy(F.session_window(ts, gap).alias("_w"), key).agg(F.count("*").alias("_n"))
    hour = lambda c: F.floor(F.unix_timestamp(c) / 3600)
    bounds = s.select(F.col(key).alias("_key"), F.col("_w.start").alias("_from"), F.col("_w.end").alias("_to"))
    bounds = bounds.withColumn("_hour", F.explode(F.sequence(hour("_from"), hour("_to"))))
    each = d.select(key, F.col(ts).alias("_ts"), F.col(item).cast("long").alias("_item"), hour(F.col(ts)).alias("_h"))
    inside = F.col(key).eqNullSafe(F.col("_key")) & (F.col("_h") == F.col("_hour")) & (F.col("_ts") >= F.col("_from")) & (F.col("_ts") < F.col("_to"))
    met = each.join(bounds, inside).select(key, F.col("_from").cast("timestamp_ntz").alias("win_start"), "_item")
    return with_cells(met, "_item", spec).groupBy(key, "win_start", "sketch_row", "sketch_col").agg(F.count("*").alias("cnt"))


def deduplicated(stream: DataFrame, ts: str, keys: list[str], delay: str) -> DataFrame:
    """Rows whose keys have not been seen within the watermark's delay; state is bounded by it."""
    return event_time(stream, ts).withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys)


def merge_into_table(stream: DataFrame, item: str, spec: SketchSpec, tag: str) -> DataFrame:
    """A stored sketch that every micro-batch is added to. Each batch writes a new version of the
    table, made of the one before and its own cells, so a batch that is run again replaces
    its own version and counts once; readers see whole versions."""
    from freqsketch.operators.build import build, summed

    spark = stream.sparkSession
    out = scratch(spark, tag)
    done: list[int] = []

    def merge(batch: DataFrame, number: int) -> None:
        cells = build(batch, item, spec)
        old = [n for n in done if n < number]
        if old:
            cells = summed(cells.unionByName(spark.read.parquet(f"{out}/version={old[-1]}")))
        cells.write.mode("overwrite").parquet(f"{out}/version={number}")
        done.append(number)

    q = stream.writeStream.option("checkpointLocation", f"{out}-state").trigger(availableNow=True).foreachBatch(merge).start()
    q.awaitTermination()
    if not done:
        return spark.createDataFrame([], "sketch_row int, sketch_col int, cnt long")
    return spark.read.parquet(f"{out}/version={done[-1]}")


def drain(stream: DataFrame, tag: str, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there and return its result table.

    Each micro-batch writes a folder of its own number, so one that is run again replaces
    itself. ``complete``: the last folder is the result. ``update``: rows of all folders."""
    spark = stream.sparkSession
    out = scratch(spark, tag)
    last: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
        last.append(number)

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{out}-state").trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    if not last:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{out}/batch={last[-1]}")
    return spark.read.schema(stream.schema).option("basePath", out).parquet(*[f"{out}/batch={n}" for n in sorted(set(last))])


def row_owned_stream(stream: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """Streaming form of the row-owned construction: a micro-batch is the batch, its commit is
    the barrier, and each sketch row's counters are the state of one owner.

    Emits (sketch_row, version, counters) after each micro-batch; the largest version holds."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def own(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        version, counters = state.get if state.exists else (0, None)
        dense = np.zeros(spec.width, np.int64) if counters is None else np.frombuffer(counters, "<i8").copy()
        for p in parts:
            dense += np.bincount(p["sketch_col"].to_numpy(), minlength=spec.width)
        state.update((version + 1, dense.astype("<i8").tobytes()))
        yield pd.DataFrame({"sketch_row": [key[0]], "version": [version + 1], "counters": [dense.astype("<i8").tobytes()]})

    cells = with_cells(stream.where(F.col(item).isNotNull()).select(F.col(item).cast("long").alias("_item")), "_item", spec)
    return cells.select("sketch_row", "sketch_col").groupBy("sketch_row").applyInPandasWithState(
        own, "sketch_row int, version long, counters binary", "version long, counters binary", "update", GroupStateTimeout.NoTimeout
    )


def unpack_rows(rows: DataFrame) -> DataFrame:
    """Cells of the latest version of each row."""
    latest = rows.groupBy("sketch_row").agg(F.max_by("counters", "version").alias("counters"))

    def cells(batches):
        for p in batches:
            for row, raw in zip(p["sketch_row"], p["counters"]):
                dense = np.frombuffer(raw, "<i8")
                at = np.flatnonzero(dense)
                yield pd.DataFrame({"sketch_row": np.full(len(at), row, np.int32), "sketch_col": at.astype(np.int32), "cnt": dense[at]})

    return latest.mapInPandas(cells, "sketch_row int, sketch_col int, cnt long")
