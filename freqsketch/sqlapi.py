"""SQL surface: functions that sketch and estimate inside queries."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from freqsketch.functions.hashing import columns, columns_udf
from freqsketch.operators.algebra import pack, unpack
from freqsketch.operators.build import build_by_group
from freqsketch.spec import SketchSpec


def sketch_aggregate(spec: SketchSpec):
    """Grouped aggregate BIGINT -> packed sketch, for small groups: a group is gathered by its task.
    ``sketch_per_group`` takes groups of any size."""

    @F.pandas_udf("binary")
    def sketch_agg(item: pd.Series, weight: pd.Series) -> bytes:
        dense = np.zeros((spec.depth, spec.width), np.int64)
        cols = columns(item.to_numpy().astype(np.int64), spec)
        for r in range(spec.depth):
            np.add.at(dense[r], cols[:, r], weight.to_numpy())
        return pack(dense, spec)

    return sketch_agg


def sketch_per_group(df: DataFrame, keys: list[str], item: str, spec: SketchSpec, weight: Column | None = None) -> DataFrame:
    """(keys, sketch): a packed sketch for each group of any size. Cells are added before they are
    gathered, so a task sees depth * width of them for a group at most, whatever the group's rows."""
    cells = build_by_group(df, keys, item, spec, weight)
    kinds = dict(cells.dtypes)

    def fold(table: pa.Table) -> pa.Table:
        dense = np.zeros((spec.depth, spec.width), np.int64)
        dense[table.column("sketch_row").to_numpy(), table.column("sketch_col").to_numpy()] = table.column("cnt").to_numpy()
        return pa.table({k: table.column(k).slice(0, 1) for k in keys} | {"sketch": pa.array([pack(dense, spec)], pa.binary())})

    return cells.groupBy(*keys).applyInArrow(fold, ", ".join(f"`{k}` {kinds[k]}" for k in keys) + ", sketch binary")


@udtf(returnType="sketch_row: int, sketch_col: int, cnt: bigint")
class CellsOf:
    """Cells of a packed sketch."""

    def eval(self, packed: bytes):
        if packed is None:
            return
        dense, _ = unpack(bytes(packed))
        for r, c in zip(*np.nonzero(dense)):
            yield int(r), int(c), int(dense[r, c])


def register(spark: SparkSession, name: str, cells: DataFrame, spec: SketchSpec) -> None:
    """``<name>_columns(item)``, ``<name>_estimate(item)``, ``<name>_sketch(item, weight)`` and
    ``<name>_cells(packed)``. The estimate reads a broadcast copy of the dense table, whose size
    the spec fixes (refused above 64 MB)."""
    if spec.depth * spec.width * 8 > 64 << 20:
        raise ValueError("sketch too large to broadcast; join its cells instead")
    dense = np.zeros((spec.depth, spec.width), np.int64)
    got = cells.toArrow()
    dense[got.column("sketch_row").to_numpy(), got.column("sketch_col").to_numpy()] = got.column("cnt").to_numpy()
    shared = spark.sparkContext.broadcast(dense)

    @F.pandas_udf("long")
    def look(item: pd.Series) -> pd.Series:
        cols = columns(item.to_numpy().astype(np.int64), spec)
        return pd.Series(shared.value[np.arange(spec.depth), cols].min(1))

    spark.udf.register(f"{name}_estimate", look)
    spark.udf.register(f"{name}_columns", columns_udf(spec))
    spark.udf.register(f"{name}_sketch", sketch_aggregate(spec))
    spark.udtf.register(f"{name}_cells", CellsOf)
