"""Small values handed to the rows of a written table by their place, without a shuffle of the rows.

The rows carry numbers from ``numbered``: the task that wrote them and their place in what it wrote.
Values are written as one small file for each such task, in the order of places; whoever reads the rows
reads the file along with them. A text of any length so meets its verdict where it lies.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import new_shared_dir, tidy
from .shared_files import atomic_writer, open_store, read_whole

#: Bits of a row number that hold the place among the rows of one task.
PLACE_BITS = 33


def write_positions(values: DataFrame, tag: str) -> str:
    """Folder of the values of (row number, int) rows, whatever their columns are called. Row numbers
    are unique; a number of which there is no row has the value -1."""
    folder = new_shared_dir(values.sparkSession, tag, keep=True)
    store, where = open_store(folder)
    store.create_dir(where, recursive=True)
    number, value = values.columns

    def write(table: pa.Table) -> pa.Table:
        rows = table.column("_n").to_numpy()
        at = rows & ((1 << PLACE_BITS) - 1)
        out = np.full(int(at.max()) + 1, -1, "<i4")
        out[at] = table.column("_v").to_numpy()
        with atomic_writer(f"{folder}/{int(rows[0] >> PLACE_BITS)}") as f:
            f.write(out.tobytes())
        return pa.table({"n": pa.array([len(rows)], pa.int64())})

    rows = values.select(F.shiftright(number, PLACE_BITS).alias("_part"), F.col(number).cast("long").alias("_n"), F.col(value).cast("int").alias("_v"))
    rows.groupBy("_part").applyInArrow(tidy(write), "n long").agg(F.sum("n")).collect()
    return folder


class Positions:
    """Values of the rows that a task reads, file by file."""

    def __init__(self, folder: str):
        self.folder, self.part, self.values = folder, -1, np.zeros(0, np.int32)

    def of(self, numbers: np.ndarray) -> np.ndarray:
        out = np.full(len(numbers), -1, np.int32)
        part, at = numbers >> PLACE_BITS, numbers & ((1 << PLACE_BITS) - 1)
        for p in np.unique(part).tolist():
            if p != self.part:
                try:
                    self.values = np.frombuffer(read_whole(f"{self.folder}/{p}"), "<i4")
                except FileNotFoundError:  # none of that task's rows has a value
                    self.values = np.zeros(0, np.int32)
                self.part = p
            mine = np.flatnonzero(part == p)
            known = mine[at[mine] < len(self.values)]
            out[known] = self.values[at[known]]
        return out


def with_positions(rows: DataFrame, number: str, folder: str, name: str) -> DataFrame:
    """``rows`` and their value, as the column ``name``."""
    fields = rows.schema.fields

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = Positions(folder)
        for b in batches:
            got = values.of(b.column(b.schema.get_field_index(number)).to_numpy())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got)], [*[f.name for f in fields], name])

    return rows.mapInArrow(look, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + [f"{name} int"]))


def picked(rows: DataFrame, number: str, folder: str, value: int) -> DataFrame:
    """The rows whose value it is."""

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = Positions(folder)
        for b in batches:
            mask = values.of(b.column(b.schema.get_field_index(number)).to_numpy()) == value
            if mask.any():
                yield b if mask.all() else b.filter(pa.array(mask))

    return rows.mapInArrow(pick, rows.schema)
