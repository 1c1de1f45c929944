"""Sketches as values: added, subtracted, scaled, compared, packed."""

from __future__ import annotations

import json
import struct
from dataclasses import asdict
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.operators.build import summed
from freqsketch.spec import VERSION, SketchSpec

_HEAD = struct.Struct("<4sI")
_MAGIC = b"FQS2"


def merge(*sketches: tuple[DataFrame, SketchSpec]) -> DataFrame:
    """Sum of sketches with the same hash functions; others raise IncompatibleSketch."""
    for _, spec in sketches[1:]:
        sketches[0][1].require_same(spec)
    return summed(reduce(DataFrame.unionByName, [c.select("sketch_row", "sketch_col", "cnt") for c, _ in sketches]))


def merge_groups(cells: DataFrame, keys: list[str]) -> DataFrame:
    """Sum over all columns but ``keys`` and the cell."""
    return cells.groupBy(*keys, "sketch_row", "sketch_col").agg(F.sum("cnt").alias("cnt"))


def scale(cells: DataFrame, factor: int) -> DataFrame:
    return cells.withColumn("cnt", F.col("cnt") * F.lit(factor).cast("long"))


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    """a - b, for streams of which b is a part: old windows expire without a rebuild."""
    return summed(a.unionByName(scale(b, -1)))


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Cells in which two sketches differ: (sketch_row, sketch_col, left_cnt, right_cnt)."""
    x, y = a.withColumnRenamed("cnt", "left_cnt"), b.withColumnRenamed("cnt", "right_cnt")
    both = x.join(y, ["sketch_row", "sketch_col"], "full").fillna(0, ["left_cnt", "right_cnt"])
    return both.where("left_cnt <> right_cnt")


def row_totals(cells: DataFrame) -> DataFrame:
    """(sketch_row, total): every row of a valid sketch sums to the stream's length."""
    return cells.groupBy("sketch_row").agg(F.sum("cnt").alias("total"))


def pack(dense: np.ndarray, spec: SketchSpec, total: int | None = None) -> bytes:
    """A sketch as bytes: all of its spec, the stream's length, the counters."""
    fields = asdict(spec) | {"total": int(dense[0].sum()) if total is None else total}
    head = json.dumps(fields, sort_keys=True).encode()
    return _HEAD.pack(_MAGIC, len(head)) + head + dense.astype("<i8").tobytes()


def unpack(raw: bytes) -> tuple[np.ndarray, SketchSpec]:
    magic, size = _HEAD.unpack_from(raw)
    if magic != _MAGIC:
        raise ValueError("not a packed sketch")
    fields = json.loads(raw[_HEAD.size : _HEAD.size + size])
    if fields.pop("version") != VERSION:
        raise ValueError("a packed sketch of another version")
    fields.pop("total")
    spec = SketchSpec(**fields)
    dense = np.frombuffer(raw, "<i8", spec.depth * spec.width, _HEAD.size + size).reshape(spec.depth, spec.width)
    return dense, spec


def packed_total(raw: bytes) -> int:
    """Length of the stream that a packed sketch has seen."""
    return json.loads(raw[_HEAD.size : _HEAD.size + _HEAD.unpack_from(raw)[1]])["total"]


def identity(spark: SparkSession, spec: SketchSpec, total: int | None = None) -> DataFrame:
    """One row that says which sketch this is, to be stored beside its cells."""
    kinds = "depth int, width int, seed bigint, item_bits int, hash_family string, eps double, delta double, fingerprint string, layout string, version int, total bigint"
    fields = asdict(spec) | {"total": total}
    names = [f.split()[0] for f in kinds.split(", ")]
    return spark.createDataFrame([tuple(fields[n] for n in names)], kinds)


def write_cells(cells: DataFrame, path: str) -> None:
    """Parquet by sketch row, sorted by column: a point query reads a few row groups."""
    cells.repartition("sketch_row").sortWithinPartitions("sketch_col").write.partitionBy("sketch_row").parquet(path)
