"""Shared helpers: table access, lineage cuts, shared folders, byte-level batches."""

from __future__ import annotations

import ctypes
import functools
import inspect
import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker handles at a time; a longer text goes alone.
SLICE_BYTES = 500_000


def ship_package(spark: SparkSession) -> None:
    """Make this package importable on executors whatever started the session."""
    sc = spark.sparkContext
    if getattr(sc, "_freqsketch_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    target = Path(tempfile.mkdtemp()) / "freqsketch_pkg.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(str(target))
    sc._freqsketch_shipped = True


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's checkpoint folder.

    Where the session names none, a temporary one is set if all of Spark is on this machine
    (tests, a laptop); on a cluster that is an error.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None)
    current = sc._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("name a folder that driver and executors share in spark.checkpoint.dir")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="ckpt-"))
        current = sc._jsc.sc().getCheckpointDir()
    return named or current.get()


def new_shared_dir(spark: SparkSession, tag: str, keep: bool = False) -> str:
    """Name of a new folder in the shared one. It goes at the end of the ``scratch`` around it, or,
    with ``keep``, at the end of one that takes everything."""
    root = shared_root(spark).rstrip("/")
    if "://" not in root and not root.startswith("file:"):
        root = "file://" + os.path.abspath(root)
    path = f"{root}/{tag}-{uuid.uuid4().hex}"
    if _SCRATCH:
        _SCRATCH[-1][keep].append(path)
    return path


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder; later stages don't recompute."""
    shared_root(df.sparkSession)
    return df.checkpoint(eager=True)


#: Folders made inside each open ``scratch``: those to drop, and those kept.
_SCRATCH: list[tuple[list[str], list[str]]] = []


@contextmanager
def scratch(spark: SparkSession, everything: bool = False) -> Iterator[None]:
    """Folders made inside go at the end, but for those kept, which are read later: they go with
    ``everything``, else they are left to the ``scratch`` around this one."""
    made: tuple[list[str], list[str]] = ([], [])
    _SCRATCH.append(made)
    try:
        yield
    finally:
        _SCRATCH.remove(made)
        for path in made[0] + made[1] * everything:
            drop_dir(spark, path)
        if _SCRATCH and not everything:
            _SCRATCH[-1][1].extend(made[1])
        # plans and shuffles that nothing refers to any more: Spark drops their files once they are collected
        spark.sparkContext._jvm.System.gc()


#: Folders that the last stage of a pipeline kept for its result.
_LEFT: list[str] = []


@contextmanager
def stage_scratch(spark: SparkSession) -> Iterator[None]:
    """``scratch`` for the stages of a pipeline, whose results are written before the next stage begins:
    what a stage keeps for its result goes when the next one begins."""
    while _LEFT:
        drop_dir(spark, _LEFT.pop())
    outer: tuple[list[str], list[str]] = ([], [])
    _SCRATCH.append(outer)
    try:
        with scratch(spark):
            yield
    finally:
        _SCRATCH.remove(outer)
        _LEFT.extend(outer[1])


def written(df: DataFrame, tag: str, keep: bool = False) -> DataFrame:
    """Columnar, compressed lineage cut: a Parquet table in the shared folder."""
    return df.sparkSession.read.schema(df.schema).parquet(saved(df, tag, keep))


def saved(df: DataFrame, tag: str, keep: bool = False) -> str:
    """The folder of a table that is written as in ``written``."""
    path = new_shared_dir(df.sparkSession, tag, keep)
    df.write.option("compression", "zstd").parquet(path)
    return path


def numbered(df: DataFrame, name: str, tag: str, keep: bool = False) -> DataFrame:
    """``df`` and a row number, written, so that a row keeps its number in every later read. Numbers
    are unique and have gaps."""
    return written(df.withColumn(name, F.monotonically_increasing_id()), tag, keep)


def settled(make):
    """A query whose result is written, and whose other folders go as soon as it is."""

    @functools.wraps(make)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship_package(spark)
        with scratch(spark, everything=True):
            out = make(spark, sf_dir)
            path = f"{shared_root(spark).rstrip('/')}/{make.__name__}-{uuid.uuid4().hex}"
            out.write.option("compression", "zstd").parquet(path)
        return spark.read.schema(out.schema).parquet(path)

    return run


def drop_dir(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def give_back() -> None:
    """Return memory that this process has freed to the system."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim:
        trim(0)


def tidy(fn):
    """An Arrow function whose worker, which lives on between tasks, keeps no freed memory."""
    if inspect.isgeneratorfunction(fn):

        @functools.wraps(fn)
        def run(batches):
            try:
                yield from fn(batches)
            finally:
                give_back()

    else:

        @functools.wraps(fn)
        def run(table):
            try:
                return fn(table)
            finally:
                give_back()

    return run


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and offsets (n+1) of a string column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64, len(column) + 1, column.offset * 8)
    if data is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    raw = np.frombuffer(data, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def byte_slices(offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``limit`` bytes each, one row at least."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1
        hi = min(n, max(lo + 1, hi))
        yield lo, hi
        lo = hi


def binary_array(values: np.ndarray, counts: np.ndarray) -> pa.Array:
    """Rows of raw little-endian values, ``counts[i]`` of them in row i."""
    off = np.zeros(len(counts) + 1, np.int64)
    np.cumsum(np.asarray(counts, np.int64) * values.dtype.itemsize, out=off[1:])
    return pa.Array.from_buffers(
        pa.large_binary(), len(counts), [None, pa.py_buffer(off), pa.py_buffer(np.ascontiguousarray(values))]
    ).cast(pa.binary())


def salted_powers(n: int, seed: int = 0x5EED) -> np.ndarray:
    """n odd pseudo-random 64-bit factors, the same in every process."""
    x = np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x | np.uint64(1)


def mix64(x: np.ndarray) -> np.ndarray:
    """Invertible scrambling of unsigned 64-bit values."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


_POWERS = salted_powers(4096)


def powers(n: int) -> np.ndarray:
    global _POWERS
    if n > len(_POWERS):
        _POWERS = salted_powers(max(n, 2 * len(_POWERS)))
    return _POWERS[:n]


def segment_hash(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit multilinear hash of each segment values[starts[i]:ends[i]], all non-empty
    and in ascending order; equal segments have equal hashes."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    lens = ends - starts
    total = int(lens.sum())
    first = np.cumsum(lens) - lens
    pos = np.arange(total) - np.repeat(first, lens)
    if total == len(values) and starts[0] == 0:
        picked = values
    else:
        picked = values[pos + np.repeat(starts, lens)]
    h = np.add.reduceat((picked.astype(np.uint64) + np.uint64(1)) * powers(int(lens.max()) + 1)[pos], first)
    return mix64(h + lens.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


#: The characters that end a word (space, tab to carriage return).
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def word_bounds(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words ``[^\\x20\\x09-\\x0D]+`` of rows, and each word's row."""
    if not len(raw):
        z = np.zeros(0, np.int64)
        return z, z, z
    inside = ~_BLANK[raw]
    begin = inside.copy()
    begin[1:] &= ~inside[:-1]
    cuts = offsets[1:-1]
    cuts = cuts[cuts < len(raw)]
    begin[cuts] = inside[cuts]
    starts = np.flatnonzero(begin)
    last = inside.copy()
    last[:-1] &= ~inside[1:] | begin[1:]
    ends = np.flatnonzero(last) + 1
    rows = np.searchsorted(offsets, starts, "right") - 1
    return starts, ends, rows
