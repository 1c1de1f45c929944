"""Construction of one sketch from a stream of items, by several strategies.

All of them yield the same cells (sketch_row, sketch_col, cnt); they differ in who updates what,
in what is exchanged, and in the memory that takes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from freqsketch.functions.hashing import columns, columns_by_row, with_cells
from freqsketch.spec import BATCH, SketchSpec

CELLS = "sketch_row int, sketch_col int, cnt long"
STRATEGIES = (
    "serial",
    "partials",
    "shared_atomic",
    "row_owned",
    "two_stage",
    "row_owned_balanced",
    "combine_items",
)


def items_of(df: DataFrame, item: str, weight: Column | None = None) -> DataFrame:
    """(item) or (item, weight); null items are dropped, null weights count 0. Without weights
    every item counts 1 and no column says so."""
    cols = [F.col(item).cast("long").alias("item")]
    if weight is not None:
        cols.append(F.coalesce(weight.cast("long"), F.lit(0)).alias("weight"))
    return df.select(*cols).where("item is not null")


def _weight(items: DataFrame) -> Column:
    return F.col("weight") if "weight" in items.columns else F.lit(1).cast("long")


def _cells_of(dense: np.ndarray) -> pa.RecordBatch:
    row, col = np.nonzero(dense)
    return pa.RecordBatch.from_arrays(
        [pa.array(row.astype(np.int32)), pa.array(col.astype(np.int32)), pa.array(dense[row, col])],
        ["sketch_row", "sketch_col", "cnt"],
    )


def _add(dense: np.ndarray, cols: np.ndarray, weight: np.ndarray | None) -> None:
    """Add the weights of a batch of items to the counters, row by row."""
    w = dense.shape[1]
    for r in range(dense.shape[0]):
        if weight is None:
            dense[r] += np.bincount(cols[:, r], minlength=w)
        else:
            np.add.at(dense[r], cols[:, r], weight)


def partial_tables(items: DataFrame, spec: SketchSpec, layout: str = "paired", batch: int = BATCH) -> DataFrame:
    """One dense table in the memory of each task (depth * width * 8 bytes), emitted once, as
    cells. A task hashes batches into a buffer of column ids, then updates its table row by row.
    As a row's update costs its width once, wide tables gather several Arrow batches."""

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dense = np.zeros((spec.depth, spec.width), np.int64)
        step = max(batch, 4 * spec.width, 1 << 16)
        held: list[pa.RecordBatch] = []
        n = 0

        def update() -> None:
            x = np.concatenate([b.column(0).to_numpy() for b in held])
            w = np.concatenate([b.column(1).to_numpy() for b in held]) if held[0].num_columns > 1 else None
            for lo in range(0, len(x), step):
                _add(dense, columns(x[lo : lo + step], spec, layout), None if w is None else w[lo : lo + step])
            held.clear()

        for b in batches:
            held.append(b)
            n += len(b)
            if n >= step:
                update()
                n = 0
        if held:
            update()
        yield _cells_of(dense)

    return items.mapInArrow(fill, CELLS)


def summed(cells: DataFrame) -> DataFrame:
    """Cells with equal places added; partial sums go first, so hot cells cost a task one row."""
    out = cells.groupBy("sketch_row", "sketch_col").agg(F.sum("cnt").alias("cnt"))
    return out.where("cnt <> 0").select("sketch_row", "sketch_col", "cnt")


def build_serial(items: DataFrame, spec: SketchSpec) -> DataFrame:
    """The whole stream through one worker; the reference for tests."""
    return partial_tables(items.coalesce(1), spec)


def build_partials(items: DataFrame, spec: SketchSpec, layout: str = "paired", workers: int | None = None) -> DataFrame:
    """A table for each worker, then added. Exchanges up to workers * depth * width cells."""
    return summed(partial_tables(items.repartition(workers) if workers else items, spec, layout))


def build_relational(items: DataFrame, spec: SketchSpec) -> DataFrame:
    """A shared table whose updates are atomic: every cell has one owner, the aggregation."""
    cells = with_cells(items, "item", spec)
    return summed(cells.select("sketch_row", "sketch_col", _weight(items).alias("cnt")))


def _buffered(items: DataFrame, spec: SketchSpec, buffer: int, segments: int, layout: str, cut: tuple[int, int] | None = None) -> DataFrame:
    """First phase: tasks gather ``buffer`` items, hash them one sketch row after the other and
    combine a row's column ids: (owner, at, cnt), packed, one record for an owner and a buffer.

    A task holds its buffer and one row of ids, never a table. An owner is a column range of a
    sketch row. With ``cut`` (fast, slow) it is a worker of a pair instead: the pair owns two
    rows; the first stage goes up to the cut, fast / (fast + slow) of the buffer on an even row and
    the rest of that on an odd one, then the workers exchange rows."""
    part = -(-spec.width // segments)

    def combined(cols: np.ndarray, weight: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        if spec.width <= 4 * len(cols):
            dense = np.bincount(cols, minlength=spec.width) if weight is None else np.zeros(spec.width, np.int64)
            if weight is not None:
                np.add.at(dense, cols, weight)
            at = np.flatnonzero(dense)
            return at, dense[at]
        at, back, n = np.unique(cols, return_inverse=True, return_counts=True)
        if weight is not None:
            n = np.zeros(len(at), np.int64)
            np.add.at(n, back, weight)
        return at, n

    def stretches(row: int, n: int) -> list[tuple[int, int, int]]:
        """(worker, from, to) of a row's updates."""
        if cut is None:
            return [(row, 0, n)]
        fast, slow = cut
        even, lone = row % 2 == 0, row % 2 == 0 and row == spec.depth - 1
        mid = n * (fast if even else slow) // (fast + slow)
        first = row - row % 2 + (0 if even else 1)
        second = first if lone else row - row % 2 + (1 if even else 0)
        return [(first, 0, mid), (second, mid, n)]

    def phase(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0

        def flush(x: np.ndarray, weight: np.ndarray | None) -> pa.RecordBatch:
            rows = []
            for r, cols in columns_by_row(x, spec, layout):
                for worker, lo, hi in stretches(r, len(x)):
                    if lo == hi:
                        continue
                    at, n = combined(cols[lo:hi], None if weight is None else weight[lo:hi])
                    edges = np.searchsorted(at, np.arange(segments + 1) * part)
                    for k in np.flatnonzero(np.diff(edges)).tolist():
                        one = slice(edges[k], edges[k + 1])
                        rows.append((worker * segments + k, r, at[one].astype("<i4").tobytes(), n[one].astype("<i8").tobytes()))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _PACKED.types)], schema=_PACKED)

        def join(k: int) -> np.ndarray:
            return np.concatenate([b.column(k).to_numpy() for b in held])

        for b in batches:
            while len(b):
                take = min(len(b), buffer - size)
                held.append(b.slice(0, take))
                size, b = size + take, b.slice(take)
                if size == buffer:
                    yield flush(join(0), join(1) if held[0].num_columns > 1 else None)
                    held, size = [], 0
        if size:
            yield flush(join(0), join(1) if held[0].num_columns > 1 else None)

    return items.mapInArrow(phase, "owner int, sketch_row int, at binary, cnt binary")


_PACKED = pa.schema([("owner", pa.int32()), ("sketch_row", pa.int32()), ("at", pa.binary()), ("cnt", pa.binary())])


def _owned(parts: DataFrame, spec: SketchSpec, owners: int, segments: int) -> DataFrame:
    """Second phase: every owner is a task that alone updates the counters that are its own: a
    column range of a row, or of a pair's two rows. It holds these counters and nothing else."""
    part = -(-spec.width // segments)

    def update(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[tuple[int, int], np.ndarray] = {}
        for b in batches:
            for owner, row, at, n in zip(*(c.to_pylist() for c in b.columns)):
                base = owner % segments * part
                if (row, base) not in own:
                    own[row, base] = np.zeros(min(part, spec.width - base), np.int64)
                # a record's places are distinct
                own[row, base][np.frombuffer(at, "<i4") - base] += np.frombuffer(n, "<i8")
        for (row, base), counters in own.items():
            at = np.flatnonzero(counters)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(at), row, np.int32)), pa.array((at + base).astype(np.int32)), pa.array(counters[at])], ["sketch_row", "sketch_col", "cnt"]
            )

    return parts.repartitionById(owners, F.col("owner")).mapInArrow(update, CELLS)


def buffer_items(spec: SketchSpec) -> int:
    """Items that a task gathers: so many that a row's counters are met several times, and 32 MB
    of them at most."""
    return min(1 << 22, max(1 << 16, 16 * spec.width))


def build_row_owned(items: DataFrame, spec: SketchSpec, batch: int | None = None, segments: int = 1, layout: str = "paired") -> DataFrame:
    """Two phases: tasks hash batches into a buffer and combine it; then each sketch row, or
    each of ``segments`` column ranges of it, has one owner that alone updates it.

    The one shuffle between the phases stands for the barrier; no counter is ever shared, and there
    is one table in all: a task of the first phase holds ``batch`` items, an owner its range.
    Owners are depth * segments, so segments let more than depth tasks work."""
    parts = _buffered(items, spec, batch or buffer_items(spec), segments, layout)
    cells = _owned(parts, spec, spec.depth * segments, segments)
    return cells.where("cnt <> 0")


def build_barrier(items: DataFrame, spec: SketchSpec, workers: int, batch: int = BATCH) -> DataFrame:
    """Demonstrator of a real barrier: all workers run at once, hash their batches, wait for one
    another, and exchange column ids so that each updates only its own sketch rows.

    Literal, and for small streams only: every round gathers the buffers of all workers, all
    tasks must hold slots together, and one failure starts the stage again."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import base64

        from pyspark import BarrierTaskContext

        ctx = BarrierTaskContext.get()
        me = ctx.partitionId()
        own = [r for r in range(spec.depth) if r % workers == me]
        dense = np.zeros((spec.depth, spec.width), np.int64)
        parts = [b.column(0).to_numpy() for b in batches]
        mine = np.concatenate(parts) if parts else np.zeros(0, np.int64)
        rounds = max(int(x) for x in ctx.allGather(str(-(-len(mine) // batch))))
        for k in range(rounds):
            cols = columns(mine[k * batch : (k + 1) * batch], spec).astype("<i4")
            shared = ctx.allGather(base64.b64encode(np.ascontiguousarray(cols).tobytes()).decode())
            for text in shared:
                got = np.frombuffer(base64.b64decode(text), "<i4").reshape(-1, spec.depth)
                for r in own:
                    dense[r] += np.bincount(got[:, r], minlength=spec.width)
        yield _cells_of(dense)

    return items.select("item").repartition(workers).mapInArrow(run, CELLS, barrier=True)


def batch_buffer(df: DataFrame, pos: str, item: str, spec: SketchSpec, batch: int = BATCH) -> DataFrame:
    """The buffer between the phases, as a relation: (batch_id, pos, sketch_row, sketch_col).

    ``pos`` is the item's place in the stream; the last batch may be short."""
    cells = with_cells(df.select(F.col(pos).alias("pos"), F.col(item).cast("long").alias("item")), "item", spec)
    return cells.select(F.floor(F.col("pos") / batch).cast("long").alias("batch_id"), "pos", "sketch_row", "sketch_col")


def build_two_stage(df: DataFrame, pos: str, item: str, spec: SketchSpec, fast: int, slow: int) -> DataFrame:
    """Paired workers: a fast and a slow one update two rows of a batch and exchange them half-
    way. The place in the batch and the row's parity say who updates in which stage, which is
    an expression; each (row, stage, worker) is aggregated alone, then the stages add up."""
    batch = fast + slow
    buf = batch_buffer(df, pos, item, spec, batch).withColumn("_at", F.col("pos") % batch)
    even = F.col("sketch_row") % 2 == 0
    head = F.when(even, F.col("_at") < fast).otherwise(F.col("_at") < slow)
    stage = F.when(head, 1).otherwise(2)
    by_fast = F.when(stage == 1, even).otherwise(~even)
    worker = F.floor(F.col("sketch_row") / 2) * 2 + F.when(by_fast, 0).otherwise(1)
    staged = buf.groupBy("sketch_row", "sketch_col", stage.alias("stage"), worker.alias("worker")).agg(F.count("*").alias("cnt"))
    return summed(staged)


#: Fixed value: the best split of a batch of updates between a fast and a slow worker.
UPDATE_SPLIT = (1.8, 1.0)


def build_balanced(
    items: DataFrame, spec: SketchSpec, split: tuple[float, float] = UPDATE_SPLIT, batch: int | None = None, segments: int = 1, layout: str = "paired"
) -> DataFrame:
    """The row-owned construction for unequal workers: buffers are hashed in chunks that go to
    whichever worker is free, and pairs of a fast and a slow worker own two rows each, which they
    exchange half-way. ``split`` (fast, slow) is what a controller has measured for the updates;
    ``streaming.balance`` measures it. A pair's partial rows are added at the end."""
    cut = (round(1000 * split[0]), round(1000 * split[1]))
    workers = spec.depth + spec.depth % 2
    return summed(_owned(_buffered(items, spec, batch or buffer_items(spec), segments, layout, cut), spec, workers * segments, segments))


def build_combined(items: DataFrame, spec: SketchSpec) -> DataFrame:
    """Equal items are counted before they are hashed: a sketch is linear, the result the same."""
    once = items.groupBy("item").agg(F.sum(_weight(items)).alias("weight"))
    return summed(partial_tables(once, spec))


def build(df: DataFrame, item: str, spec: SketchSpec, strategy: str = "partials", weight: Column | None = None, **options) -> DataFrame:
    """Cells of the sketch of a column. Null items are skipped; an empty stream has no cells."""
    items = items_of(df, item, weight)
    make = {
        "serial": build_serial,
        "partials": build_partials,
        "shared_atomic": build_relational,
        "row_owned": build_row_owned,
        "combine_items": build_combined,
        "row_owned_balanced": build_balanced,
    }[strategy]
    return make(items, spec, **options)


def build_by_group(df: DataFrame, keys: list[str], item: str, spec: SketchSpec, weight: Column | None = None) -> DataFrame:
    """One sketch for each group: keys, sketch_row, sketch_col, cnt. Items are counted first, so
    a group of any size reaches the hash as its distinct items."""
    w = F.lit(1).cast("long") if weight is None else weight.cast("long")
    once = df.where(F.col(item).isNotNull()).groupBy(*keys, F.col(item).cast("long").alias("_item")).agg(F.sum(w).alias("_w"))
    cells = with_cells(once, "_item", spec)
    return cells.groupBy(*keys, "sketch_row", "sketch_col").agg(F.sum("_w").alias("cnt"))


def build_relaxed(df: DataFrame, pos: str, item: str, spec: SketchSpec, lanes: int, n: int) -> DataFrame:
    """What a shared table without atomic updates can lose, as a fixed model: ``lanes`` workers
    walk equal stretches in lock step, and updates of one counter in one tick count once.

    One lane loses nothing. The model is ours; it reproduces that losses grow with skew."""
    tick = F.col("pos") % -(-n // lanes)
    cells = with_cells(df.select(F.col(pos).alias("pos"), F.col(item).cast("long").alias("item")), "item", spec)
    once = cells.select("sketch_row", "sketch_col", tick.alias("_tick")).distinct()
    return once.groupBy("sketch_row", "sketch_col").agg(F.count("*").alias("cnt"))
