"""Near-duplicate vectors by an epsilon grid order join (operator 3)."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import new_shared_dir, numbered, read_table, settled, tidy, written
from .components import connected_components, settle
from .positions import Positions, write_positions
from .sharding import byte_prefix_shards
from .shared_files import atomic_writer, open_store, read_whole

COSINE = 0.95
#: Leading principal dimensions of the grid.
GRID_DIMS = 8
#: Leading principal dimensions that a pair is looked at in before all of them.
HEAD_DIMS = 23
#: What single precision may take from a cosine of the leading dimensions.
SLACK = 1e-5
#: Vectors in an interval of the sequence that a task holds, and in the smallest interval
#: that is compared as a whole.
BLOCK = 4096
LEAF = 256
#: Boxes under a node of the tree over the intervals.
FAN = 256
#: Intervals on each side that a task joins at most, and bytes of those it keeps.
TILE = 16
TILE_BYTES = 64 << 20


def _matrix(column: pa.Array, dim: int, scaled: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Rows as doubles, zero-padded to ``dim``, and whether each can link at all."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    lens = column.value_lengths().fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
    out = np.zeros((len(lens), dim))
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(float)  # null components become NaN
    have = np.maximum(lens, 0)
    rows = np.repeat(np.arange(len(lens)), have)
    cols = np.arange(len(flat)) - np.repeat(np.cumsum(have) - have, have)
    out[rows, cols] = flat
    good = (lens > 0) & np.isfinite(out).all(1)
    out[~good] = 0.0
    # the largest component becomes 1, so that no square overflows or vanishes
    scale = np.abs(out).max(1, initial=0.0)
    good &= scale > 0
    if not scaled:
        return out, good
    return out / np.where(scale > 0, scale, 1.0)[:, None], good


def _unit(m: np.ndarray) -> np.ndarray:
    return m / np.sqrt((m * m).sum(1, keepdims=True))


def principal_axes(vectors: DataFrame, dim: int, n_axes: int) -> np.ndarray:
    """Leading eigenvectors of the covariance of all unit vectors; dim^2 sums are collected."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(dim * dim + dim + 1)
        for b in batches:
            m, good = _matrix(b.column(0), dim)
            u = _unit(m[good])
            total += np.concatenate([(u.T @ u).ravel(), u.sum(0), [len(u)]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], ["i", "v"])

    got = vectors.select("v").mapInArrow(sums, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).toPandas()
    total = np.zeros(dim * dim + dim + 1)
    total[got["i"].to_numpy()] = got["v"].to_numpy()
    n = max(total[-1], 1.0)
    mean = total[dim * dim : -1] / n
    cov = total[: dim * dim].reshape(dim, dim) / n - np.outer(mean, mean)
    return np.linalg.eigh(cov)[1][:, ::-1][:, :n_axes]


def _box_gap(lo1, hi1, lo2, hi2) -> np.ndarray:
    """Least distance between boxes; no two of their points are nearer."""
    return np.sqrt((np.maximum(0.0, np.maximum(lo1 - hi2, lo2 - hi1)) ** 2).sum(-1))


def interval_join(lo: np.ndarray, hi: np.ndarray, a: tuple[int, int], b: tuple[int, int], eps: float) -> Iterator[tuple[int, int]]:
    """Pairs (i <= j) of the boxes of intervals a and b of one sequence that can hold vectors
    within ``eps``. Intervals whose common boxes are too distant are skipped whole, others
    are halved and joined again."""
    todo = [(a, b)]
    while todo:
        (a0, a1), (b0, b1) = todo.pop()
        if a0 >= a1 or b0 >= b1 or a0 >= b1:
            continue
        gap = _box_gap(lo[a0:a1].min(0), hi[a0:a1].max(0), lo[b0:b1].min(0), hi[b0:b1].max(0))
        if gap > eps:
            continue
        if a1 - a0 == 1 and b1 - b0 == 1:
            if a0 <= b0:
                yield a0, b0
            continue
        if a1 - a0 >= b1 - b0:
            mid = (a0 + a1) // 2
            todo += [((a0, mid), (b0, b1)), ((mid, a1), (b0, b1))]
        else:
            mid = (b0 + b1) // 2
            todo += [((a0, a1), (b0, mid)), ((a0, a1), (mid, b1))]


def _leaf_boxes(p: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    cuts = np.arange(0, len(p), LEAF)
    return cuts, np.minimum.reduceat(p, cuts), np.maximum.reduceat(p, cuts)


def _leaf_edges(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Few edges that connect what ``mask`` (rows x columns) connects."""
    r, c = mask.shape
    row, col = np.arange(r), r + np.arange(c)
    big = r + c
    while True:
        new_row = np.minimum(row, np.where(mask, col, big).min(1))
        new_col = np.minimum(col, np.where(mask, new_row[:, None], big).min(0))
        if (new_row == row).all() and (new_col == col).all():
            break
        row, col = new_row, new_col
    label = np.concatenate([row, col])
    node = np.flatnonzero(label != np.arange(big))
    return node, label[node]


def _leaf_mask(x: dict, a: slice, y: dict, b: slice, cosine: float) -> np.ndarray | None:
    """Which vectors of two leaves are linked (rows x columns); None if none are.

    The cosine of the leading dimensions and the lengths of what is left is never below the true one,
    so pairs that fall short there are done; few are left, unless the leaves are full of links."""
    near = x["h"][a] @ y["h"][b].T >= np.float32(cosine - SLACK)
    n = np.count_nonzero(near)
    if not n:
        return None
    if n * 16 > near.size:
        near = x["u"][a] @ y["u"][b].T >= cosine
    else:
        r, c = np.nonzero(near)
        near[r, c] = (x["u"][a][r] * y["u"][b][c]).sum(1) >= cosine
    near &= x["dim"][a, None] == y["dim"][None, b]
    return near


def join_blocks(x: dict, y: dict, same: bool, eps: float, cosine: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Links between two blocks, or inside one: (id, links, root) of vectors that have any."""
    nx = len(x["id"])
    ids = x["id"] if same else np.concatenate([x["id"], y["id"]])
    degree = np.zeros(len(ids), np.int64)
    shift = 0 if same else nx
    cx, lox, hix = _leaf_boxes(x["p"])
    cy, loy, hiy = (cx, lox, hix) if same else _leaf_boxes(y["p"])
    lo, hi = (lox, hix) if same else (np.concatenate([lox, loy]), np.concatenate([hix, hiy]))
    left = (0, len(cx))
    right = left if same else (len(cx), len(cx) + len(cy))
    ea, eb = [], []
    for i, j in interval_join(lo, hi, left, right, eps):
        j -= right[0]
        a0, a1, b0, b1 = cx[i], min(cx[i] + LEAF, nx), cy[j], min(cy[j] + LEAF, len(y["id"]))
        mask = _leaf_mask(x, slice(a0, a1), y, slice(b0, b1), cosine)
        if mask is None:
            continue
        inside = same and i == j
        if inside:
            np.fill_diagonal(mask, False)
        if not mask.any():
            continue
        degree[a0:a1] += mask @ y["times"][b0:b1]
        if not inside:
            degree[shift + b0 : shift + b1] += x["times"][a0:a1] @ mask
        node, label = _leaf_edges(mask)
        place = np.concatenate([np.arange(a0, a1), shift + np.arange(b0, b1)])
        ea.append(place[node])
        eb.append(place[label])
    if not ea:
        z = np.zeros(0, np.int64)
        return z, z, z
    return _classes(ids, degree, np.concatenate(ea), np.concatenate(eb))


def _classes(ids: np.ndarray, degree: np.ndarray, ea: np.ndarray, eb: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(id, links, root) of vectors with links, from edges between places."""
    order = np.argsort(ids, kind="stable")
    rank = np.empty(len(ids), np.int64)
    rank[order] = np.arange(len(ids))
    parent = settle(np.arange(len(ids)), rank[ea], rank[eb])
    root = ids[order][parent[rank]]
    have = degree > 0
    return ids[have], degree[have], root[have]


def _together(found: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What several pairs of blocks gave, as one row for each vector."""
    ids, links, roots = (np.concatenate(c) for c in zip(*found))
    names, at = np.unique(np.concatenate([ids, roots]), return_inverse=True)
    degree = np.zeros(len(names), np.int64)
    np.add.at(degree, at[: len(ids)], links)
    return _classes(names, degree, at[: len(ids)], at[len(ids) :])


def _block_pairs(blocks: DataFrame, n_blocks: int, n_axes: int, eps: float) -> DataFrame:
    """(i, j), i <= j, of the blocks whose boxes are within ``eps``: a tree of boxes, FAN to a node,
    is joined level by level from its root. A task sees the boxes under two nodes, and pairs of
    nodes that are too distant are never made."""

    def packed(level: DataFrame) -> DataFrame:
        box = F.sort_array(F.collect_list(F.struct("node", "lo", "hi")))
        return level.groupBy(F.floor(F.col("node") / FAN).cast("int").alias("node")).agg(box.alias("under"))

    ends = lambda f, c: F.array(*[f(F.get(c, F.lit(i))) for i in range(n_axes)])
    levels = [blocks.select(F.col("block").alias("node"), "lo", "hi")]
    n = n_blocks
    while n > FAN:
        up = levels[-1].groupBy(F.floor(F.col("node") / FAN).cast("int").alias("node")).agg(ends(F.min, "lo").alias("lo"), ends(F.max, "hi").alias("hi"))
        levels.append(written(up, "vector-boxes"))
        n = -(-n // FAN)

    def descend(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                same = r["i"] == r["j"]
                boxes = r["a"] if same else r["a"] + r["b"]
                lo, hi = (np.array([x[k] for x in boxes], float).reshape(-1, n_axes) for k in ("lo", "hi"))
                left = (0, len(r["a"]))
                right = left if same else (len(r["a"]), len(boxes))
                got = list(interval_join(lo, hi, left, right, eps))
                yield pa.RecordBatch.from_arrays([pa.array([boxes[x[k]]["node"] for x in got], pa.int32()) for k in (0, 1)], ["i", "j"])

    pairs = None
    for level in reversed(levels):
        under = packed(level)
        a = under.select(F.col("node").alias("i"), F.col("under").alias("a"))
        b = under.select(F.col("node").alias("j"), F.col("under").alias("b"))
        if pairs is None:
            pairs = a.select("i", F.col("i").alias("j"))
        pairs = written(pairs.join(a, "i").join(b, "j").select("i", "j", "a", "b").mapInArrow(tidy(descend), "i int, j int"), "vector-pairs")
    return pairs


def vector_links(df: DataFrame, key: str, vector: str, cosine: float = COSINE, n_axes: int = GRID_DIMS, block: int = BLOCK) -> DataFrame:
    """(id, n_links, component_id) for every row of (key, vector).

    Unit vectors are sorted by their grid cells (side: the distance that the cosine stands
    for) on the leading principal axes of all vectors; the sequence is cut into intervals,
    and a recursive join over a tree of their bounding boxes keeps the pairs of intervals that can
    hold links; a task joins such pairs, recursing further. Distances on the axes never
    exceed true ones, so no link is lost. Equal vectors are joined as one and counted.

    The sequence is made of row numbers and cells. Vectors as given are shuffled once, to the file of
    their interval in the shared folder, which the tasks that join it read: what is shuffled and kept grows
    with the table, however many pairs of intervals there are.

    Tasks return each vector's number of links and a root of its local class, never the links
    themselves, so that a group of copies costs its size. Vectors that are null, empty, zero
    or hold null or non-finite components link with nothing, nor do vectors of different
    length. Every row is a vector of its own, also where rows or keys repeat; a row whose key
    is null stays alone. Other columns are ignored; an empty table gives no rows.
    """
    spark = df.sparkSession
    eps = math.sqrt(max(0.0, 2 - 2 * cosine)) + 1e-9
    src = df.select(F.col(key).cast("long").alias("id"), F.col(vector).alias("v"))
    kind = src.schema["v"].dataType.simpleString()

    def identify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lens = b.column(1).value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
            m, good = _matrix(b.column(1), max(int(lens.max(initial=0)), 1), scaled=False)
            good &= b.column(0).is_valid().to_numpy(zero_copy_only=False)
            digests = [hashlib.blake2b(r[:n].tobytes(), digest_size=16).digest() if ok else None for r, n, ok in zip(m, lens.tolist(), good.tolist())]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(digests, pa.binary())], ["id", "v", "_d"])

    rows = numbered(src.mapInArrow(tidy(identify), f"id long, v {kind}, _d binary"), "_r", "vectors", keep=True)
    heads = rows.where("_d is not null").groupBy("_d").agg(F.min("_r").alias("head"), F.count("*").alias("times"), F.min("id").alias("least"))
    heads = written(heads, "vector-heads", keep=True)
    times_of = write_positions(heads.select("head", "times"), "vector-times")
    dim = max(int(rows.agg(F.max(F.size("v"))).first()[0] or 0), 1)
    n_axes = min(n_axes, dim)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        times = Positions(times_of)
        for b in batches:
            n = times.of(b.column(0).to_numpy())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n)], ["_r", "v", "times"]).filter(pa.array(n > 0))

    ones = rows.select("_r", "v").mapInArrow(tidy(first), f"_r long, v {kind}, times int")
    axes = spark.sparkContext.broadcast(principal_axes(ones, dim, min(max(n_axes, HEAD_DIMS), dim)))

    def on_axes(v: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        u = _unit(_matrix(v, dim)[0])
        return u, u @ axes.value

    cell_of = lambda p: np.floor(p[:, :n_axes] / eps).astype(np.int32)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cells = cell_of(on_axes(b.column(1))[1])
            offsets = pa.array(np.arange(len(b) + 1, dtype=np.int32) * n_axes)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, pa.array(cells.ravel()))], ["id", "cell"])

    placed = written(ones.mapInArrow(tidy(place), "id long, cell array<int>"), "vector-places")
    n_blocks = max(1, -(-placed.count() // block))
    sequence = byte_prefix_shards(placed, [F.get("cell", F.lit(i)) for i in range(n_axes)], F.lit(1), n_blocks, {"id": F.col("id")})
    block_of = write_positions(sequence.select("id", "shard"), "vector-shards")
    spark.sparkContext._jvm.System.gc()  # shuffles of the sequence go before vectors are shuffled
    folder = new_shared_dir(spark, "vector-files", keep=True)
    store, where = open_store(folder)
    store.create_dir(where, recursive=True)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = Positions(block_of)
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(at.of(b.column(0).to_numpy()))], ["_r", "v", "times", "block"])

    def pack(table: pa.Table) -> pa.Table:
        number, p = table.column("block")[0].as_py(), on_axes(table.column("v"))[1]
        table = table.take(np.lexsort(cell_of(p).T[::-1])).select(["_r", "v", "times"])
        sink = pa.BufferOutputStream()
        with pa.ipc.new_file(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
            out.write_table(table)
        with atomic_writer(f"{folder}/{number}") as f:
            f.write(sink.getvalue())
        p = p[:, :n_axes]
        return pa.table({"block": pa.array([number], pa.int32()), "lo": [p.min(0).tolist()], "hi": [p.max(0).tolist()]})

    blocks = written(
        ones.mapInArrow(tidy(deal), f"_r long, v {kind}, times int, block int").groupBy("block").applyInArrow(tidy(pack), "block int, lo array<double>, hi array<double>"),
        "vector-blocks",
    )
    spark.sparkContext._jvm.System.gc()
    pairs = _block_pairs(blocks, n_blocks, n_axes, eps)
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    side = max(1, min(TILE, n_blocks // math.isqrt(6 * tasks), TILE_BYTES // (block * dim * 8)))
    tasks = max(tasks, min((n_blocks // side) ** 2 // 8, 100 * tasks))
    tile = [F.floor(F.col(c) / side).cast("int").alias(f"_{c}") for c in ("i", "j")]

    def load(number: int) -> dict:
        t = pa.ipc.open_file(pa.py_buffer(read_whole(f"{folder}/{number}"))).read_all().combine_chunks()
        v = t.column("v").combine_chunks()
        u, p = on_axes(v)
        h = p[:, :HEAD_DIMS]
        h = np.column_stack([h, np.sqrt(np.maximum(0.0, 1 - (h * h).sum(1)))]).astype(np.float32)
        return {"id": t.column("_r").to_numpy(), "times": t.column("times").to_numpy().astype(np.int64), "u": u, "h": h, "p": np.ascontiguousarray(p[:, :n_axes]),
                "dim": v.value_lengths().to_numpy(zero_copy_only=False)}

    def join(table: pa.Table) -> pa.Table:
        left, found, y, last = {}, [(np.zeros(0, np.int64),) * 3], None, None
        for i, j in sorted(zip(table.column("i").to_pylist(), table.column("j").to_pylist()), key=lambda p: (p[1], p[0])):
            if j != last:
                y, last = left[j] if j in left else load(j), j
            if i not in left:
                left[i] = y if i == j else load(i)
            found.append(join_blocks(left[i], y, i == j, eps, cosine))
        return pa.table(dict(zip(("id", "links", "root"), map(pa.array, _together(found)))))

    found = written(
        pairs.select("i", "j", *tile).repartition(tasks, "_i", "_j").groupBy("_i", "_j").applyInArrow(tidy(join), "id long, links long, root long"),
        "vector-links", keep=True,
    )
    degrees = found.groupBy(F.col("id").alias("head")).agg(F.sum("links").alias("links"))
    classes = connected_components(found.select(F.col("id").alias("a"), F.col("root").alias("b"))).select(F.col("node").alias("head"), "component")
    by_head = heads.join(degrees, "head", "left").join(classes, "head", "left").withColumn("_c", F.coalesce("component", "head"))
    names = by_head.groupBy(F.col("_c").alias("_k")).agg(F.min("least").alias("_least"))
    by_head = by_head.join(names, F.col("_c") == F.col("_k"), "left").select(
        F.col("_d").alias("_hd"), (F.coalesce("links", F.lit(0)) + F.col("times") - 1).alias("_n"), F.col("_least").alias("_c")
    )
    return rows.select("id", "_d").join(by_head, F.col("_d") == F.col("_hd"), "left").select(
        "id", F.coalesce("_n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("_c", "id").alias("component_id")
    )


@settled
def op3_grid_order_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links and class of every vector; see ``vector_links``."""
    out = vector_links(read_table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    kept = F.col("id").eqNullSafe(F.col("component_id"))
    return out.select(F.col("id").alias("vec_id"), "n_links", "component_id", kept.alias("kept"))
