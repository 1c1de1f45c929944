"""Connected components of an edge table, without the driver seeing edges or nodes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import scratch, tidy, written


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component): every node of an edge, with the smallest node it reaches.

    First every task shrinks the edges it reads to stars, which takes no shuffle and most of the
    rounds away. Then rounds of two star operations: each node hands its larger neighbours to the smallest node
    around it, then its smaller ones. Edges never grow in number; the rounds needed grow with
    the logarithm of the nodes. A node with very many neighbours costs no task their number:
    minima combine before the shuffle, and the join against them is an equi-join that adaptive
    execution splits. Loops and repeated edges are ignored.
    """
    with scratch(edges.sparkSession):
        e = written(_undirected(_local_stars(edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")))), "edges")
        state = _checksum(e)
        for _ in range(max_rounds):
            if not state[0]:
                break
            e = written(_small_star(_large_star(e)), "edges")
            before, state = state, _checksum(e)
            if state == before:
                break
        else:
            raise RuntimeError("components did not settle")
        ends = F.explode(F.array("a", "b")).alias("node")
        return written(e.select(ends, F.col("b").alias("component")).distinct(), "components", keep=True)


def _local_stars(edges: DataFrame, chunk: int = 1 << 20) -> DataFrame:
    """Edges that connect the same nodes, each to the smallest of its part of the input."""

    def shrink(batches):
        held_a, held_b, n = [], [], 0

        def stars():
            a, b = np.concatenate(held_a), np.concatenate(held_b)
            nodes, code = np.unique(np.concatenate([a, b]), return_inverse=True)
            parent = settle(np.arange(len(nodes)), code[: len(a)], code[len(a) :])
            leaf = np.flatnonzero(parent != np.arange(len(nodes)))
            return nodes[leaf], nodes[parent[leaf]]

        for t in batches:
            held_a.append(t.column(0).to_numpy())
            held_b.append(t.column(1).to_numpy())
            n += len(t)
            if n >= chunk:
                yield pa.RecordBatch.from_arrays(list(map(pa.array, stars())), ["a", "b"])
                held_a, held_b, n = [], [], 0
        if n:
            yield pa.RecordBatch.from_arrays(list(map(pa.array, stars())), ["a", "b"])

    return edges.where("a is not null and b is not null and a <> b").mapInArrow(tidy(shrink), "a long, b long")


def settle(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest node that each node reaches through edges (a, b) and the pointers given."""
    while len(a):
        low = np.minimum(parent[a], parent[b])
        np.minimum.at(parent, parent[a], low)
        np.minimum.at(parent, parent[b], low)
        while True:
            up = parent[parent]
            if (up == parent).all():
                break
            parent = up
        keep = parent[a] != parent[b]
        a, b = a[keep], b[keep]
    return parent


def _checksum(e: DataFrame) -> tuple:
    """Number of edges and two sums over them; equal edge sets have equal sums."""
    other = F.xxhash64(F.lit(1), "b", "a").bitwiseAND((1 << 40) - 1)
    return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").bitwiseAND((1 << 40) - 1)), F.sum(other)).first())


def _undirected(e: DataFrame) -> DataFrame:
    """Each edge once, from its larger to its smaller node."""
    return (
        e.where("a is not null and b is not null and a <> b")
        .select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        .distinct()
    )


def _large_star(e: DataFrame) -> DataFrame:
    both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m"))
    # larger neighbours of each node go to the least node around it
    return _undirected(both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")))


def _small_star(e: DataFrame) -> DataFrame:
    # edges point from larger to smaller nodes; all smaller neighbours join the least one
    least = e.groupBy("a").agg(F.min("b").alias("m"))
    joined = e.join(least, "a")
    return _undirected(
        joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    )
