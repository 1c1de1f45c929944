"""Tabulation hashing: random tables, the separate and the merged layout, a modular family."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.functions.keys import byte_columns
from freqsketch.spec import SketchSpec

#: Fixed value: the modulus of the modular family, a prime just above 2^32.
MODULUS = 4294967311


@lru_cache(maxsize=16)
def hash_tables(depth: int, chars: int, seed: int) -> np.ndarray:
    """Random 32-bit values (chars, 256, depth): the depth functions lie side by side, so that
    one place of a character holds the contribution to every function."""
    out = np.empty((chars, 256, depth), np.int64)
    for r in range(depth):
        for c in range(chars):
            for v in range(256):
                out[c, v, r] = int(hashlib.md5(f"{seed}:{r}:{c}:{v}".encode()).hexdigest()[:8], 16)
    return out


def hash_table_df(spark: SparkSession, spec: SketchSpec) -> DataFrame:
    """The same values as a relation (hash_id, char_pos, char_val, rnd)."""
    t = spark.range(spec.depth * spec.chars * 256)
    cols = t.select(
        F.floor(F.col("id") / (spec.chars * 256)).cast("int").alias("hash_id"),
        (F.floor(F.col("id") / 256) % spec.chars).cast("int").alias("char_pos"),
        (F.col("id") % 256).cast("int").alias("char_val"),
    )
    text = F.concat_ws(":", F.lit(str(spec.seed)), "hash_id", "char_pos", "char_val")
    return cols.withColumn("rnd", F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long"))


def merged_table_df(spark: SparkSession, spec: SketchSpec) -> DataFrame:
    """One row for each character and value: the contributions to all functions together."""
    g = hash_table_df(spark, spec).groupBy("char_pos", "char_val")
    return g.agg(F.transform(F.array_sort(F.collect_list(F.struct("hash_id", "rnd"))), lambda s: s["rnd"]).alias("rnd"))


def _words(t: np.ndarray) -> np.ndarray:
    """32-bit entries of the last axis packed two by two in 64-bit words."""
    if t.shape[-1] % 2:
        t = np.concatenate([t, np.zeros_like(t[..., :1])], -1)
    return np.ascontiguousarray(t).view(np.uint64)


@lru_cache(maxsize=8)
def merged_tables(depth: int, chars: int, seed: int) -> list[np.ndarray]:
    """For each character (256, depth) 32-bit entries: a slice holds what it adds to every function."""
    return list(_words(hash_tables(depth, chars, seed).astype(np.uint32)))


@lru_cache(maxsize=8)
def separate_tables(depth: int, chars: int, seed: int) -> list[list[np.ndarray]]:
    """For each function a table of 256 32-bit entries for each character."""
    t = hash_tables(depth, chars, seed).astype(np.uint32)
    return [[np.ascontiguousarray(t[c, :, r]) for c in range(chars)] for r in range(depth)]


@lru_cache(maxsize=8)
def paired_tables(depth: int, chars: int, seed: int) -> list[np.ndarray]:
    """The merged tables of two neighbouring characters combined: (65536, depth) for each pair,
    packed in 64-bit words, so that half as many slices are read and XORed."""
    t = hash_tables(depth, chars, seed).astype(np.uint32)
    return [_words((t[c][None, :, :] ^ t[c + 1][:, None, :]).reshape(65536, -1)) for c in range(0, chars, 2)]


#: Items hashed at a time: their slices stay in a core's cache.
CHUNK = 8192


def _mod(h: np.ndarray, width: int | None) -> np.ndarray:
    if width is None:
        return h
    w = np.uint32(width)
    return h - (h // w) * w  # division by a scalar is vectorised, the remainder is not


def _hashed(x: np.ndarray, spec: SketchSpec, layout: str, width: int | None) -> np.ndarray:
    """(n, depth) hash values, or column ids with a width; stored row after row."""
    key = (spec.depth, spec.chars, spec.seed)
    out = np.empty((spec.depth, len(x)), np.int64)
    if layout == "separate":
        tables = separate_tables(*key)
        for lo in range(0, len(x), CHUNK):
            part = x[lo : lo + CHUNK]
            chars = [(part >> (8 * c)) & 255 for c in range(spec.chars)]
            for r in range(spec.depth):
                h = tables[r][0].take(chars[0])
                for c in range(1, spec.chars):
                    h ^= tables[r][c].take(chars[c])
                out[r, lo : lo + len(part)] = _mod(h, width)
        return out.T
    tables, bits = (merged_tables(*key), 8) if layout == "merged" else (paired_tables(*key), 16)
    for lo in range(0, len(x), CHUNK):
        part = x[lo : lo + CHUNK]
        h = tables[0].take(part & ((1 << bits) - 1), 0)
        for k in range(1, len(tables)):
            h ^= tables[k].take((part >> (bits * k)) & ((1 << bits) - 1), 0)
        out[:, lo : lo + len(part)] = _mod(h.view(np.uint32), width)[:, : spec.depth].T
    return out.T


def hash_values(items: np.ndarray, spec: SketchSpec, layout: str = "paired") -> np.ndarray:
    """(n, depth) 32-bit hash values. ``merged`` reads one slice per character, ``separate`` one
    entry per character and function, ``paired`` one slice per two characters; values are equal."""
    return _hashed(items.astype(np.int64, copy=False), spec, layout, None)


@lru_cache(maxsize=16)
def modular_factors(depth: int, seed: int) -> tuple[tuple[int, int], ...]:
    """(a, b) of each row: 1 <= a < 2^31 and 0 <= b < 2^32, so that products fit in a BIGINT."""
    take = lambda s: int(hashlib.md5(s.encode()).hexdigest()[:8], 16)
    return tuple((1 + take(f"{seed}:a:{r}") % (2**31 - 1), take(f"{seed}:b:{r}")) for r in range(depth))


def columns(items: np.ndarray, spec: SketchSpec, layout: str = "paired") -> np.ndarray:
    """(n, depth) column ids."""
    if spec.hash_family == "modular":
        x = items.astype(np.int64) & 0xFFFFFFFF
        return np.stack([(a * x + b) % MODULUS % spec.width for a, b in modular_factors(spec.depth, spec.seed)], 1)
    if spec.width < 1 << 32:
        return _hashed(items.astype(np.int64, copy=False), spec, layout, spec.width)
    return hash_values(items, spec, layout) % spec.width


@lru_cache(maxsize=32)
def _row_pair_tables(depth: int, chars: int, seed: int, pair: int) -> list[np.ndarray]:
    """What ``paired_tables`` hold for two neighbouring functions, each a vector of its own."""
    return [np.ascontiguousarray(t[:, pair]) for t in paired_tables(depth, chars, seed)]


def columns_by_row(items: np.ndarray, spec: SketchSpec, layout: str = "paired"):
    """(row, column ids) one sketch row after the other, with the memory of two rows."""
    if layout != "paired" or spec.hash_family == "modular" or spec.width >= 1 << 32:
        cols = columns(items, spec, layout)
        yield from ((r, cols[:, r]) for r in range(spec.depth))
        return
    x = items.astype(np.int64, copy=False)
    parts = [((x >> (16 * k)) & 0xFFFF).astype(np.int32) for k in range(spec.chars // 2)]
    for pair in range(-(-spec.depth // 2)):
        tables = _row_pair_tables(spec.depth, spec.chars, spec.seed, pair)
        h = tables[0].take(parts[0])
        for t, k in zip(tables[1:], parts[1:]):
            h ^= t.take(k)
        two = h.view(np.uint32).reshape(-1, 2)
        w = np.uint32(spec.width)
        for r in range(2 * pair, min(2 * pair + 2, spec.depth)):
            one = np.ascontiguousarray(two[:, r % 2])
            yield r, (one - (one // w) * w).astype(np.int64)


def _lists(values: np.ndarray, kind) -> pa.Array:
    """Rows of an array as Arrow lists."""
    n, d = values.shape
    flat = pa.array(np.ascontiguousarray(values).ravel().astype(kind))
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), flat)


def columns_udf(spec: SketchSpec, layout: str = "paired"):
    """Arrow function BIGINT -> array of column ids, one for each sketch row; null for null."""

    @F.arrow_udf("array<int>")
    def cols(item: pa.Array) -> pa.Array:
        filled = item.fill_null(0)
        out = _lists(columns(filled.to_numpy(zero_copy_only=False), spec, layout), np.int32)
        return pc.if_else(item.is_null(), None, out) if item.null_count else out

    return cols


def hashes_udf(spec: SketchSpec):
    """Arrow function BIGINT -> array of 32-bit hash values, one for each sketch row."""

    @F.arrow_udf("array<bigint>")
    def values(item: pa.Array) -> pa.Array:
        return _lists(hash_values(item.fill_null(0).to_numpy(zero_copy_only=False), spec), np.int64)

    return values


def with_cells(df: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """One row for each row and sketch row: the input's columns, sketch_row, sketch_col."""
    return df.select("*", F.posexplode(columns_udf(spec)(F.col(item))).alias("sketch_row", "sketch_col"))


def separate_cells(spark: SparkSession, df: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """The separate layout as a relation: each byte meets every function's own table. The
    tables' size is fixed by the spec."""
    bytes_ = F.posexplode(F.array(*byte_columns(F.col(item), spec.chars))).alias("char_pos", "char_val")
    looked = df.select(item, bytes_).join(F.broadcast(hash_table_df(spark, spec)), ["char_pos", "char_val"])
    return looked.groupBy(item, F.col("hash_id").alias("sketch_row")).agg(
        (F.bit_xor("rnd") % spec.width).cast("int").alias("sketch_col")
    )


def merged_cells(spark: SparkSession, df: DataFrame, item: str, spec: SketchSpec) -> DataFrame:
    """The merged layout as a relation: one lookup per byte returns a slice; slices are combined
    position by position, without a shuffle."""
    table = merged_table_df(spark, spec)
    out = df.select(item)
    folded: Column | None = None
    for c, b in enumerate(byte_columns(F.col(item), spec.chars)):
        t = table.where(F.col("char_pos") == c).select(F.col("char_val").alias(f"_v{c}"), F.col("rnd").alias(f"_r{c}"))
        out = out.join(F.broadcast(t), b == F.col(f"_v{c}"))
        nxt = F.col(f"_r{c}")
        folded = nxt if folded is None else F.zip_with(folded, nxt, lambda x, y: x.bitwiseXOR(y))
    return out.select(item, F.posexplode(F.transform(folded, lambda h: (h % spec.width).cast("int"))).alias("sketch_row", "sketch_col"))
