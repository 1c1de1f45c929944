"""Token counts of flat token files by scanning for separators (operator 10)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import byte_slices, new_shared_dir, read_table, settled, text_buffer, tidy, written
from .shared_files import atomic_writer, open_store, read_range
from .tokens import encoder, id_type, tokenizer_path

#: Fixed value: the end-of-document id of the vocabulary.
END_OF_TEXT = 50256
BLOCK_BYTES = 8 << 20


def write_flat_files(df: DataFrame, text: str, key: str, folder: str, path: str, end_id: int = END_OF_TEXT) -> DataFrame:
    """Write the ids of each text and ``end_id``, nothing else, one file for each partition.

    Returns (file, ordinal, key): which document is the n-th of which file. The files
    themselves have no header and no index. Names of special tokens in a text are written as plain
    text, so that no text holds ``end_id``. Null and empty texts leave a lone ``end_id``; rows with
    equal or null keys are documents of their own; other columns are ignored.
    """
    picked = df.select(F.col(key).alias("_key"), F.col(text).alias("_text"))
    kind = picked.schema["_key"].dataType.simpleString()

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, width = encoder(path, escape=True), id_type(path)
        name = f"tokens-{TaskContext.get().partitionId():06d}.bin"
        done = 0
        with atomic_writer(f"{folder}/{name}") as out:
            for b in batches:
                col = b.column(1)
                _, off = text_buffer(col)
                for lo, hi in byte_slices(off):
                    ids, counts = enc.encode([t or "" for t in col.slice(lo, hi - lo).to_pylist()])
                    flat = np.insert(ids.astype(width), np.cumsum(counts), width.type(end_id))
                    out.write(flat.tobytes())
                n = len(b)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([name] * n), pa.array(np.arange(done, done + n, dtype=np.int64)), b.column(0)], ["file", "ordinal", "key"]
                )
                done += n

    return picked.mapInArrow(tidy(write), f"file string, ordinal long, key {kind}")


def scan_separators(spark: SparkSession, folder: str, end_id: int = END_OF_TEXT, width: int = 2, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(file, ordinal, start, n_tokens) of every document of flat, unindexed token files.

    Files are cut into blocks without regard to documents. A task finds all separators of its
    block in one vectorised comparison; a running sum and a running maximum over the blocks'
    counts and last separators then give each block its first ordinal and the place where
    its first document began. ``n_tokens`` leaves the separator out. A last document without a
    separator is counted too. Empty files hold no documents, nor does an empty folder. Files are
    listed and cut by tasks; the driver sees none of them.
    """
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.bin").load(folder).select("path", "length")
    files = files.where(F.col("length") > 0).select(F.element_at(F.split("path", "/"), -1).alias("file"), F.col("length").alias("total"))
    each = files.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("total") - 1) / block_bytes))))
    each = each.withColumn("at", F.col("block") * block_bytes)
    plan = each.select("file", "block", "at", F.least(F.lit(block_bytes), F.col("total") - F.col("at")).alias("bytes"), F.floor(F.col("total") / width).alias("total"))
    plan = plan.repartition(max(1, int(spark.conf.get("spark.sql.shuffle.partitions"))), "file", "block")
    kind = np.dtype(f"<u{width}")

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                ids = np.frombuffer(read_range(f"{folder}/{r['file']}", r["at"], r["bytes"]), kind)
                hits = np.flatnonzero(ids == end_id) + r["at"] // width
                last = r["at"] + r["bytes"] == r["total"] * width
                if last and (not len(ids) or ids[-1] != end_id):
                    hits = np.append(hits, r["total"])  # the end of the file ends a document
                yield pa.RecordBatch.from_arrays(
                    [pa.array([r["file"]]), pa.array([r["block"]]), pa.array([len(hits)], pa.int64()),
                     pa.array([int(hits[-1]) if len(hits) else None], pa.int64()),
                     pa.array([hits.tolist()], pa.list_(pa.int64()))],
                    ["file", "block", "n", "last", "ends"],
                )

    found = written(plan.mapInArrow(tidy(scan), "file string, block long, n long, last long, ends array<long>"), "separators")
    before = W.partitionBy("file").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    stitched = found.select(
        "file",
        "ends",
        F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_first"),
        F.coalesce(F.max("last").over(before) + 1, F.lit(0)).alias("_open"),
    )
    each = stitched.select("file", "_first", "_open", "ends", F.posexplode("ends").alias("_k", "_end"))
    start = F.when(F.col("_k") == 0, F.col("_open")).otherwise(F.get("ends", F.col("_k") - 1) + 1)
    return each.select("file", (F.col("_first") + F.col("_k")).alias("ordinal"), start.alias("start"), (F.col("_end") - start).alias("n_tokens"))


@settled
def op10_separator_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every document, counted in flat files of the whole table."""
    docs = read_table(spark, sf_dir, "documents")
    folder = new_shared_dir(spark, "flat-tokens")
    path = tokenizer_path()
    store, where = open_store(folder)
    store.create_dir(where, recursive=True)
    index = written(write_flat_files(docs, "text", "doc_id", folder, path), "flat-index")
    counts = scan_separators(spark, folder, END_OF_TEXT, id_type(path).itemsize)
    return index.join(counts, ["file", "ordinal"]).select(F.col("key").alias("doc_id"), "file", "ordinal", "start", "n_tokens")
