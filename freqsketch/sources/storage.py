"""Tables, scratch folders and streams."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def ship_package(spark: SparkSession) -> None:
    """Make this package importable on executors, whatever started the session."""
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


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, tag: str) -> str:
    """A new folder that all executors share, under the session's checkpoint folder. Without one a
    temporary folder is used if all of Spark is on this machine; on a cluster that is an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        set_ = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not set_.isEmpty():
            root = set_.get()
        elif spark.sparkContext.master.startswith("local"):
            root = tempfile.gettempdir()
        else:
            raise RuntimeError("name a folder that driver and executors share in spark.checkpoint.dir")
    if "://" not in root and not root.startswith("file:"):
        root = "file://" + os.path.abspath(root)
    return f"{root.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def stored(df: DataFrame, tag: str) -> DataFrame:
    """A table that is written once and then read wherever it is used."""
    path = scratch(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def csv_copy(df: DataFrame, tag: str = "csv") -> DataFrame:
    """The rows of a flat table through CSV files, read with the table's schema."""
    path = scratch(df.sparkSession, tag)
    df.write.option("header", True).csv(path)
    return df.sparkSession.read.schema(df.schema).option("header", True).csv(path)


def rate_stream(spark: SparkSession, rows: int) -> DataFrame:
    """A stream of (timestamp, value) with the values 0, 1, 2, ..., ``rows`` of them a micro-batch."""
    return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).load()


def stream(spark: SparkSession, sf_dir: str, name: str, max_files: int = 1) -> DataFrame:
    """A file stream over a table, with the schema of its batch form."""
    schema = table(spark, sf_dir, name).schema
    # a file source wants a folder or a pattern, also where the table is one file
    glob = f"{sf_dir}/{name[:-1]}[{name[-1]}].parquet"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(glob)
