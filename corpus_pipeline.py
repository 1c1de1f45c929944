"""From raw documents to packed training sequences: five stages over the whole table.

Each stage reads what its predecessor kept, as Parquet. All but the last return the columns of
``documents``. Every stage decides by row, through written row numbers, never by ``doc_id``: rows
whose ``doc_id`` is null or repeated have verdicts and masks of their own. An empty table passes
through all stages. The input's other columns, if any, are passed on as they are. A stage's result is
to be written before the next stage is called, for then the tables it rests on go.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freqsketch.llm.common import drop_dir, numbered, saved, ship_package, stage_scratch, written
from freqsketch.llm.minhash import near_duplicate_classes
from freqsketch.llm.mixing import mix_repetitions, word_count
from freqsketch.llm.packing import pack_documents
from freqsketch.llm.positions import picked, write_positions
from freqsketch.llm.quality import quality_verdicts, with_statistics
from freqsketch.llm.secrets import pair_key, redacted
from freqsketch.llm.tokens import tokenizer_path

#: Words in a shingle of the near-duplicate stage.
SHINGLE_WORDS = 5


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or are robust outliers of their group go.

    Null, empty and blank texts have fewer words than the base rules ask for, so they go. Null
    languages and sources are groups of their own; equal rows share their verdict; a very long text
    is judged like others."""
    ship_package(spark)
    with stage_scratch(spark):
        verdicts = quality_verdicts(with_statistics(docs, "text", docs.columns))
    return verdicts.where("kept").select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates one document stays, a first one with the smallest id.

    Of repeated rows one stays, also where they share an id; rows with a null id or a text without
    words stand alone and stay. Ties go to the first row in the order of the input."""
    ship_package(spark)
    with stage_scratch(spark):
        rows = numbered(docs, "_row", "near-duplicate-rows", keep=True)
        classes = near_duplicate_classes(rows, "text", "doc_id", words=SHINGLE_WORDS, row="_row")
        extra = write_positions(classes.where("not first").select("row", F.lit(1).alias("extra")), "extra-copies")
    return picked(rows, "_row", extra, -1).select(docs.columns)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Values that look live are masked; widely copied examples stay. No document goes.

    Null and empty texts stay as they are; a null source is one owner; ``n_chars`` follows the text
    and stays where the text is null; equal rows are masked alike."""
    ship_package(spark)
    with stage_scratch(spark):
        out = redacted(docs, "text", "source", pair_key("source", "lang"))
    n_chars = F.coalesce(F.char_length("text").cast("long"), F.col("n_chars"))
    return out.withColumn("n_chars", n_chars).select(docs.columns)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents, repeated or left out so that sources come near their targets.

    Null sources form one source, the last in order; texts without words have size 0: they come as
    often as their source comes whole, and half-way cases come once more. Equal rows are told apart by their row
    numbers."""
    with stage_scratch(spark):
        rows = numbered(docs, "_row", "mixing-rows", keep=True)
        sized = rows.select("_row", "doc_id", "source", word_count(F.col("text")).alias("size"))
        times = mix_repetitions(written(sized, "sizes"), row="_row").select("_row", F.col("whole").alias("_times"))
        times = written(times.where("_times > 0"), "times", keep=True)
    return rows.join(times, "_row").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 2048 ids, neighbours together.

    Null and empty texts are documents of the end id alone; rows with equal or null ids are packed
    each for itself; a text longer than a sequence goes on in the next."""
    ship_package(spark)
    with stage_scratch(spark):
        return pack_documents(docs, "text", "doc_id", tokenizer_path())


STAGES = [
    ("quality", quality),
    ("near_duplicates", near_duplicates),
    ("secrets", secrets),
    ("mixing", mixing),
    ("packing", packing),
]

#: SQL has neither robust estimates nor tokenizers; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``. A stage's result goes as soon as the next one's is written."""
    df, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES[:-1]:
        out = stage(spark, df, sf_dir)
        path = saved(out, f"stage-{name}")
        df = spark.read.schema(out.schema).parquet(path)
        if before:
            drop_dir(spark, before)
        before = path
    return STAGES[-1][1](spark, df, sf_dir)
