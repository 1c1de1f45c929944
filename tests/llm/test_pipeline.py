import corpus_pipeline
from pyspark.sql import functions as F

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages(spark, sf, tmp_path):
    df = docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        df = stage(spark, df, sf)
        assert name == "packing" or df.columns == COLUMNS
        df.write.parquet(str(tmp_path / name))
        df = kept[name] = spark.read.parquet(str(tmp_path / name))
    assert kept["near_duplicates"].select("doc_id").distinct().count() == kept["near_duplicates"].count() <= kept["quality"].count() <= docs.count()
    assert kept["secrets"].count() == kept["near_duplicates"].count()
    mixed = kept["mixing"].select("doc_id").distinct()
    assert mixed.join(kept["secrets"], "doc_id", "left_anti").count() == 0
    packed = kept["packing"].groupBy("doc_id").agg(F.sum("length").alias("n"), F.max("doc_tokens").alias("one"))
    copies = kept["mixing"].groupBy("doc_id").agg(F.count("*").alias("copies"))
    assert packed.join(copies, "doc_id").where("n <> one * copies").count() == 0 and packed.count() == mixed.count()
