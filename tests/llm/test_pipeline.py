from pyspark.sql import functions as F

import corpus_pipeline
from privsketch.llm import suffix_dedup, toxicity
from privsketch.llm._util import keep


def test_stages_on_documents(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "toxicity", "simhash_near_dedup", "suffix_array_dedup", "packing"]
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, keep(stage(spark, docs, small), name)
        seen[name] = docs
        if name != "packing":
            assert docs.columns == corpus_pipeline.COLUMNS and docs.count() <= before.count()
    assert seen["language_id"].filter("lang is null").count() == 0
    assert toxicity.toxicity(seen["toxicity"], spark.read.parquet(f"{small}/labels.parquet")).count() == seen["toxicity"].count()
    again = suffix_dedup.deduplicate(seen["simhash_near_dedup"]).agg(F.sum(F.col("n_bytes") - F.col("n_removed"))).first()[0]
    left = seen["suffix_array_dedup"].agg(F.sum(F.octet_length("text"))).first()[0]
    assert again - 8 * 200 <= left <= again
    assert seen["packing"].select("doc_id").distinct().count() == seen["suffix_array_dedup"].count()


def test_run_equals_the_stages(spark, small):
    out = corpus_pipeline.run(spark, small)
    assert out.columns == ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    assert out.groupBy("sequence_id").agg(F.sum("length").alias("n")).filter("n > 2048").count() == 0


def test_pipeline_of_odd_documents(spark, odd, tmp_path):
    odd.select("doc_id", "text", "lang", "source", "n_chars").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(4, 0, 1), (7, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() >= 1
    empty = tmp_path / "empty"
    odd.select("doc_id", "text", "lang", "source", "n_chars").filter("false").write.parquet(str(empty / "documents.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(empty / "labels.parquet"))
    assert corpus_pipeline.run(spark, str(empty)).count() == 0
