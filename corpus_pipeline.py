"""A corpus pipeline of five stages: language, toxicity, near-duplicates, repeated passages, packing.

Every stage takes ``(spark, docs, sf_dir)``; all but the last return the columns of ``documents``. ``run`` writes each result as Parquet to
the shared folder and reads it back as the next stage's documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privsketch.llm import language_id, packing, simhash, suffix_dedup, toxicity
from privsketch.llm._util import keep

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: A text whose language is no likelier than all others together is rejected.
LEAST_LANGUAGE_SCORE = 0.5


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without letters and texts of no clear language; a missing ``lang`` is filled with the prediction."""
    marked = language_id.with_language(docs, None, language_id.ORDER, language_id.SAMPLE_DOCS, (4, 2), COLUMNS[1:])
    kept = marked.filter((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_LANGUAGE_SCORE))
    return kept.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts that score at or over the operator's threshold."""
    machine = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), (3, 1))
    return toxicity.with_score(docs, machine, COLUMNS[1:]).filter(F.col("score") < toxicity.THRESHOLD).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest doc_id of each group; documents without an id cannot be compared by it and stay."""
    marked = keep(simhash.fingerprints(docs), "fingerprints")
    first = simhash.grouped(marked).filter("doc_id = component_id").select("doc_id").distinct()
    own = docs.select(*COLUMNS)
    return own.join(first, "doc_id", "left_semi").union(own.filter("doc_id is null")).select(*COLUMNS)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts passages that start in an earlier document; every document stays, with what is left of it."""
    cut = suffix_dedup.without_repeats(docs.drop("n_chars"), ["lang", "source"])
    return cut.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("language_id", language), ("toxicity", toxic), ("simhash_near_dedup", near_duplicates), ("suffix_array_dedup", repeated_passages), ("packing", pack)]

#: No stage but the last could be said in SQL; the pipeline is tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = keep(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
