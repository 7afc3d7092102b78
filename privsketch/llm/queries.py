"""The registered queries of the training-data operators: ``queries()`` and ``oracle_sql()`` for ``__spark_entry__``.

Each reads its whole table, applies its operator with production parameters and derives the digest columns.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import byte_bpe, embedding_cover, language_id, lm_score, media_ogg, packing, simhash, suffix_dedup, token_counts, toxicity


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), 2048)


def op2_media_ogg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_ogg.media_rows(documents(spark, sf_dir))


def op3_embedding_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_cover.near_duplicates(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), 0.95)


def op4_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_score.score(documents(spark, sf_dir), hold=(7, 2))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir), 2).select("doc_id", "fingerprint", "component_id")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"), hold=(3, 1))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(documents(spark, sf_dir), hold=(4, 2))


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.deduplicate(documents(spark, sf_dir)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.encode_digests(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_token_counts, op2_media_ogg, op3_embedding_cover, op4_lm_score, op5_simhash, op6_toxicity, op7_packing, op8_language_id, op9_suffix_dedup, op10_byte_bpe]
    return {f.__name__: f for f in found}


#: Links by brute force and reachability by recursion.
EMBEDDING_SQL = """
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
l AS (SELECT p.vec_id AS a, q.vec_id AS b FROM v p JOIN v q ON p.vec_id <> q.vec_id WHERE list_cosine_similarity(p.e, q.e) >= 0.95),
reach(a, b) AS (SELECT vec_id, vec_id FROM v UNION SELECT reach.a, l.b FROM reach JOIN l ON reach.b = l.a),
c AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a),
n AS (SELECT a AS vec_id, count(*) AS n_links FROM l GROUP BY a)
SELECT vec_id, coalesce(n_links, 0) AS n_links, component_id, vec_id = component_id AS kept FROM c LEFT JOIN n USING (vec_id)
"""

#: Every 50-byte string as hex, its first document, the covered stretches and what lies between them.
PASSAGE_SQL = """
WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS hx, length(hex(encode(coalesce(text, '')))) // 2 AS n_bytes FROM documents),
s AS MATERIALIZED (SELECT doc_id, i, substr(hx, 2 * i + 1, 100) AS g FROM (SELECT doc_id, hx, unnest(range(greatest(n_bytes - 49, 0))) AS i FROM d)),
f AS (SELECT g, min(doc_id) AS first FROM s GROUP BY g),
c AS (SELECT s.doc_id, s.i FROM s JOIN f USING (g) WHERE f.first < s.doc_id),
o AS (SELECT doc_id, i, CASE WHEN i - lag(i) OVER (PARTITION BY doc_id ORDER BY i) <= 50 THEN 0 ELSE 1 END AS fresh FROM c),
m AS MATERIALIZED (SELECT doc_id, run, min(i) AS a, max(i) + 50 AS b FROM (SELECT doc_id, i, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM o) GROUP BY doc_id, run),
k AS (SELECT doc_id, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS lo, a AS hi FROM m UNION ALL SELECT doc_id, max(b), any_value(n_bytes) FROM m JOIN d USING (doc_id) GROUP BY doc_id),
r AS (SELECT doc_id, string_agg(substr(hx, 2 * lo + 1, 2 * (hi - lo)), '' ORDER BY lo) AS kept FROM k JOIN d USING (doc_id) GROUP BY doc_id),
t AS (SELECT doc_id, sum(b - a) AS n_removed, count(*) AS n_spans FROM m GROUP BY doc_id)
SELECT doc_id, n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(CASE WHEN n_spans IS NULL THEN hx ELSE kept END)) AS kept_sha256
FROM d LEFT JOIN t USING (doc_id) LEFT JOIN r USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    """The others need hashes, tokenizers or models that SQL lacks; tests hold them against brute force."""
    return {"op3_embedding_cover": EMBEDDING_SQL, "op9_suffix_dedup": PASSAGE_SQL}
