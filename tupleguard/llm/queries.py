"""The registered queries of the corpus operators, with their oracles in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from . import decontaminate, kneser_ney, language_id, minhash_dedup, packing, pii, quality, textkit, token_counts, vector_dedup, warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of at most 1024 tokens, with certificates."""
    return packing.pack_documents(_table(spark, sf_dir, "documents"), capacity=1024)


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The quality score of every document, learned where crc32 mod 5 is not 0."""
    docs = _table(spark, sf_dir, "documents")
    held = textkit.crc_mod("doc_id", 5) == 0
    model = quality.fit(docs, _table(spark, sf_dir, "labels"), where=~held)
    out = quality.score(docs, model)
    return out.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greedy word-piece lengths of every document."""
    return token_counts.token_counts(_table(spark, sf_dir, "documents"))


def op4_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links of all vectors of a label at cosine 0.93, and their components."""
    return vector_dedup.vector_groups(_table(spark, sf_dir, "embeddings"), cosine=0.93)


def op5_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate groups of all documents, four-word shingles at 0.8."""
    out = minhash_dedup.near_duplicates(_table(spark, sf_dir, "documents"), k=4, percent=80)
    return out.select("doc_id", "n_shingles", "component_id", "kept")


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages written as WARC records and read back by byte ranges."""
    out = warc.round_trip(_table(spark, sf_dir, "pages"))
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document, learned from those whose crc32 mod 4 is not 2."""
    docs = _table(spark, sf_dir, "documents")
    held = textkit.crc_mod("doc_id", 4) == 2
    model = language_id.fit(docs, ~held)
    out = language_id.identify(docs.select("doc_id", "text"), model)
    return out.select("doc_id", held.alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its personal data replaced by surrogates."""
    docs = _table(spark, sf_dir, "documents")
    return pii.replace(docs.select("doc_id", "text"), key=b"production key")


def op9_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of every document by a trigram model of those whose crc32 mod 7 is not 2."""
    docs = _table(spark, sf_dir, "documents")
    held = textkit.crc_mod("doc_id", 7) == 2
    out = kneser_ney.score(docs, kneser_ney.fit(docs, ~held))
    return out.withColumn("held_out", held)


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which documents hold a benchmark item, with tolerance for substituted words."""
    return decontaminate.scan(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


OP4_SQL = r"""
WITH RECURSIVE ok AS (
  SELECT vec_id, label, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS e FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda v: v IS NULL OR NOT isfinite(v))) = 0
    AND len(list_filter(embedding, lambda v: v <> 0)) > 0
), pairs AS (
  SELECT a.vec_id AS x, b.vec_id AS y FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.93
), reach AS (
  SELECT vec_id, vec_id AS r FROM embeddings UNION SELECT reach.vec_id, pairs.y FROM reach JOIN pairs ON pairs.x = reach.r
), comp AS (SELECT vec_id, min(r) AS component_id FROM reach GROUP BY vec_id
), n AS (SELECT x, count(*) AS n_links FROM pairs GROUP BY x)
SELECT comp.vec_id, coalesce(n_links, 0) AS n_links, component_id, comp.vec_id = component_id AS kept FROM comp LEFT JOIN n ON n.x = comp.vec_id
"""

OP5_SQL = r"""
WITH RECURSIVE toks AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i+3], ' '))) END AS s FROM toks
), sh AS (SELECT doc_id, unnest(s) AS g, len(s) AS n FROM sets
), pairs AS (
  SELECT a.doc_id AS x, b.doc_id AS y FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))
), reach AS (
  SELECT doc_id, doc_id AS r FROM documents UNION SELECT reach.doc_id, pairs.y FROM reach JOIN pairs ON pairs.x = reach.r
), comp AS (SELECT doc_id, min(r) AS component_id FROM reach GROUP BY doc_id)
SELECT sets.doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component_id, sets.doc_id = component_id AS kept FROM sets JOIN comp ON comp.doc_id = sets.doc_id
"""

OP6_SQL = r"""
WITH p AS (SELECT page_id, coalesce(html, '') AS h, sha1(coalesce(html, '')) AS hex FROM pages
), f AS (SELECT hex, min(page_id) AS first_id FROM p GROUP BY hex
), d AS (
  SELECT p.page_id, p.h, f.first_id, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + CAST((CAST(('0x' || substr(p.hex, 1 + 10 * CAST(i // 8 AS INT), 10)) AS BIGINT) >> (35 - 5 * (i % 8))) & 31 AS INT), 1)), '') AS digest
  FROM p JOIN f ON p.hex = f.hex)
SELECT page_id, CAST(octet_length(encode(h)) AS BIGINT) AS payload_bytes, digest AS payload_digest,
  CASE WHEN page_id = first_id THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first_id THEN first_id END AS refers_to FROM d
"""

QUERIES = {
    "op1_packing": op1_packing,
    "op2_quality": op2_quality,
    "op3_token_counts": op3_token_counts,
    "op4_vector_dedup": op4_vector_dedup,
    "op5_minhash_dedup": op5_minhash_dedup,
    "op6_warc": op6_warc,
    "op7_language_id": op7_language_id,
    "op8_pii": op8_pii,
    "op9_kneser_ney": op9_kneser_ney,
    "op10_decontaminate": op10_decontaminate,
}
ORACLES = {"op4_vector_dedup": OP4_SQL, "op5_minhash_dedup": OP5_SQL, "op6_warc": OP6_SQL}
