"""A corpus pipeline of five stages over ``documents``: language ID, near-duplicate removal,
benchmark decontamination, personal data, packing.

Each stage takes ``(spark, docs, sf_dir)``, works on all rows that its predecessor kept and
returns a DataFrame; all but the last return the columns of ``documents``. ``run`` writes each
stage's rows as Parquet in the shared folder and reads them again for the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from tupleguard.llm import decontaminate, language_id, minhash_dedup, packing, pii
from tupleguard.llm.state import keep, release
from tupleguard.shipping import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of an identifiable language, ``lang`` set to it: those without text or without
    a letter go. Learns from the labelled documents of its input."""
    ship(spark)
    found = language_id.identify(docs, language_id.fit(docs))
    return found.where("lang_pred <> 'und'").withColumn("lang", F.col("lang_pred")).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group: five-word shingles, similarity 0.8 or more."""
    ship(spark)
    return minhash_dedup.keep_one(docs, k=5, percent=80).select(*docs.columns)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    ship(spark)
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*docs.columns)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents with surrogates for personal data; ``n_chars`` follows the new text."""
    ship(spark)
    out = pii.replace(docs, key=b"production key")
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("pii_entities") > 0, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of at most 1024 tokens."""
    ship(spark)
    return packing.pack_documents(docs, capacity=1024)


STAGES = [
    ("language_id", languages),
    ("minhash_near_dedup", near_duplicates),
    ("benchmark_decontamination", benchmark_leaks),
    ("pii_surrogates", personal_data),
    ("best_fit_packing", sequences),
]

#: The stages' models have no SQL form; ``tests/llm`` holds a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        before, docs = docs, keep(stage(spark, docs, sf_dir), f"pipeline-{name}", None)
        if hasattr(before, "kept_path"):
            release(before)
    return docs
