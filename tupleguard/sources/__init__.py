"""Relations for guarded sessions: files and frames registered under the names policies use."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def register(spark: SparkSession, sf_dir: str, tables=TABLES) -> None:
    """Views over ``<sf_dir>/<table>.parquet``."""
    for t in tables:
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)


def read(spark: SparkSession, name: str, path: str, format: str = "parquet", schema=None, **options) -> DataFrame:  # noqa: A002
    """A file source of any format of Spark's (parquet, csv, json, orc), named for policies."""
    reader = spark.read.format(format).options(**options)
    df = (reader.schema(schema) if schema is not None else reader).load(path)
    df.createOrReplaceTempView(name)
    return df


class GuardedSession:
    """The only handle that a guarded caller gets: queries go through the guard."""

    def __init__(self, guard):
        self._guard = guard

    def sql(self, text: str) -> DataFrame:
        return self._guard.query(text)

    def table(self, name: str) -> DataFrame:
        return self._guard.query(f"select * from {name}")
