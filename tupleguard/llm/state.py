"""Where intermediate results are kept: the shared folder of ``spark.checkpoint.dir``.

The setting is read from the session. Only where it is unset (tests on one machine) is a
folder of our own used."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    jsc = spark.sparkContext._jsc.sc()
    have = jsc.getCheckpointDir()
    if have.isDefined():
        return have.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        named = "file://" + os.path.join(tempfile.gettempdir(), "tupleguard-checkpoints")
    spark.sparkContext.setCheckpointDir(named)
    return jsc.getCheckpointDir().get()


def shared_path(spark: SparkSession, name: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_root(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


#: Files of a kept table of narrow rows, at most, for each core of the cluster. Creating a file
#: costs an executor a call to the file system (a forked process on some); tables of whole
#: texts keep the partitions that they have.
FILES_A_CORE = 1


def packed(df: DataFrame, a_core: int = FILES_A_CORE) -> DataFrame:
    """``df`` in a number of partitions that follows the cluster: small shuffle partitions are
    written one after another into one file, without another shuffle."""
    return df.coalesce(a_core * df.sparkSession.sparkContext.defaultParallelism)


def keep(df: DataFrame, name: str = "stage", a_core: int | None = FILES_A_CORE) -> DataFrame:
    """The rows written to the shared folder and read again: lineage ends here, and the loss of
    an executor costs nothing but the tasks that it was running."""
    path = shared_path(df.sparkSession, name)
    (df if a_core is None else packed(df, a_core)).write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.kept_path = path
    return out


def release(*frames: DataFrame) -> None:
    """Removes kept tables and held blocks that nothing reads any more (the frames that ``keep``
    and ``hold`` returned, not ones derived from them)."""
    for df in frames:
        if hasattr(df, "kept_path"):
            remove(df.sparkSession, df.kept_path)
        else:
            df.unpersist()


def hold(df: DataFrame) -> DataFrame:
    """The rows in the executors' block stores, on disk, for several readers. Lineage stays: the
    blocks of a lost executor are computed again. For wide tables that one function reads."""
    return df.persist(StorageLevel.DISK_ONLY)
