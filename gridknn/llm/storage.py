"""Where intermediate tables go: the folder that all executors share.

The same few lines as in gridknn.sources.shared: this subpackage is an optional part that
nothing else imports, so that the rest stays whole without it.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Bytes of an Arrow batch, so that a Python worker and the JVM hold few rows of text at a time.
BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"
BATCH_BYTES = 4 << 20
#: Removes the shuffle files of a query when it has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; only where it is unset (tests) a temporary folder of this machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        found = "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")
    return found.rstrip("/")


def small_batches(spark: SparkSession) -> None:
    """Arrow batches of at most BATCH_BYTES from now on, unless the session sets a size itself."""
    unset = "64m"
    if spark.conf.get(BATCH, unset) == unset:
        spark.conf.set(BATCH, str(BATCH_BYTES))


@contextmanager
def shuffles_removed(spark: SparkSession):
    """Queries made in this block leave no shuffle files when they have ended: for those that run once."""
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, before)


def saved(df: DataFrame, name: str, partition_by: str | None = None, options: dict | None = None) -> DataFrame:
    """df written once as Parquet in the shared folder and read again: cuts lineage, survives lost executors.

    The write is a query of its own that is never run again, so its shuffle files go with it.
    """
    spark = df.sparkSession
    small_batches(spark)
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with shuffles_removed(spark):
        (df.write.partitionBy(partition_by) if partition_by else df.write).options(**options or {}).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._saved_at = path
    return out


def bucketed(df: DataFrame, name: str, buckets: int, by: list[str]) -> DataFrame:
    """df as a table of the session's catalog, bucketed and sorted, with its files in the shared folder."""
    spark = df.sparkSession
    small_batches(spark)
    path = f"{shared_dir(spark)}/{name}"
    with shuffles_removed(spark):
        df.write.bucketBy(buckets, *by).sortBy(*by).option("path", path).saveAsTable(name)
    out = spark.table(name)
    out._saved_at = path
    return out


def discard(*tables: DataFrame | None) -> None:
    """Removes saved tables that no later plan reads; others are left alone."""
    for df in tables:
        if path := getattr(df, "_saved_at", None):
            jvm = df.sparkSession._jvm
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
