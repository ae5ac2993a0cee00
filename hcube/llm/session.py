"""Where operators put the tables that cut lineage, and how they free what they used."""

from __future__ import annotations

import contextlib
import gc
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; one of our own only where none is set (tests)."""
    found = spark.sparkContext.getCheckpointDir()
    if not found:
        found = spark.conf.get("spark.checkpoint.dir", None)
        if not found:
            found = tempfile.mkdtemp(prefix="hcube-checkpoint-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def written(df: DataFrame, name: str, release: bool = True) -> DataFrame:
    """``df`` written as parquet to the shared folder and read back: a plan without lineage.

    ``release`` lets Spark's cleaner drop the shuffle files of finished jobs, which
    it does only once the driver's garbage has been collected.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with small_batches(spark):
        df.write.option("compression", "zstd").parquet(path)
    schema = df.schema
    del df
    if release:
        free(spark)
    out = spark.read.schema(schema).parquet(path)
    out.written_to = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes tables that ``written`` returned and that no later plan reads."""
    for table in tables:
        jvm = table.sparkSession.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(table.written_to)
        path.getFileSystem(table.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


@contextlib.contextmanager
def small_batches(spark: SparkSession, size: str = "8m"):
    """While it holds, rows go to Python by batches of a few megabytes, so that long texts don't add up."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key, None)
    spark.conf.set(key, size)
    try:
        yield
    finally:
        spark.conf.set(key, before) if before else spark.conf.unset(key)


def free(spark: SparkSession, times: int = 1) -> None:
    """Collects garbage here and in the driver's JVM, so that shuffle files of finished jobs go.

    What is let go here reaches the JVM a moment later: more than one time before a large step.
    """
    for k in range(times):
        gc.collect()
        if k:
            time.sleep(0.2)
        spark.sparkContext._jvm.System.gc()


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
