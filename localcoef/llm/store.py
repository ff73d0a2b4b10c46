"""Intermediate tables of the text operators, besides those written to the shared folder."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

from localcoef.plans.store import written  # noqa: F401  the text operators write their tables with it too


def small_batches(spark: SparkSession) -> None:
    """Arrow batches of 8 MB, so that whole texts of any length take little memory twice; a setting of the user's stays."""
    name, usual = "spark.sql.execution.arrow.maxBytesPerBatch", ("67108864b", "64m", "67108864")
    if spark.conf.get(name, usual[0]).lower() in usual:
        spark.conf.set(name, "8m")


def kept(df: DataFrame) -> DataFrame:
    """The same rows, worked out once and kept on the executors' disks; what a lost executor held is worked out again."""
    return df.persist(StorageLevel.DISK_ONLY)


def discard(spark: SparkSession, df: DataFrame) -> None:
    """Removes the files of a written table that is no longer read."""
    jvm = spark.sparkContext._jvm
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        where = jvm.org.apache.hadoop.fs.Path(folder)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
