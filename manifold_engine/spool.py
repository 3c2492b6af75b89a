"""Shared-folder tables that cut lineage, and sizes read from plans."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder every executor can reach: ``spark.checkpoint.dir``.

    Only where that setting is absent in a single-process session, as in tests,
    does the engine pick a folder of its own; on a cluster it refuses, because
    each executor would write to a disk of its own.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    master = spark.sparkContext.master
    if master == "local" or master.startswith("local["):
        return "file:///tmp/checkpoints"
    raise RuntimeError(f"set spark.checkpoint.dir to a folder that all executors of {master} share")


def _own(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/spool-{spark.sparkContext.applicationId}"


def sweep(spark: SparkSession) -> bool:
    """Delete this application's tables; only once no frame that reads one is still needed."""
    path = spark._jvm.org.apache.hadoop.fs.Path(_own(spark))
    return bool(path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True))


def spool(df: DataFrame, tag: str = "t") -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and read it back.

    Unlike a cached frame the table survives lost executors, and unlike
    ``checkpoint()`` it is columnar, compressed and readable with pruning.
    """
    spark = df.sparkSession
    path = f"{_own(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def plan_bytes(df: DataFrame) -> int:
    """Catalyst's size estimate of ``df`` (file sizes for scans), 0 if unknown; no job runs."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size if size < 1 << 60 else 0


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_bytes(df: DataFrame, column: str) -> int:
    """Bytes of a text column as they are in memory; one scan of that column."""
    return df.agg(F.sum(F.octet_length(column))).first()[0] or 0
