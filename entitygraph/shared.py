"""Lineage cuts in the folder that the driver and every executor share."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The cluster's ``spark.checkpoint.dir``; a temporary folder of this machine only where that is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    app = spark.sparkContext.applicationId
    return _LOCAL.setdefault(app, tempfile.mkdtemp(prefix="entitygraph-"))


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str, compression: str = "snappy") -> DataFrame:
    """Writes the rows as Parquet to the shared folder and reads them back: later steps neither recompute them nor lose
    them with an executor."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", compression).parquet(path)
    kept = spark.read.schema(df.schema).parquet(path)
    kept._materialised = path
    return kept


def discard(df: DataFrame) -> None:
    """Deletes what ``materialise`` wrote, once all that reads it is written itself."""
    path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._materialised)
    path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffle files of finished steps now instead of at its next half-hourly collection."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
