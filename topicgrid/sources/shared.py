"""The folder that the driver and all executors share, and frames that are written there once and read often."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new path below spark.checkpoint.dir; where that is unset a temporary folder, in local mode only. It goes when Python ends."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="topicgrid-")
    path = f"{root.rstrip('/')}/topicgrid-{name}-{uuid.uuid4().hex}"
    atexit.register(remove, spark, path)
    return path


def located(spark: SparkSession, path: str):
    """The file system and the path as the JVM knows them."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def remove(spark: SparkSession, path: str) -> None:
    if spark.sparkContext._jvm is None or spark.sparkContext._jsc is None:
        return
    fs, where = located(spark, path)
    fs.delete(where, True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as Parquet and read again, so that what reads it often doesn't make it often."""
    path = shared_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
