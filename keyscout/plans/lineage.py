"""Lineage cuts that survive lost executors."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: kinds that parquet cannot hold
_CHECKPOINTED = (T.NullType, T.CalendarIntervalType, T.VariantType)


def shared_folder(spark: SparkSession) -> str:
    """The folder ``spark.checkpoint.dir`` names; a temporary one only for a local master that names none."""
    place = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if place:
        return place.rstrip("/")
    if not (spark.sparkContext.master + "[").startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    place = tempfile.mkdtemp(prefix="keyscout")
    spark.sparkContext.setCheckpointDir(place)
    return place


def snapshot(df: DataFrame) -> DataFrame:
    """``df`` written in columns to the shared folder and read again: later scans read only what they need.

    Snapshots of one application share a folder ``keyscout-<application id>`` there; ``release`` removes one.
    """
    spark = df.sparkSession
    place = shared_folder(spark)
    if any(isinstance(f.dataType, _CHECKPOINTED) for f in df.schema.fields):
        if spark.sparkContext.getCheckpointDir() is None:
            spark.sparkContext.setCheckpointDir(place)
        return df.checkpoint(eager=True)
    path = f"{place}/keyscout-{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(df: DataFrame) -> None:
    """Removes the files of a snapshot that nothing reads any more."""
    spark = df.sparkSession
    own = f"/keyscout-{spark.sparkContext.applicationId}/"
    files = [f for f in df.inputFiles() if own in f]
    if files:
        jvm = spark.sparkContext._jvm
        folder = jvm.org.apache.hadoop.fs.Path(files[0].rsplit("/", 1)[0])
        folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def tidy(spark: SparkSession) -> None:
    """Lets Spark remove the shuffle files of finished jobs: its cleaner only sees what the JVM has collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
