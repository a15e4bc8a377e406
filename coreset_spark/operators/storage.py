"""Checkpoints that survive lost executors, and folders that all of them share."""

from __future__ import annotations

import atexit
import shutil
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder for checkpoints: the one that the context has, else the one that the session names.

    Where neither does, as in tests, a new one in the warehouse, which all executors reach; if that is a local path, it goes
    when the program ends. Of the others Spark removes what is no longer read if spark.cleaner.referenceTracking.cleanCheckpoints says so.
    """
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        at = named or f"{spark.conf.get('spark.sql.warehouse.dir')}/_checkpoints-{uuid.uuid4().hex}"
        if not named and at.startswith("file:"):
            atexit.register(shutil.rmtree, at.removeprefix("file:").replace("//", "/"), ignore_errors=True)
        context.setCheckpointDir(at)
    return context.getCheckpointDir()


def new_folder(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that nothing has used yet."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder of one's own, in whatever file system it lies."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder: later reads survive lost executors, and never recompute."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)
