"""Folders that driver and executors share, and the few file operations that the engine needs on them."""

from __future__ import annotations

import uuid

from pyspark.sql import SparkSession

from deltamp.durable import shared_folder


def scratch(spark: SparkSession) -> str:
    """A new folder under the session's checkpoint folder."""
    return f"{shared_folder(spark)}/scratch-{uuid.uuid4().hex}"


def _path(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def names(spark: SparkSession, path: str) -> list[str]:
    """The names in a folder; none where there is no folder."""
    p, fs = _path(spark, path)
    return sorted(x.getPath().getName() for x in fs.listStatus(p)) if fs.exists(p) else []


def touch(spark: SparkSession, path: str) -> None:
    p, fs = _path(spark, path)
    fs.create(p, True).close()


def remove(spark: SparkSession, path: str) -> None:
    p, fs = _path(spark, path)
    fs.delete(p, True)
