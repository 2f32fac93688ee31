"""Folders that the driver and every executor share."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str]] = []


def fresh_folder(spark: SparkSession, purpose: str) -> str:
    """A new folder's name below the session's ``spark.checkpoint.dir``.

    A session without one gets a temporary folder only if it runs in a single process (``local`` masters).
    """
    top = spark.conf.get("spark.checkpoint.dir", None)
    if not top:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        top = tempfile.mkdtemp(prefix="rungwise-")
        spark.conf.set("spark.checkpoint.dir", top)
    return f"{top.rstrip('/')}/{purpose}-{uuid.uuid4().hex}"


def written(df: DataFrame, purpose: str) -> DataFrame:
    """``df`` written to the shared folder and read again, so that what follows reads the same rows; gone when the driver ends."""
    spark = df.sparkSession
    path = fresh_folder(spark, purpose)
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        with contextlib.suppress(Exception):
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
