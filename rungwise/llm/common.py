"""Helpers shared by the corpus operators: shared-folder cuts and Arrow batch sizes."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of one Arrow batch.  Whole texts travel in these batches, so the default of 10,000 is too many.
ARROW_ROWS = 1000

_written: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_batches(spark: SparkSession) -> None:
    """Bound what one Arrow batch of whole texts can hold (a runtime setting of the session)."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))


def shared_folder(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names.

    A session without one gets a temporary folder only if it runs in a single process (``local`` masters);
    on a cluster, where executors could not see it, an error tells to set the folder.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="rungwise-")
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder and read it again: lineage ends, every executor can reread it."""
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/rungwise-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def drop_cut(df: DataFrame | None) -> None:
    """Delete what ``cut`` wrote, once no later result reads it."""
    path = getattr(df, "_cut_path", None)
    if path:
        _delete(df.sparkSession, path)
        _written[:] = [x for x in _written if x[1] != path]


#: A key with more than this share of all rows is hot; so there are at most 1 / HOT_SHARE hot keys.
HOT_SHARE = 1 / 500


def keyed_join(rows: DataFrame, table: DataFrame, key: str, total: int) -> DataFrame:
    """Inner join of ``rows`` with ``table(key, __n, ...)``, which has one row a key; ``__n`` counts the rows of the key.

    Keys with over ``HOT_SHARE`` of the ``total`` rows, a bounded number, are broadcast, so that no task gets all
    rows of a hot key; the others are joined by their key.
    """
    most = max(1, int(total * HOT_SHARE))
    hot, rest = table.where(F.col("__n") > most).drop("__n"), table.where(F.col("__n") <= most).drop("__n")
    cool = rows.join(F.broadcast(hot.select(key)), key, "left_anti")
    return rows.join(F.broadcast(hot), key).unionByName(cool.join(rest.hint("merge"), key))


@contextlib.contextmanager
def scratch():
    """Deletes at its end what ``cut`` wrote inside, but for the frames handed to the function it gives."""
    before, kept = {x[1] for x in _written}, set()

    def keep(df: DataFrame) -> DataFrame:
        kept.add(getattr(df, "_cut_path", None))
        return df

    yield keep
    for spark, path in [x for x in _written if x[1] not in before and x[1] not in kept]:
        _delete(spark, path)
        _written[:] = [x for x in _written if x[1] != path]


def _delete(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):
        jvm = spark._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        _delete(spark, path)
