"""Streams of symbols and of edits: blocks as they fill up, net edits by batch, late edits, windows and drift.

Every function takes and returns DataFrames; those without state or sinks work on batches as well.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.schedules import Law
from ..sources.shared import fresh_folder

MISSING = "\x00"
LATENESS = "1 hour"
EPOCH = "TIMESTAMP_NTZ'1970-01-01 00:00:00'"


def table_stream(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 100) -> DataFrame:
    """A table's files as a stream; the schema is that of the files at hand.

    Event time must be an instant: a ``ts`` without a time zone is taken as UTC, whatever the session's zone.
    """
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    # a table may be one file; the file source takes that through a pattern only
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/{name}.parque[t]")
    if dict(stream.dtypes).get("ts") == "timestamp_ntz":
        stream = stream.withColumn("ts", F.timestamp_micros(F.expr(f"timestampdiff(MICROSECOND, {EPOCH}, ts)")))
    return stream


def wall_clock(instant: str) -> Column:
    """An instant as a UTC timestamp without time zone."""
    return F.expr(f"timestampadd(MICROSECOND, unix_micros({instant}), {EPOCH})").alias(instant)


def land(stream: DataFrame, purpose: str) -> DataFrame:
    """Runs an append stream over all that is there, into the shared folder, and reads the rows back."""
    spark, folder = stream.sparkSession, fresh_folder(stream.sparkSession, purpose)
    query = stream.writeStream.format("parquet").option("path", f"{folder}/rows").option("checkpointLocation", f"{folder}/log").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/rows")


def appended_blocks(symbols: DataFrame, b0: int) -> DataFrame:
    """``(blk, n_sym, body)`` of ``(pos, ch)`` rows, each block once all its ``b0`` symbols have come.

    State is held by block, so it is bounded by ``b0`` characters a key and spreads over all tasks; a complete
    block's state goes.  A position that comes twice before its block is complete overwrites itself.  The last,
    partial block stays in the state until its symbols come.  Null positions and symbols are ignored.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        cells = list(state.get[0]) if state.exists else [MISSING] * b0
        for frame in frames:
            for at, ch in zip(frame["at"], frame["ch"], strict=True):
                cells[at] = ch
        if MISSING in cells:
            state.update(("".join(cells),))
            return
        if state.exists:
            state.remove()
        yield pd.DataFrame({"blk": [key[0]], "n_sym": [b0], "body": ["".join(cells)]})

    placed = symbols.where("pos IS NOT NULL AND ch IS NOT NULL").select(F.floor(F.col("pos") / b0).alias("blk"), (F.col("pos") % b0).cast("int").alias("at"), "ch")
    return placed.groupBy("blk").applyInPandasWithState(step, "blk long, n_sym int, body string", "cells string", "append", GroupStateTimeout.NoTimeout)


def land_net_edits(edits: DataFrame) -> DataFrame:
    """``(blk, edit_id, src)``: the last edit of each block of a stream ``(edit_id, blk, src)``.

    Each micro-batch writes its net edits to a folder named by its number, in place of what an earlier attempt of
    the same batch left; so a repeated batch changes nothing.  Edits may come in any order.
    """
    spark, folder = edits.sparkSession, fresh_folder(edits.sparkSession, "net-edits")

    def put(batch: DataFrame, number: int) -> None:
        batch.groupBy("blk").agg(F.max("edit_id").alias("edit_id"), F.max_by("src", "edit_id").alias("src")).write.mode("overwrite").parquet(f"{folder}/net/batch={number}")

    edits.select("edit_id", "blk", "src").writeStream.foreachBatch(put).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).start().awaitTermination()
    net = spark.read.schema("blk long, edit_id long, src long").option("recursiveFileLookup", "true").parquet(f"{folder}/net")
    return net.groupBy("blk").agg(F.max("edit_id").alias("edit_id"), F.max_by("src", "edit_id").alias("src"))


def once(edits: DataFrame, lateness: str = LATENESS) -> DataFrame:
    """Each ``edit_id`` once, and no edit later than the watermark; the query's progress counts the late ones."""
    return edits.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["edit_id"])


def dropped_late(query) -> int:
    """Rows that a query has dropped behind its watermark, over all its recent batches."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def windowed(edits: DataFrame, *measures: Column, width: str = "1 day", slide: str | None = None, lateness: str = LATENESS) -> DataFrame:
    """``(start, measures)`` by window of ``ts``; on a stream a window appears once the watermark has passed its end."""
    return edits.withWatermark("ts", lateness).groupBy(F.window("ts", width, slide).alias("w")).agg(*measures).select(F.col("w.start").alias("start"), "*").drop("w")


def drift(symbols: DataFrame, law: Law, num: int, den: int, width: str = "1 day") -> DataFrame:
    """``(start, n, drifted)`` by window: whether some symbol's count is off its share in ``law`` by over num/den, or unknown."""
    counts = [F.sum((F.col("symbol") == s).cast("long")).alias(f"c{i}") for i, s in enumerate(law.symbols)]
    seen = windowed(symbols, F.count("*").alias("n"), *counts, width=width)
    off, known = F.lit(False), F.lit(0)
    for i, c in enumerate(law.counts):
        off = off | (F.abs(F.col(f"c{i}") * law.total - F.col("n") * c) * den > F.col("n") * c * num)
        known = known + F.coalesce(F.col(f"c{i}"), F.lit(0))
    return seen.select("start", "n", (off | (known < F.col("n"))).alias("drifted"))


def reads_after_edits(edits: DataFrame, reads: DataFrame, within: str = "1 hour") -> DataFrame:
    """Pairs ``(edit_id, read_id)`` on the same block, the read at or after the edit and within the interval."""
    e = edits.select("edit_id", F.col("blk").alias("e_blk"), F.col("ts").alias("e_ts")).withWatermark("e_ts", LATENESS)
    r = reads.select("read_id", F.col("blk").alias("r_blk"), F.col("ts").alias("r_ts")).withWatermark("r_ts", LATENESS)
    return e.join(r, F.expr(f"e_blk = r_blk AND r_ts >= e_ts AND r_ts <= e_ts + INTERVAL {within}")).select("edit_id", "read_id")
