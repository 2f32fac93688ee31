"""Range joins by buckets: versions valid at a time, and cells of varying size under a span."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def versions(edits: DataFrame) -> DataFrame:
    """``(blk, edit_id, at, until)`` of edits ``(edit_id, blk, at)``: each holds until the block's next; the last has no end."""
    w = Window.partitionBy("blk").orderBy("at", "edit_id")
    return edits.select("blk", "edit_id", "at", F.lead("at").over(w).alias("until"))


def valid_at(points: DataFrame, intervals: DataFrame, width: int) -> DataFrame:
    """Points ``(read_id, blk, t)`` joined with the version ``(blk, edit_id, at, until)`` that holds at ``t``.

    Times are integers.  Intervals are dealt to the buckets of ``width`` they meet, so the join is an equi-join on
    block and bucket with a range test beside it; open ends reach to the latest point.
    """
    end = points.agg(F.max("t")).first()[0]
    if end is None:
        return points.join(intervals.select("blk", "edit_id"), "blk").select("read_id", "blk", "edit_id")
    bucket = lambda c: F.floor(c / width)
    last = F.least(F.coalesce(F.col("until") - 1, F.lit(end)), F.lit(end))
    dealt = intervals.where(F.col("at") <= last).select("blk", "edit_id", "at", "until", F.explode(F.sequence(bucket(F.col("at")), bucket(last))).alias("bucket"))
    met = points.withColumn("bucket", bucket(F.col("t"))).join(dealt, ["blk", "bucket"])
    return met.where((F.col("t") >= F.col("at")) & (F.col("until").isNull() | (F.col("t") < F.col("until")))).select("read_id", "blk", "edit_id")


def overlapping(spans: DataFrame, cells: DataFrame, width: int) -> DataFrame:
    """``(req_id, cell, overlap)``: symbols that span ``(req_id, start, len)`` shares with cell ``(cell, first, size)``.

    Both sides are dealt to buckets; a pair counts in the first bucket that both meet, so none counts twice.
    """

    def dealt(df: DataFrame, low: Column, size: Column) -> DataFrame:
        return df.where(size > 0).withColumn("bucket", F.explode(F.sequence(F.floor(low / width), F.floor((low + size - 1) / width))))

    s, c = dealt(spans, F.col("start"), F.col("len")), dealt(cells, F.col("first"), F.col("size"))
    low, high = F.greatest("start", "first"), F.least(F.col("start") + F.col("len"), F.col("first") + F.col("size"))
    return s.join(c, "bucket").where((low < high) & (F.col("bucket") == F.floor(low / width))).select("req_id", "cell", (high - low).alias("overlap"))


def multiset_diff(before: DataFrame, after: DataFrame) -> DataFrame:
    """``(side, rows)``: rows that went, came and stayed, repeats counted."""
    out = None
    for side, rows in (("gone", before.exceptAll(after)), ("come", after.exceptAll(before)), ("kept", before.intersectAll(after))):
        one = rows.agg(F.count("*").alias("rows")).select(F.lit(side).alias("side"), "rows")
        out = one if out is None else out.unionByName(one)
    return out
