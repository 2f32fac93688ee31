"""Cutting sequences into blocks and blocks into groups; settled tests on whole blocks."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.schedules import Law


def block_number(pos: Column, n: int, b0: int) -> Column:
    """Block of a position; the last block takes the remainder."""
    return F.least(F.floor(pos / b0).cast("long"), F.lit(max(n // b0, 1) - 1).cast("long"))


def group_number(child: Column, children: int, fanout: int) -> Column:
    """Group of a child unit; the last group takes the remainder."""
    return F.least(F.floor(child / fanout).cast("long"), F.lit(max(children // fanout, 1) - 1).cast("long"))


def cut_blocks(placed: DataFrame, n: int, b0: int, chunk_blocks: int = 1) -> DataFrame:
    """``(chunk, blk, n_sym, body)`` from ``(pos, ch)``: one exchange, on the chunk, serves every grouping inside it.

    ``chunk_blocks`` is the number of blocks of the largest group that one task handles.
    """
    blk = block_number(F.col("pos"), n, b0)
    chunk = group_number(blk, max(n // b0, 1), chunk_blocks)
    dealt = placed.select(chunk.alias("chunk"), blk.alias("blk"), "pos", "ch").repartition("chunk")
    listed = F.array_sort(F.collect_list(F.struct("pos", "ch")))
    return dealt.groupBy("chunk", "blk").agg(F.count("*").cast("int").alias("n_sym"), F.array_join(F.transform(listed, lambda x: x["ch"]), "").alias("body"))


def cut_text(df: DataFrame, id_col: str, text: Column, b0: int) -> DataFrame:
    """``(seq_id, blk, n_sym, body)`` of texts, one sequence per row, by substrings (never one row per character)."""
    rows = df.select(F.col(id_col).alias("seq_id"), text.alias("t")).where("length(t) > 0")
    count = F.greatest(F.floor(F.length("t") / b0), F.lit(1)).cast("int")
    cut = rows.withColumn("n_blk", count).select("seq_id", "t", "n_blk", F.explode(F.sequence(F.lit(0), F.col("n_blk") - 1)).alias("blk"))
    size = F.when(F.col("blk") == F.col("n_blk") - 1, F.length("t") - F.col("blk") * b0).otherwise(b0)
    body = F.substring(F.col("t"), F.col("blk") * b0 + 1, size)
    return cut.select("seq_id", F.col("blk").cast("long").alias("blk"), size.cast("int").alias("n_sym"), body.alias("body"))


def symbol_count(body: Column, ch: str) -> Column:
    return F.length(body) - F.length(F.replace(body, F.lit(ch), F.lit("")))


def settled(body: Column, law: Law, num: int, den: int) -> Column:
    """Whether every symbol's count is within num/den of its expectation, in integers; no unknown symbol."""
    n = law.total
    tests = []
    seen = F.lit(0)
    for i, c in enumerate(law.counts):
        count = symbol_count(body, law.chars[i]).cast("long")
        seen = seen + count
        tests.append(F.abs(count * n - F.length(body).cast("long") * c) * den <= F.length(body).cast("long") * c * num)
    return reduce(lambda a, b: a & b, tests, seen == F.length(body))
