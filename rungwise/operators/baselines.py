"""The codecs that the ladder and the ranked codec are compared with."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.lz import code_length
from ..functions.typeindex import FIRST_CHAR, digit_width
from ..plans.schedules import LadderSchedule, Law
from .blocks import settled


def lz_length(k: int):
    """LZ78 bits of a body, Arrow-batched."""

    @F.pandas_udf("long")
    def bits(body: pd.Series) -> pd.Series:
        return pd.Series([code_length([ord(c) - FIRST_CHAR for c in text], k) for text in body], dtype="int64")

    return bits


def text_lz_length():
    """LZ78 bits of a text over the characters it holds, Arrow-batched."""

    @F.pandas_udf("long")
    def bits(text: pd.Series) -> pd.Series:
        out = []
        for t in text:
            codes = {c: i for i, c in enumerate(sorted(set(t)))}
            out.append(code_length([codes[c] for c in t], max(1, len(codes))))
        return pd.Series(out, dtype="int64")

    return bits


def gram_counts(k: int, length: int):
    """Counts of all ``k ** length`` grams of a body, by gram number; bounded, and one array per text."""

    @F.pandas_udf("array<long>")
    def counts(body: pd.Series) -> pd.Series:
        out = []
        for text in body:
            codes = np.frombuffer((text or "").encode("ascii"), np.uint8).astype(np.int64) - FIRST_CHAR
            n = max(0, len(codes) - length + 1)
            number = np.zeros(n, np.int64)
            for i in range(length):
                number = number * k + codes[i : i + n]
            out.append(np.bincount(number, minlength=k**length))
        return pd.Series(out, dtype=object)

    return counts


def flat(blocks: DataFrame, law: Law, s: LadderSchedule) -> DataFrame:
    """Independent fixed-length blocks: ``(blk, n_sym, failed, bits)``; an atypical block is an error."""
    return blocks.select("blk", "n_sym", (~settled(F.col("body"), law, s.num, s.den)).alias("failed"), F.lit(s.k0).cast("long").alias("bits"))


def whole_lz(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """One LZ code per sequence: a read or an edit of one symbol costs all of it."""
    bits = text_lz_length()(F.col(text_col))
    return df.where(f"length({text_col}) > 0").select(F.col(id_col).alias("seq_id"), F.length(text_col).cast("long").alias("n"), bits.alias("bits")).withColumn("read_bits", F.col("bits")).withColumn("edit_bits", 2 * F.col("bits"))


def addressed(blocks: DataFrame, law: Law, n: int, range_chunks: int = 1_000_000) -> DataFrame:
    """Variable-length words with an explicit table of addresses: ``(blk, len, address)``.

    Words are summed by chunk, chunks by ranges of ``range_chunks``, so no window sees more than one range; the
    ranges' own sums, one row for each million chunks, go through the driver.
    """
    from pyspark.sql import Window

    sized = blocks.select("chunk", "blk", lz_length(law.k)(F.col("body")).alias("len"))
    sums = sized.groupBy("chunk").agg(F.sum("len").alias("sum")).withColumn("range", F.floor(F.col("chunk") / range_chunks))
    starts, at = [], 0
    for r in sorted(sums.groupBy("range").agg(F.sum("sum").alias("sum")).collect()):
        starts.append((r["range"], at))
        at += r["sum"]
    ranges = F.broadcast(blocks.sparkSession.createDataFrame(starts, "range long, start long"))
    earlier = F.sum("sum").over(Window.partitionBy("range").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1))
    bases = sums.withColumn("earlier", F.coalesce(earlier, F.lit(0))).join(ranges, "range").select("chunk", (F.col("start") + F.col("earlier")).alias("base"))
    within = Window.partitionBy("chunk").orderBy("blk").rowsBetween(Window.unboundedPreceding, -1)
    return sized.withColumn("inner", F.coalesce(F.sum("len").over(within), F.lit(0))).join(bases, "chunk").select("blk", "len", (F.col("base") + F.col("inner")).alias("address"))


def syndrome_rows(b: int, rows: int, weight: int = 3) -> list[list[int]]:
    """For each column of the sparse parity matrix the checks it enters, from a linear congruence."""
    return [sorted({(7919 * (j + 1) + 104729 * (t + 1) * (j + 3) + 31 * t) % rows for t in range(weight)}) for j in range(b)]


def syndromes(blocks: DataFrame, b: int, rows: int) -> DataFrame:
    """``(blk, syndrome)`` of binary bodies: the parity of the ones in each check, as a long of up to 62 checks."""
    if rows > 62:
        raise ValueError("at most 62 checks fit a long")
    masks = [sum(1 << r for r in checks) for checks in syndrome_rows(b, rows)]
    table = F.array(*[F.lit(m).cast("long") for m in masks])
    bits = blocks.where(F.col("n_sym") == b).select("blk", F.posexplode(F.split("body", "")).alias("i", "ch")).where("ch = '1'")
    some = bits.groupBy("blk").agg(F.bit_xor(F.element_at(table, F.col("i") + 1)).alias("s"))
    return blocks.where(F.col("n_sym") == b).select("blk").join(some, "blk", "left").select("blk", F.coalesce("s", F.lit(0)).alias("syndrome"))


def decode_syndrome(syndrome: int, b: int, rows: int, most: int = 3) -> list[int] | None:
    """The lightest pattern with this syndrome and up to ``most`` ones; None if there is none."""
    from itertools import combinations

    masks = [sum(1 << r for r in checks) for checks in syndrome_rows(b, rows)]
    for w in range(most + 1):
        for at in combinations(range(b), w):
            x = 0
            for i in at:
                x ^= masks[i]
            if x == syndrome:
                return [int(i in at) for i in range(b)]
    return None


def spill(blocks: DataFrame, law: Law, keep: list[int], fanout: int) -> DataFrame:
    """``(level, units, kept_bits, spilled_bits)``: a fixed part of each word stays, the rest climbs."""
    level = blocks.select("blk", lz_length(law.k)(F.col("body")).alias("len")).withColumn("u", F.col("blk"))
    out = None
    for i, k in enumerate(keep):
        row = level.agg(F.count("*").alias("units"), F.sum(F.least(F.col("len"), F.lit(k))).alias("kept_bits"), F.sum(F.greatest(F.col("len") - k, F.lit(0))).alias("spilled_bits")).select(F.lit(i).alias("level"), "*")
        out = row if out is None else out.unionByName(row)
        level = level.groupBy(F.floor(F.col("u") / fanout).alias("u")).agg(F.sum(F.greatest(F.col("len") - k, F.lit(0))).alias("len"))
    return out


def raw_bits(law: Law) -> int:
    return digit_width(law.k)
