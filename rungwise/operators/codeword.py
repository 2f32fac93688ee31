"""The ladder's codeword bit by bit: what the sparse store stands for, cell after cell, level after level."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.typeindex import FIRST_CHAR, TypicalSet, unpack_bits, word_width
from .ladder import LadderStore


def _word_bits(store: LadderStore):
    """Packed word and symbol count -> the word's bits; zeros where the block is open."""
    law, s = store.law, store.schedule
    counts, num, den, k0 = list(law.counts), s.num, s.den, s.k0
    widths: dict[int, int] = {}

    @F.pandas_udf("string")
    def bits(word: pd.Series, n_sym: pd.Series) -> pd.Series:
        out = []
        for w, n in zip(word, n_sym, strict=True):
            if n not in widths:
                widths[n] = word_width(k0, TypicalSet(counts, num, den, n))
            out.append("0" * widths[n] if w is None else unpack_bits(w, widths[n]))
        return pd.Series(out, dtype=object)

    return bits


def cells(store: LadderStore) -> DataFrame:
    """``(level, cell, bits)``: level 0 holds index words, the others a header and the open children's symbols.

    Inside an open child, a block that settled below is written in markers (the number after the last symbol's).
    An open group's cell is zeros; every cell is filled up to its level's width.
    """
    s = store.schedule
    out = store.blocks0.select(F.lit(0).alias("level"), F.col("blk").alias("cell"), _word_bits(store)(F.col("word"), F.col("n_sym")).alias("bits"))
    symbol = lambda x: F.lpad(F.bin(F.ascii(x) - FIRST_CHAR), s.digit_bits, "0")
    marker = format(store.law.k, f"0{s.digit_bits}b")
    digits = F.when(F.col("settled"), F.repeat(F.lit(marker), F.col("n_sym"))).otherwise(F.array_join(F.transform(F.split("body", ""), symbol), ""))
    for i, (groups, level) in enumerate(zip(store.groups, s.levels, strict=True), 1):
        child_open = ~F.col("settled") if i == 1 else ~F.col(f"settled{i - 1}")
        carried = store.state.where(child_open & F.col(f"settled{i}")).select(F.col(f"g{i}").alias("grp"), "blk", digits.alias("d"))
        payload = carried.groupBy("grp").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("blk", "d"))), lambda x: x["d"]), "").alias("payload"))
        first = F.col("grp") * level.fanout
        header = F.array_join(F.transform(F.sequence(F.lit(0), F.col("n_child").cast("int") - 1), lambda j: F.when(F.array_contains("header", first + j), "1").otherwise("0")), "")
        body = F.when(F.col("settled"), F.concat(header, F.coalesce("payload", F.lit("")))).otherwise(F.lit(""))
        filled = F.concat(body, F.repeat(F.lit("0"), F.greatest(F.lit(level.width) - F.length(body), F.lit(0))))
        out = out.unionByName(groups.join(payload, "grp", "left").select(F.lit(i).alias("level"), F.col("grp").alias("cell"), filled.alias("bits")))
    return out


def codeword(store: LadderStore) -> DataFrame:
    """``(level, cell, at, bits)``: every cell with the place of its first bit in the whole codeword.

    Inside a level places are arithmetic, for only its last cell can be wider; the levels' lengths are a handful of rows.
    """
    s = store.schedule
    made = cells(store)
    lengths = made.groupBy("level").agg(F.sum(F.length("bits")).alias("n"))
    above = lengths.select(F.col("level").alias("lower"), "n")
    base = lengths.select("level").join(F.broadcast(above), F.col("lower") < F.col("level"), "left").groupBy("level").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("base"))
    width = F.element_at(F.array(*[F.lit(w).cast("long") for w in s.widths]), F.col("level") + 1)
    return made.join(F.broadcast(base), "level").select("level", "cell", (F.col("base") + F.col("cell") * width).alias("at"), "bits")


def flipped(before: LadderStore, after: LadderStore) -> DataFrame:
    """``(level, cells, rewritten_bits, flipped_bits)`` of the cells that differ: their whole width, and the bits that differ.

    Levels without a changed cell have no row.  Only differing cells are compared bit by bit.
    """
    old, new = cells(before).withColumnRenamed("bits", "old"), cells(after).withColumnRenamed("bits", "new")
    changed = old.join(new, ["level", "cell"]).where("old <> new")
    n = F.greatest(F.length("old"), F.length("new"))
    bits = lambda c: F.split(F.concat(F.col(c), F.repeat(F.lit("0"), n - F.length(c))), "")
    differ = F.size(F.filter(F.zip_with(bits("old"), bits("new"), lambda a, b: a != b), lambda x: x)).cast("long")
    return changed.groupBy("level").agg(F.count("*").alias("cells"), F.sum(n.cast("long")).alias("rewritten_bits"), F.sum(differ).alias("flipped_bits"))
