"""Zero-error storage: LZ words of a fixed width where they fit, raw symbols behind a flag where not."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.lz import fixed_word, read_fixed_word
from ..functions.typeindex import FIRST_CHAR, char_of
from .blocks import cut_text


def lz_word(k: int):
    """Body and width -> fixed LZ word as a bit string, null where it doesn't fit; Arrow-batched."""

    @F.pandas_udf("string")
    def word(body: pd.Series, width: pd.Series) -> pd.Series:
        return pd.Series([fixed_word([ord(c) - FIRST_CHAR for c in t], k, w) for t, w in zip(body, width, strict=True)], dtype=object)

    return word


def lz_body(k: int):
    """Fixed LZ word and symbol count -> body; Arrow-batched."""

    @F.pandas_udf("string")
    def body(word: pd.Series, n_sym: pd.Series) -> pd.Series:
        return pd.Series([None if w is None else "".join(map(char_of, read_fixed_word(w, k, n))) for w, n in zip(word, n_sym, strict=True)], dtype=object)

    return body


def escaped_texts(df: DataFrame, id_col: str, text: Column, k: int, b0: int, num: int, den: int) -> DataFrame:
    """``(seq_id, blk, n_sym, flag, word)``: flag 0 and LZ words of num/den of the raw width if all of a text's blocks fit, else flag 1 and raw bodies."""
    raw_bits = max(1, (k - 1).bit_length())
    blocks = cut_text(df, id_col, text, b0)
    tried = blocks.withColumn("short", lz_word(k)(F.col("body"), F.floor(F.col("n_sym") * raw_bits * num / den).cast("int")))
    fits = tried.groupBy("seq_id").agg(F.bool_and(F.col("short").isNotNull()).alias("fits"))
    return tried.join(fits, "seq_id").select("seq_id", "blk", "n_sym", F.when(F.col("fits"), 0).otherwise(1).alias("flag"), F.when(F.col("fits"), F.col("short")).otherwise(F.col("body")).alias("word"))


def unescaped_texts(stored: DataFrame, k: int) -> DataFrame:
    """``(seq_id, flag, text)`` of what ``escaped_texts`` stored; a text is put together in its one row, as it came."""
    short = F.when(F.col("flag") == 0, F.col("word"))
    body = F.coalesce(lz_body(k)(short, F.col("n_sym")), F.col("word"))
    listed = F.array_sort(F.collect_list(F.struct("blk", body.alias("b"))))
    return stored.groupBy("seq_id", "flag").agg(F.array_join(F.transform(listed, lambda x: x["b"]), "").alias("text"))


def prefix_free(words: DataFrame) -> DataFrame:
    """One row ``(words, clashes, prefix_free)``: whether no distinct ``word`` begins another.

    Only lengths that occur are tried, and a word meets its prefixes by equality, so no pair is compared.
    """
    known = words.select("word").where("word IS NOT NULL").distinct()
    lengths = known.select(F.length("word").alias("n")).distinct()
    heads = known.join(lengths, F.col("n") < F.length("word")).select(F.expr("substring(word, 1, n)").alias("word")).distinct()
    clashes = heads.join(known, "word", "left_semi").agg(F.count("*").alias("clashes"))
    return known.agg(F.count("*").alias("words")).join(clashes).select("words", "clashes", (F.col("clashes") == 0).alias("prefix_free"))
