"""SQL forms of the codec functions, registered by name on a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .lz import code_length
from .typeindex import unpack_bits


def text_bits(text: str) -> int:
    """LZ78 bits of a text over the characters it holds."""
    codes = {c: i for i, c in enumerate(sorted(set(text)))}
    return code_length([codes[c] for c in text], max(1, len(codes)))


def lz78_bits(text: pd.Series) -> pd.Series:
    return text.map(text_bits, na_action="ignore").astype("Int64")


def block_entropy(symbol: pd.Series) -> float:
    """Order-0 entropy of a group's symbols, nulls as one symbol of their own."""
    p = symbol.value_counts(normalize=True, dropna=False)
    from math import log2

    return float(-sum(x * log2(x) for x in p)) + 0.0


class BitsOf:
    """The bits of a binary value, first bit first."""

    def eval(self, data: bytes):
        if data is not None:
            yield from ((i, int(b)) for i, b in enumerate(unpack_bits(bytes(data), 8 * len(data))))


class SpanBlocks:
    """The blocks that a span of a sequence of n symbols touches, with the part of each."""

    def eval(self, start: int, length: int, n: int, b0: int):
        end, last = min(start + length, n), max(n // b0, 1) - 1
        at = start
        while at < end:
            blk = min(at // b0, last)
            stop = end if blk == last else min(end, (blk + 1) * b0)
            yield blk, at - blk * b0, stop - at
            at = stop


def register(spark: SparkSession) -> None:
    """``lz78_bits(text)``, ``block_entropy(symbol)``, ``bits_of(binary)`` and ``span_blocks(start, len, n, b0)`` for SQL."""
    spark.udf.register("lz78_bits", F.pandas_udf(lz78_bits, "long"))
    spark.udf.register("block_entropy", F.pandas_udf(block_entropy, "double"))
    spark.udtf.register("bits_of", F.udtf(BitsOf, returnType="pos long, bit int"))
    spark.udtf.register("span_blocks", F.udtf(SpanBlocks, returnType="blk long, first long, size long"))
