"""Denser words for settled groups: a header by its number among headers of equal weight, a payload by radix or LZ code.

The plain word spends a header bit per child and a whole number of bits per symbol.  The variants keep the same
content and stay decodable from the group's child count and the payload's length, which the schedule gives.
"""

from __future__ import annotations

from math import comb

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import lz
from ..functions.rankdir import class_bits, class_number
from ..functions.typeindex import FIRST_CHAR, char_of, digit_width, radix_pack, radix_unpack, to_bits
from .ladder import LadderStore

VARIANTS = ("plain", "radix", "lz")


def _weighed(header: str) -> str:
    """A header as its weight and its number among the headers of that weight."""
    n, ones = len(header), header.count("1")
    return to_bits(ones, n.bit_length()) + to_bits(class_number(header), (comb(n, ones) - 1).bit_length())


def pack_open_children(header: str, payload: list[int], base: int, variant: str) -> str:
    """The word of a group: ``header`` has a bit per child, ``payload`` the open children's digits below ``base``."""
    if variant == "plain":
        return header + "".join(to_bits(d, digit_width(base)) for d in payload)
    if variant == "radix":
        return _weighed(header) + to_bits(radix_pack(payload, base), (base ** len(payload) - 1).bit_length())
    if variant == "lz":
        return _weighed(header) + lz.encode(payload, base)
    raise ValueError(f"no such variant: {variant}")


def unpack_open_children(bits: str, n_child: int, n_payload: int, base: int, variant: str) -> tuple[str, list[int]]:
    if variant == "plain":
        wide = digit_width(base)
        return bits[:n_child], [int(bits[at : at + wide], 2) for at in range(n_child, n_child + n_payload * wide, wide)]
    first = n_child.bit_length()
    ones = int(bits[:first], 2)
    at = first + (comb(n_child, ones) - 1).bit_length()
    header = class_bits(int(bits[first:at] or "0", 2), ones, n_child)
    rest = bits[at:]
    return header, radix_unpack(int(rest or "0", 2), base, n_payload) if variant == "radix" else lz.decode(rest, base, n_payload)


def open_children(store: LadderStore) -> DataFrame:
    """``(level, grp, header, payload)`` of the settled groups; settled blocks inside open children are markers."""
    s, marker, out = store.schedule, char_of(store.law.k), None
    symbols = F.when(F.col("settled"), F.repeat(F.lit(marker), F.col("n_sym"))).otherwise(F.col("body"))
    for i, (groups, level) in enumerate(zip(store.groups, s.levels, strict=True), 1):
        below = "settled" if i == 1 else f"settled{i - 1}"
        carried = store.state.where(~F.col(below) & F.col(f"settled{i}")).select(F.col(f"g{i}").alias("grp"), "blk", symbols.alias("p"))
        payload = carried.groupBy("grp").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("blk", "p"))), lambda x: x["p"]), "").alias("payload"))
        first = F.col("grp") * level.fanout
        header = F.array_join(F.transform(F.sequence(F.lit(0), F.col("n_child").cast("int") - 1), lambda j: F.when(F.array_contains("header", first + j), "1").otherwise("0")), "")
        one = groups.where("settled").select("grp", header.alias("header")).join(payload, "grp", "left").select(F.lit(i).alias("level"), "grp", "header", F.coalesce("payload", F.lit("")).alias("payload"))
        out = one if out is None else out.unionByName(one)
    return out


def dense_words(store: LadderStore, variants: tuple[str, ...] = VARIANTS) -> DataFrame:
    """``(level, grp, variant, bits, same)``: the length of every settled group's word, and whether it decodes."""
    base = store.law.k + 1

    @F.pandas_udf("bits long, same boolean")
    def coded(header: pd.Series, payload: pd.Series, variant: pd.Series) -> pd.DataFrame:
        rows = []
        for h, p, v in zip(header, payload, variant, strict=True):
            digits = [ord(c) - FIRST_CHAR for c in p]
            word = pack_open_children(h, digits, base, v)
            rows.append((len(word), unpack_open_children(word, len(h), len(digits), base, v) == (h, digits)))
        return pd.DataFrame(rows, columns=["bits", "same"])

    asked = open_children(store).withColumn("variant", F.explode(F.array(*map(F.lit, variants))))
    return asked.withColumn("c", coded("header", "payload", "variant")).select("level", "grp", "variant", "c.bits", "c.same")
