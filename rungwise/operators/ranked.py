"""The ranked codec: fixed blocks of sub-blocks, a flag per sub-block, and offsets by arithmetic on ranks.

A block's word is its flags with their running counts, then the sub-blocks' words (an index among typical sub-blocks
or raw digits) one after the other, filled with zeros to one width for all blocks.  What is left behind the last
whole block is kept raw in a row of its own.
"""

from __future__ import annotations

from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.typeindex import FIRST_CHAR, TypicalSet, char_of, digit_width, pack_bits, to_bits, unpack_bits
from ..plans.schedules import Law, RankedSchedule
from .blocks import settled

#: Flags in one number of the rank directory.
CHUNK = 62


@dataclass
class RankedStore:
    """``blocks(blk, flags array<long>, before array<long>, y binary, failed)`` and ``tail(blk, n_sym, body)``, raw."""

    blocks: DataFrame
    tail: DataFrame
    schedule: RankedSchedule
    law: Law
    n: int


def cut_subblocks(placed: DataFrame, n: int, s: RankedSchedule) -> DataFrame:
    """``(blk, sub, body)`` of the whole blocks; what is left behind them is ``cut_tail``'s."""
    whole = placed.where(F.col("pos") < n // s.b0 * s.b0)
    keys = whole.select(F.floor(F.col("pos") / s.b0).cast("long").alias("blk"), F.floor(F.col("pos") % s.b0 / s.b1).cast("int").alias("sub"), "pos", "ch").repartition("blk")
    listed = F.array_sort(F.collect_list(F.struct("pos", "ch")))
    return keys.groupBy("blk", "sub").agg(F.array_join(F.transform(listed, lambda x: x["ch"]), "").alias("body"))


def cut_tail(placed: DataFrame, n: int, s: RankedSchedule) -> DataFrame:
    """``(blk, n_sym, body)``: the symbols behind the last whole block, fewer than a block's, in one row (none: no row)."""
    rest = placed.where(F.col("pos") >= n // s.b0 * s.b0)
    listed = F.array_sort(F.collect_list(F.struct("pos", "ch")))
    return rest.groupBy(F.floor(F.col("pos") / s.b0).cast("long").alias("blk")).agg(F.count("*").cast("int").alias("n_sym"), F.array_join(F.transform(listed, lambda x: x["ch"]), "").alias("body"))


def words(subs: DataFrame, law: Law, s: RankedSchedule) -> DataFrame:
    """Adds ``open`` (flag 1: stored raw), ``len`` and ``start``: the word's place in its block's payload."""
    flagged = subs.withColumn("open", (~settled(F.col("body"), law, s.num, s.den)).cast("int"))
    sized = flagged.withColumn("len", F.when(F.col("open") == 1, s.raw_bits).otherwise(s.word_bits).cast("long"))
    before = Window.partitionBy("blk").orderBy("sub").rowsBetween(Window.unboundedPreceding, -1)
    return sized.withColumn("start", F.coalesce(F.sum("len").over(before), F.lit(0)))


def encode(subs: DataFrame, law: Law, s: RankedSchedule) -> DataFrame:
    """``(blk, flags, n_open, used_bits, reserved_bits, failed)``; flags[i div CHUNK] holds sub-block i in bit i mod CHUNK."""
    sized = words(subs, law, s)
    chunks = [F.bit_or(F.when(F.floor(F.col("sub") / CHUNK) == c, F.expr(f"shiftleft(cast(open as bigint), sub % {CHUNK})")).otherwise(F.lit(0).cast("long"))) for c in range(-(-s.subs // CHUNK))]
    out = sized.groupBy("blk").agg(F.array(*chunks).alias("flags"), F.sum("open").alias("n_open"), F.sum("len").alias("used_bits"))
    return out.select("blk", "flags", "n_open", (F.col("used_bits") + s.subs).alias("used_bits"), F.lit(s.y_bits + s.subs).cast("long").alias("reserved_bits"), ((F.col("n_open") > s.open_most) | (F.col("used_bits") > s.y_bits)).alias("failed"))


def directory(flags: Column, s: RankedSchedule) -> Column:
    """Open sub-blocks before each chunk of the flags."""
    counts = [F.lit(0).cast("long")]
    for c in range(-(-s.subs // CHUNK) - 1):
        counts.append(counts[-1] + F.bit_count(flags[c]).cast("long"))
    return F.array(*counts)


def rank(flags: Column, before: Column, i: Column) -> Column:
    """Open sub-blocks before sub-block i: one running count and one chunk are read."""
    chunk = F.least(F.floor(i / CHUNK).cast("int"), F.size(flags) - 1)
    mask = F.pow(F.lit(2.0), i - chunk * CHUNK).cast("long") - 1
    return F.element_at(before, chunk + 1) + F.bit_count(F.element_at(flags, chunk + 1).bitwiseAND(mask))


def select(flags: Column, s: RankedSchedule, k: Column) -> Column:
    """Sub-block of the k-th open one (from 1); null if there are fewer."""
    bits = F.flatten(F.transform(flags, lambda f: F.transform(F.sequence(F.lit(0), F.lit(CHUNK - 1)), lambda i: F.getbit(f, i))))
    places = F.filter(F.transform(bits, lambda b, i: F.when(b == 1, i)), lambda x: x.isNotNull())
    return F.when((k >= 1) & (k <= F.size(places)), F.element_at(places, F.greatest(k.cast("int"), F.lit(1))))


def locate(blocks: DataFrame, requests: DataFrame, s: RankedSchedule) -> DataFrame:
    """Where sub-block ``(blk, sub)`` of each request lies: flag, rank before it, payload start, its bits and bits probed.

    One equi-join; the rest is arithmetic, no level is climbed.
    """
    counted = blocks if "before" in blocks.columns else blocks.withColumn("before", directory(F.col("flags"), s))
    at = requests.join(counted, "blk")
    before = rank(F.col("flags"), F.col("before"), F.col("sub"))
    flag = rank(F.col("flags"), F.col("before"), F.col("sub") + 1) - before
    start = before * s.raw_bits + (F.col("sub") - before) * s.word_bits
    length = F.when(flag == 1, s.raw_bits).otherwise(s.word_bits)
    more = [c for c in ("y",) if c in blocks.columns]
    return at.select(*requests.columns, before.cast("long").alias("rank_before"), flag.cast("long").alias("open"), start.cast("long").alias("payload_start"), length.cast("long").alias("len_bits"), (F.lit(s.subs) + length).cast("long").alias("probes"), "failed", *more)


def _coder(law: Law, s: RankedSchedule):
    """Body and flag -> the sub-block's bits, and back."""
    typical, wide = TypicalSet(list(law.counts), s.num, s.den, s.b1), digit_width(law.k)

    def bits(body: str, is_open: int) -> str:
        codes = [ord(c) - FIRST_CHAR for c in body]
        return "".join(to_bits(c, wide) for c in codes) if is_open else to_bits(typical.index(codes) - 1, s.word_bits)

    def body(word: str, is_open: int) -> str:
        codes = [int(word[i : i + wide], 2) for i in range(0, len(word), wide)] if is_open else typical.unindex(int(word, 2) + 1)
        return "".join(map(char_of, codes))

    return bits, body


def block_words(law: Law, s: RankedSchedule):
    """Sub-blocks' bodies and flags in order -> the block's payload, zeros to its full width; Arrow-batched."""
    bits, _ = _coder(law, s)

    @F.pandas_udf("binary")
    def payload(bodies: pd.Series, opens: pd.Series, failed: pd.Series) -> pd.Series:
        return pd.Series([pack_bits(("" if bad else "".join(bits(b, o) for b, o in zip(bs, os, strict=True))).ljust(s.y_bits, "0")) for bs, os, bad in zip(bodies, opens, failed, strict=True)], dtype=object)

    return payload


def sub_bodies(law: Law, s: RankedSchedule):
    """Bytes that hold a sub-block's bits from bit ``shift`` on, and its flag -> its body, null without bytes; Arrow-batched."""
    _, body = _coder(law, s)

    @F.pandas_udf("string")
    def decode(data: pd.Series, shift: pd.Series, length: pd.Series, is_open: pd.Series) -> pd.Series:
        return pd.Series([None if d is None else body(unpack_bits(d, 8 * len(d))[a : a + n], o) for d, a, n, o in zip(data, shift, length, is_open, strict=True)], dtype=object)

    return decode


def _payloads(subs: DataFrame, law: Law, s: RankedSchedule) -> DataFrame:
    """``(blk, flags, before, y, failed)`` of whole blocks."""
    known = encode(subs, law, s).select("blk", "flags", "failed")
    flagged = subs.withColumn("open", (~settled(F.col("body"), law, s.num, s.den)).cast("int"))
    listed = flagged.groupBy("blk").agg(F.array_sort(F.collect_list(F.struct("sub", "open", "body"))).alias("l"))
    both = listed.join(known, "blk")
    y = block_words(law, s)(F.transform("l", lambda x: x["body"]), F.transform("l", lambda x: x["open"]), F.col("failed"))
    return both.select("blk", "flags", directory(F.col("flags"), s).alias("before"), y.alias("y"), "failed")


def store_of(placed: DataFrame, n: int, law: Law, s: RankedSchedule) -> RankedStore:
    """``(pos, ch)`` -> store."""
    return RankedStore(_payloads(cut_subblocks(placed, n, s), law, s), cut_tail(placed, n, s), s, law, n)


def bodies(store: RankedStore, requests: DataFrame) -> DataFrame:
    """``requests`` of sub-blocks with ``body``, from the stored words alone; null in failed blocks.

    Only the bytes that hold a sub-block's bits go to its decoder, none of a failed block: its words outgrow its width,
    so places behind the payload's end would be read.
    """
    s = store.schedule
    found = locate(store.blocks, requests, s)
    first = F.floor(F.col("payload_start") / 8).cast("int")
    held = F.expr("CAST(floor((payload_start % 8 + len_bits + 7) / 8) AS INT)")
    data = F.when(~F.col("failed"), F.substring("y", first + 1, held))
    body = sub_bodies(store.law, s)(data, (F.col("payload_start") % 8).cast("int"), F.col("len_bits").cast("int"), F.col("open").cast("int"))
    return found.select(*requests.columns, "probes", "failed", "open", body.alias("body"))


def decode(store: RankedStore) -> DataFrame:
    """``(blk, body, failed)`` of every block and the tail."""
    s = store.schedule
    every = store.blocks.select("blk", F.explode(F.sequence(F.lit(0), F.lit(s.subs - 1))).alias("sub"))
    parts = bodies(store, every).groupBy("blk", "failed").agg(F.array_sort(F.collect_list(F.struct("sub", "body"))).alias("l"))
    whole = parts.select("blk", F.when(~F.col("failed"), F.array_join(F.transform("l", lambda x: x["body"]), "")).alias("body"), "failed")
    return whole.unionByName(store.tail.select("blk", "body", F.lit(False).alias("failed")))


def update_store(store: RankedStore, edits: DataFrame) -> RankedStore:
    """The store after edits ``(edit_id, blk, sub, body)`` of whole sub-blocks; the last edit of a sub-block wins.

    Only touched blocks are read and written anew (a failed block can't be edited and stays).  Sub-blocks that keep
    their status keep their place; a flipped one moves what follows it, so its block is packed again.
    """
    s, law = store.schedule, store.law
    last = edits.groupBy("blk", "sub").agg(F.max_by("body", "edit_id").alias("new"))
    touched = store.blocks.where("not failed").join(last.select("blk").distinct(), "blk", "left_semi")
    every = touched.select("blk", F.explode(F.sequence(F.lit(0), F.lit(s.subs - 1))).alias("sub"))
    old = bodies(RankedStore(touched, store.tail, s, law, store.n), every).select("blk", "sub", "body")
    now = old.join(last, ["blk", "sub"], "left").select("blk", "sub", F.coalesce("new", "body").alias("body"))
    kept = store.blocks.join(touched.select("blk"), "blk", "left_anti")
    return RankedStore(kept.unionByName(_payloads(now, law, s)), store.tail, s, law, store.n)


def update_costs(subs: DataFrame, edits: DataFrame, law: Law, s: RankedSchedule) -> DataFrame:
    """``(edit_id, blk, sub, case, bits)``: a kept status patches one word, a flipped one rewrites the block."""
    sized = words(subs, law, s)
    used = sized.groupBy("blk").agg(F.sum("len").alias("used"))
    at = edits.select("edit_id", "blk", "sub", F.col("body").alias("new_body")).join(sized.select("blk", "sub", "open", "len"), ["blk", "sub"]).join(used, "blk")
    now = (~settled(F.col("new_body"), law, s.num, s.den)).cast("int")
    case = F.concat(F.when(F.col("open") == 1, "O").otherwise("S"), F.when(now == 1, "O").otherwise("S"))
    new_len = F.when(now == 1, s.raw_bits).otherwise(s.word_bits)
    bits = F.when(F.col("open") == now, s.subs + 2 * F.col("len")).otherwise(2 * s.subs + 2 * F.col("used") - F.col("len") + new_len)
    return at.select("edit_id", "blk", "sub", case.alias("case"), bits.cast("long").alias("bits"))


def answer(store: RankedStore, spans: DataFrame) -> DataFrame:
    """``(req_id, start, len, value, probes, failed)`` of spans, from the stored words and the raw tail.

    A read of the tail probes its symbols' digits.  A span past the end is cut there; an empty one has no row.
    """
    s, n = store.schedule, store.n
    total, wide = n // s.b0 * s.b0, digit_width(store.law.k)
    inside = spans.select("req_id", "start", "len", F.least(F.col("len"), F.greatest(F.lit(n) - F.col("start"), F.lit(0))).alias("got")).where("got > 0")
    end = F.least(F.col("start") + F.col("got"), F.lit(total))
    cells = inside.where(F.col("start") < total).select("req_id", "start", "len", end.alias("end"), F.explode(F.sequence(F.floor(F.col("start") / s.b1), F.floor((end - 1) / s.b1))).alias("cell"))
    found = bodies(store, cells.withColumn("blk", F.floor(F.col("cell") / s.subs)).withColumn("sub", (F.col("cell") % s.subs).cast("int")))
    low = F.greatest(F.col("start") - F.col("cell") * s.b1, F.lit(0))
    high = F.least(F.col("end") - F.col("cell") * s.b1, F.lit(s.b1))
    pieces = found.select("req_id", "start", "len", "cell", F.substring("body", (low + 1).cast("int"), (high - low).cast("int")).alias("p"), "probes", "failed")
    first = F.greatest(F.col("start"), F.lit(total))
    size = F.col("start") + F.col("got") - first
    ends = inside.where(F.col("start") + F.col("got") > total).withColumn("blk", F.lit(n // s.b0).cast("long")).join(store.tail.select("blk", "body"), "blk")
    rest = ends.select("req_id", "start", "len", F.lit(total).cast("long").alias("cell"), F.substring("body", (first - total + 1).cast("int"), size.cast("int")).alias("p"), (size * wide).cast("long").alias("probes"), F.lit(False).alias("failed"))
    joined = pieces.unionByName(rest)
    return joined.groupBy("req_id", "start", "len").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("cell", "p"))), lambda x: x["p"]), "").alias("value"), F.sum("probes").alias("probes"), F.max("failed").alias("failed"))
