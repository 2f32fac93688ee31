"""The ladder codec: blocks settle at level 0 or climb; groups settle when few of their children are open.

The store is sparse.  Whatever a cell of any level would carry is the raw bodies of level-0-open blocks and a
header; so there is one row per block (its word if settled), one row per group and level (its header), and one row
per open block (its body and home level).  Cell widths stay arithmetic, for all cost measures.
"""

from __future__ import annotations

from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lz import fixed_word, read_fixed_word
from ..functions.typeindex import FIRST_CHAR, TypicalSet, char_of, pack_bits, to_bits, unpack_bits, word_width
from ..plans.schedules import LadderSchedule, Law
from .blocks import group_number, settled


@dataclass
class LadderStore:
    """``blocks0(chunk, blk, n_sym, settled, word)``, ``groups[l](grp, n_child, open_count, settled, header)``,
    ``open_rows(blk, body, home)``; home is null where no level settled."""

    blocks0: DataFrame
    groups: list[DataFrame]
    open_rows: DataFrame
    schedule: LadderSchedule
    law: Law
    n: int
    state: DataFrame  # blk, n_sym, body, settled, group numbers, open counts and flags by level, home


def lz_encoder(law: Law, s: LadderSchedule):
    """Body -> packed LZ word, null where it doesn't fit the schedule's width; Arrow-batched."""
    k = law.k

    @F.pandas_udf("binary")
    def encode(body: pd.Series) -> pd.Series:
        words = [fixed_word([ord(c) - FIRST_CHAR for c in text], k, s.word_bits(len(text))) for text in body]
        return pd.Series([None if w is None else pack_bits(w) for w in words], dtype=object)

    return encode


def lz_decoder(law: Law, s: LadderSchedule):
    k = law.k

    @F.pandas_udf("string")
    def decode(word: pd.Series, n_sym: pd.Series) -> pd.Series:
        return pd.Series([None if w is None else "".join(map(char_of, read_fixed_word(unpack_bits(w, s.word_bits(n)), k, n))) for w, n in zip(word, n_sym, strict=True)], dtype=object)

    return decode


def block_settled(body: Column, law: Law, s: LadderSchedule) -> Column:
    """Whether a block has a word at level 0: it is typical, or its LZ code fits if the schedule is universal."""
    return lz_encoder(law, s)(body).isNotNull() if s.universal else settled(body, law, s.num, s.den)


def word_encoder(law: Law, s: LadderSchedule):
    """Body -> packed index of a settled block, as an Arrow-batched function."""
    counts, num, den, k0 = list(law.counts), s.num, s.den, s.k0
    sets: dict[int, TypicalSet] = {}

    @F.pandas_udf("binary")
    def encode(body: pd.Series, ok: pd.Series) -> pd.Series:
        out = []
        for text, good in zip(body, ok, strict=True):
            if not good:
                out.append(None)
                continue
            t = sets.setdefault(len(text), TypicalSet(counts, num, den, len(text)))
            number = t.index([ord(c) - FIRST_CHAR for c in text])
            out.append(pack_bits(to_bits(number, word_width(k0, t))))
        return pd.Series(out, dtype=object)

    return encode


def word_decoder(law: Law, s: LadderSchedule):
    if s.universal:
        return lz_decoder(law, s)
    counts, num, den, k0 = list(law.counts), s.num, s.den, s.k0
    sets: dict[int, TypicalSet] = {}

    @F.pandas_udf("string")
    def decode(word: pd.Series, n_sym: pd.Series) -> pd.Series:
        out = []
        for data, n in zip(word, n_sym, strict=True):
            if data is None:
                out.append(None)
                continue
            t = sets.setdefault(n, TypicalSet(counts, num, den, n))
            out.append("".join(map(char_of, t.unindex(int(unpack_bits(data, word_width(k0, t)), 2)))))
        return pd.Series(out, dtype=object)

    return decode


def children_at(s: LadderSchedule, n: int, level: int) -> int:
    """Units of ``level`` in a sequence of n symbols."""
    units = max(n // s.b0, 1)
    for x in s.levels[:level]:
        units = max(units // x.fanout, 1)
    return units


def with_groups(blocks: DataFrame, s: LadderSchedule, n: int) -> DataFrame:
    """Group numbers of every level beside each block: ``g1``, ``g2`` ..."""
    out, child = blocks, F.col("blk")
    for i, level in enumerate(s.levels, 1):
        child = group_number(child, children_at(s, n, i - 1), level.fanout)
        out = out.withColumn(f"g{i}", child)
    return out


def climb(level0: DataFrame, s: LadderSchedule) -> tuple[DataFrame, list[DataFrame]]:
    """Group states level by level; every level reads the small table of the level below.

    Groups nest in the chunk by which blocks are dealt, so the first aggregation needs no further exchange.
    """
    groups = []
    below = level0.select("chunk", F.col("blk").alias("child"), "settled", *[f"g{i}" for i in range(1, len(s.levels) + 1)])
    for i, level in enumerate(s.levels, 1):
        upper = [f"g{j}" for j in range(i + 1, len(s.levels) + 1)]
        child = F.col("child")
        table = below.groupBy("chunk", f"g{i}", *upper).agg(
            F.count("*").alias("n_child"),
            F.sum((~F.col("settled")).cast("long")).alias("open_count"),
            F.array_sort(F.collect_list(F.when(~F.col("settled"), child))).alias("header"),
        )
        table = table.withColumn("settled", F.col("open_count") <= F.floor(F.col("n_child") * level.num / level.den))
        groups.append(table.select("chunk", F.col(f"g{i}").alias("grp"), "n_child", "open_count", "settled", "header"))
        below = table.select("chunk", F.col(f"g{i}").alias("child"), "settled", *upper)
    return below, groups


def home_column(levels: int) -> Column:
    out = F.lit(None).cast("int")
    for i in range(levels, 0, -1):
        out = F.when(F.col(f"settled{i}"), F.lit(i)).otherwise(out)
    return F.when(F.col("settled"), F.lit(0)).otherwise(out)


def encode(blocks: DataFrame, law: Law, s: LadderSchedule, n: int, words: bool = True) -> LadderStore:
    """Blocks ``(chunk, blk, n_sym, body)`` -> store.  ``words`` False leaves the index words out (costs only)."""
    if s.universal:  # the word itself is the test
        coded = blocks.withColumn("word", lz_encoder(law, s)(F.col("body"))).withColumn("settled", F.col("word").isNotNull())
        return store_of(coded, law, s, n)
    tested = blocks.withColumn("settled", settled(F.col("body"), law, s.num, s.den))
    return store_of(tested, law, s, n, word_encoder(law, s)(F.col("body"), F.col("settled")) if words else F.lit(None).cast("binary"))


def store_of(tested: DataFrame, law: Law, s: LadderSchedule, n: int, word: Column | None = None) -> LadderStore:
    """Blocks with ``settled``, and ``word`` as a column of theirs or as given, -> store."""
    level0 = with_groups(tested, s, n)
    _, groups = climb(level0, s)
    state = level0
    for i, g in enumerate(groups, 1):
        state = state.join(g.select("chunk", F.col("grp").alias(f"g{i}"), F.col("open_count").alias(f"open{i}"), F.col("n_child").alias(f"n{i}"), F.col("settled").alias(f"settled{i}")), ["chunk", f"g{i}"])
    state = state.withColumn("home", home_column(len(groups)))
    blocks0 = level0.select("chunk", "blk", "n_sym", "settled", (F.col("word") if word is None else word).alias("word"))
    return LadderStore(blocks0, groups, state.where("not settled").select("chunk", "blk", "body", "home"), s, law, n, state)


def decode(store: LadderStore) -> DataFrame:
    """``(blk, body, failed)`` of every block, from the store alone."""
    body = word_decoder(store.law, store.schedule)(F.col("word"), F.col("n_sym"))
    back = store.blocks0.join(store.open_rows.select("blk", F.col("body").alias("raw"), "home"), "blk", "left")
    return back.select("blk", "n_sym", F.when(F.col("settled"), body).when(F.col("home").isNotNull(), F.col("raw")).alias("body"), (~F.col("settled") & F.col("home").isNull()).alias("failed"))


def full_cost(s: LadderSchedule, home: Column) -> Column:
    """Bits of a read that takes every visited cell whole; a failed block visits all levels."""
    sums, at = [], 0
    for w in s.widths:
        at += w
        sums.append(at)
    return F.element_at(F.array(*[F.lit(x).cast("long") for x in sums]), F.coalesce(home, F.lit(len(sums) - 1)) + 1)


def header_cost(s: LadderSchedule, home: Column) -> Column:
    """Bits of a read that takes only headers below the home level and the home cell whole."""
    out, headers = [s.k0], 0
    for level in s.levels:
        out.append(s.k0 + headers + level.width)
        headers += level.header
    return F.element_at(F.array(*[F.lit(x).cast("long") for x in out]), F.coalesce(home, F.lit(len(out) - 1)) + 1)


def slot_cost(s: LadderSchedule, home: Column) -> Column:
    """Bits of a read that takes headers and, of the home cell, only the wanted block's digits."""
    out, headers = [s.k0], 0
    for level in s.levels:
        headers += level.header
        out.append(s.k0 + headers + s.b0 * s.digit_bits)
    return F.element_at(F.array(*[F.lit(x).cast("long") for x in out]), F.coalesce(home, F.lit(len(out) - 1)) + 1)


def touched(spans: DataFrame, n: int, b0: int) -> DataFrame:
    """Spans ``(req_id, start, len)`` exploded to the blocks they cover."""
    first, last = F.col("start"), F.col("start") + F.col("len") - 1
    last_blk = max(n // b0, 1) - 1
    blk = lambda p: F.least(F.floor(p / b0).cast("long"), F.lit(last_blk).cast("long"))
    return spans.where("len > 0").select("req_id", "start", "len", F.explode(F.sequence(blk(first), blk(last))).alias("blk"))


def read_spans(store: LadderStore, spans: DataFrame, max_level: int | None = None) -> DataFrame:
    """``(req_id, start, len, value, home_max, probes_full, probes_header, probes_slot, failed)`` for every span.

    Only the blocks that spans touch are decoded; probes count each touched block once per span.  With
    ``max_level`` blocks that live higher count as failed (the local error of a capped read).  An empty span has an
    empty value and no probes; a span past the end is cut at the end and ``failed``.
    """
    s = store.schedule
    exploded = clipped(spans, store.n, s.b0)
    wanted = exploded.select("blk").distinct()
    part = store.blocks0.join(wanted, "blk", "left_semi").join(store.open_rows.select("blk", F.col("body").alias("raw"), "home"), "blk", "left")
    body = word_decoder(store.law, s)(F.col("word"), F.col("n_sym"))
    home = F.when(F.col("settled"), F.lit(0)).otherwise(F.col("home"))
    part = part.select("blk", "n_sym", "settled", home.alias("home"), F.when(F.col("settled"), body).when(F.col("home").isNotNull(), F.col("raw")).alias("body"))
    return stitched(spans, exploded, part, s, store.n, max_level)


def clipped(spans: DataFrame, n: int, b0: int) -> DataFrame:
    """Spans cut at the end of the sequence, exploded to the blocks they cover."""
    inside = spans.select("req_id", "start", F.least(F.col("len"), F.greatest(F.lit(n) - F.col("start"), F.lit(0))).alias("len"))
    return touched(inside, n, b0)


def stitched(spans: DataFrame, exploded: DataFrame, blocks: DataFrame, s: LadderSchedule, n: int, max_level: int | None = None) -> DataFrame:
    """Answers to ``spans`` from the decoded ``blocks(blk, n_sym, home, body)`` that they touch."""
    b0 = s.b0
    cap = len(s.levels) if max_level is None else max_level
    part = blocks.select("blk", "n_sym", "home", F.when(F.col("home") <= cap, F.col("body")).alias("body")).withColumn("bad", F.col("body").isNull())
    cost_home = F.least(F.coalesce(F.col("home"), F.lit(len(s.levels))), F.lit(cap))
    joined = exploded.join(part, "blk").withColumn("at", F.greatest(F.col("start") - F.col("blk") * b0, F.lit(0)))
    piece = F.substring(F.coalesce("body", F.repeat(F.lit("?"), F.col("n_sym"))), (F.col("at") + 1).cast("int"), (F.least(F.col("start") + F.col("len"), F.col("blk") * b0 + F.col("n_sym")) - F.greatest(F.col("start"), F.col("blk") * b0)).cast("int"))
    found = joined.groupBy("req_id").agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("blk", piece.alias("p")))), lambda x: x["p"]), "").alias("value"),
        F.max(F.coalesce(F.col("home"), F.lit(-1))).alias("home_max"),
        F.sum(full_cost(s, cost_home)).alias("probes_full"),
        F.sum(header_cost(s, cost_home)).alias("probes_header"),
        F.sum(slot_cost(s, cost_home)).alias("probes_slot"),
        F.max("bad").alias("bad"),
    )
    zero, got = F.lit(0).cast("long"), F.least(F.col("len"), F.greatest(F.lit(n) - F.col("start"), F.lit(0)))
    return spans.join(found, "req_id", "left").select("req_id", "start", "len", F.coalesce("value", F.lit("")).alias("value"), F.coalesce(F.col("home_max"), F.lit(0)).alias("home_max"), *(F.coalesce(c, zero).alias(c) for c in ("probes_full", "probes_header", "probes_slot")), (F.coalesce("bad", F.lit(False)) | (got < F.col("len"))).alias("failed"))


def shared_cells(store: LadderStore, spans: DataFrame) -> DataFrame:
    """``(req_id, cells, bits)``: each distinct cell of a span charged once."""
    s = store.schedule
    at = touched(spans, store.n, s.b0).join(store.state.select("blk", *[f"g{i}" for i in range(1, len(s.levels) + 1)], "home"), "blk")
    top = F.coalesce("home", F.lit(len(s.levels)))
    cells = F.array(*[F.when(top >= i, F.struct(F.lit(i).alias("level"), (F.col("blk") if i == 0 else F.col(f"g{i}")).alias("cell"), F.lit(w).cast("long").alias("bits"))) for i, w in enumerate(s.widths)])
    once = at.select("req_id", F.explode(F.filter(cells, lambda x: x.isNotNull())).alias("c")).select("req_id", "c.*").distinct()
    return once.groupBy("req_id").agg(F.count("*").alias("cells"), F.sum("bits").alias("bits"))


def update_state(store: LadderStore, edits: DataFrame) -> DataFrame:
    """State ``(blk, body, settled, home)`` after the edits ``(edit_id, blk, body)``; the last edit of a block wins.

    Open counts change by the net of settled and opened blocks in each touched group; only a flipped group passes
    a change on to the next level.
    """
    s, law = store.schedule, store.law
    net = edits.groupBy("blk").agg(F.max_by("body", "edit_id").alias("new_body"))
    state = store.state.join(net, "blk", "left").withColumn("now", F.coalesce("new_body", "body"))
    state = state.withColumn("now_settled", F.when(F.col("new_body").isNull(), F.col("settled")).otherwise(block_settled(F.col("now"), law, s)))
    change = state.where("now_settled <> settled").select("g1", F.when(F.col("settled"), 1).otherwise(-1).alias("d")) if s.levels else None
    out = state
    for i, level in enumerate(s.levels, 1):
        delta = change.groupBy(f"g{i}").agg(F.sum("d").alias(f"d{i}"))
        out = out.join(delta, f"g{i}", "left").withColumn(f"now_settled{i}", F.col(f"open{i}") + F.coalesce(f"d{i}", F.lit(0)) <= F.floor(F.col(f"n{i}") * level.num / level.den))
        if i < len(s.levels):
            change = out.where(f"now_settled{i} <> settled{i}").select(f"g{i}", f"g{i + 1}", F.when(F.col(f"settled{i}"), 1).otherwise(-1).alias("d")).distinct().select(f"g{i + 1}", "d")
    home = F.lit(None).cast("int")
    for i in range(len(s.levels), 0, -1):
        home = F.when(F.col(f"now_settled{i}"), F.lit(i)).otherwise(home)
    return out.select("blk", F.col("now").alias("body"), F.col("now_settled").alias("settled"), F.when(F.col("now_settled"), F.lit(0)).otherwise(home).alias("home"))


def update_costs(store: LadderStore, edits: DataFrame, sequential: bool = False) -> DataFrame:
    """``(edit_id, blk, case, old_home, new_home, bits_read, bits_written)`` of every edit.

    Each edit meets the stored state or, if ``sequential``, the state that the edits with smaller ids left (ids are
    distinct).  Settled to settled rewrites the word.  Open to open reads up to the home cell and rewrites it.
    Otherwise every cell up to the higher of the two homes is read and rewritten.

    The sequence of edits needs no loop: a block's state is its previous edit's, and a group's open count is the
    stored one plus the running sum of what earlier edits changed in it.
    """
    s, law = store.schedule, store.law
    at = edits.select("edit_id", "blk", F.col("body").alias("new_body")).join(store.state, "blk").withColumn("new", block_settled(F.col("new_body"), law, s))
    if sequential:
        at = at.withColumn("settled", F.coalesce(F.lag("new").over(Window.partitionBy("blk").orderBy("edit_id")), F.col("settled")))
    shift = lambda before, after: F.when(F.col(before) & ~F.col(after), 1).when(~F.col(before) & F.col(after), -1).otherwise(0)
    at = at.withColumn("d1", shift("settled", "new"))
    for i, level in enumerate(s.levels, 1):
        most = F.floor(F.col(f"n{i}") * level.num / level.den)
        if sequential:
            earlier = Window.partitionBy(f"g{i}").orderBy("edit_id").rowsBetween(Window.unboundedPreceding, -1)
            at = at.withColumn(f"open{i}", F.col(f"open{i}") + F.coalesce(F.sum(f"d{i}").over(earlier), F.lit(0))).withColumn(f"settled{i}", F.col(f"open{i}") <= most)
        at = at.withColumn(f"new{i}", F.col(f"open{i}") + F.col(f"d{i}") <= most)
        at = at.withColumn(f"d{i + 1}", shift(f"settled{i}", f"new{i}"))
    if sequential:
        at = at.withColumn("home", home_column(len(s.levels)))
    new_home = F.lit(None).cast("int")
    for i in range(len(s.levels), 0, -1):
        new_home = F.when(F.col(f"new{i}"), F.lit(i)).otherwise(new_home)
    new_home = F.when(F.col("new"), F.lit(0)).otherwise(new_home)
    at = at.withColumn("new_home", new_home).withColumn("case", F.concat(F.when(F.col("settled"), "S").otherwise("O"), F.when(F.col("new"), "S").otherwise("O")))
    top = F.lit(len(s.levels))
    old, new = F.coalesce("home", top), F.coalesce("new_home", top)
    widths = F.array(*[F.lit(w).cast("long") for w in s.widths])
    both = full_cost(s, F.greatest(old, new))
    read = F.when(F.col("case") == "SS", F.lit(s.k0).cast("long")).when(F.col("case") == "OO", full_cost(s, old)).otherwise(both)
    wrote = F.when(F.col("case") == "SS", F.lit(s.k0).cast("long")).when(F.col("case") == "OO", F.element_at(widths, old + 1)).otherwise(both)
    return at.select("edit_id", "blk", "case", F.coalesce("home", F.lit(-1)).alias("old_home"), F.coalesce("new_home", F.lit(-1)).alias("new_home"), read.alias("bits_read"), wrote.alias("bits_written"))
