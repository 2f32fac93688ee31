"""Registered queries of the codecs, their measures and their baselines."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.typeindex import TypicalSet
from .operators import baselines, ladder, ranked
from .operators.blocks import cut_blocks, cut_text, group_number, settled, symbol_count
from .plans import bounds
from .plans.schedules import PRESETS, RANKED_DEMO, LadderSchedule, Law, ladder_schedule, ranked_schedule, universal_schedule
from .sources import ladder_store
from .sources.catalog import SOURCES, class_text, index_rows, law_of, positions, read_table, symbol_column
from .sources.shared import fresh_folder, written

LAW_SOURCES = ("li_flag", "li_status", "li_small_qty", "li_zero_tax", "od_status", "od_prio", "ev_type", "dc_lang", "lb_quality", "lb_toxic", "cv_role")
N_SPANS, N_EDITS = 200, 100
STRETCH = 4096


def _blocks(spark: SparkSession, sf_dir: str, preset: str, **more) -> tuple[DataFrame, Law, LadderSchedule, int]:
    p = PRESETS[preset] | more
    placed, law, n = positions(spark, sf_dir, p["source"])
    s = universal_schedule(law, p["b0"], p["slack"], p["num"], p["den"], p["fanouts"], n) if "slack" in p else ladder_schedule(law, p["b0"], p["num"], p["den"], p["fanouts"], n)
    chunk = 1
    for x in s.levels:
        chunk *= x.fanout
    return cut_blocks(placed, n, s.b0, chunk), law, s, n


def _store(spark: SparkSession, sf_dir: str, preset: str = "demo3", words: bool = False, **more) -> ladder.LadderStore:
    blocks, law, s, n = _blocks(spark, sf_dir, preset, **more)
    return ladder.encode(blocks, law, s, n, words)


_saved: dict[tuple[str, str, str], ladder_store.SavedStore] = {}


def _saved_store(spark: SparkSession, sf_dir: str, preset: str = "demo3") -> ladder_store.SavedStore:
    """The preset's store in the session's shared folder, written at its first use."""
    key = (spark.sparkContext.applicationId, sf_dir, preset)
    if key not in _saved:
        _saved[key] = ladder_store.save(_store(spark, sf_dir, preset, words=True), fresh_folder(spark, "store"))
    return _saved[key]


def spans(spark: SparkSession, n: int, count: int = N_SPANS) -> DataFrame:
    start = (F.col("id") * 7919 + 13) % n
    return spark.range(count).select(F.col("id").alias("req_id"), start.alias("start"), F.least(F.col("id") * 104729 % 97 + 1, F.lit(n) - start).alias("len"))


def edits(blocks: DataFrame, units: int, b0: int, count: int = N_EDITS) -> DataFrame:
    """Whole-block edits whose bodies come from other blocks of the same sequence."""
    k = blocks.sparkSession.range(count).select(F.col("id").alias("edit_id"), ((F.col("id") * 7919 + 5) % units).alias("blk"), ((F.col("id") * 6007 + 11) % units).alias("src"))
    whole = blocks.where(F.col("n_sym") == b0)
    bodies = k.join(whole.select(F.col("blk").alias("src"), "body"), "src")
    return bodies.join(whole.select("blk"), "blk", "left_semi").select("edit_id", "blk", "body")


# laws, positions, blocks


def alphabet_law(spark, sf_dir):
    out = None
    for name in LAW_SOURCES:
        one = symbol_column(spark, sf_dir, name).groupBy("symbol").agg(F.count("*").alias("cnt")).select(F.lit(name).alias("source"), "symbol", "cnt")
        out = one if out is None else out.unionByName(one)
    return out


def source_entropy(spark, sf_dir):
    w = Window.partitionBy("source")
    p = alphabet_law(spark, sf_dir).withColumn("total", F.sum("cnt").over(w)).withColumn("p", F.col("cnt") / F.col("total"))
    return p.groupBy("source").agg(F.count("*").alias("k"), F.max("total").alias("n"), F.round(-F.sum(F.col("p") * F.log2("p")), 6).alias("entropy"))


def dyadic_report(spark, sf_dir):
    w = Window.partitionBy("source")
    p = alphabet_law(spark, sf_dir).withColumn("total", F.sum("cnt").over(w))
    power = (F.col("total") % F.col("cnt") == 0) & (F.bit_count(F.floor(F.col("total") / F.col("cnt")).cast("long")) == 1)
    return p.groupBy("source").agg(F.bool_and(power).alias("dyadic"), F.max(F.round(F.log2(F.col("total") / F.col("cnt")), 6)).alias("max_self_information"))


def dense_positions(spark, sf_dir):
    s = SOURCES["li_small_qty"]
    return index_rows(read_table(spark, sf_dir, s.table).select(*s.key), s.key).select("pos", "l_orderkey", "l_partkey")


def block_cut(spark, sf_dir):
    blocks, *_ = _blocks(spark, sf_dir, "demo3")
    return blocks.select("blk", "n_sym", "body")


def block_cut_text(spark, sf_dir):
    return cut_text(read_table(spark, sf_dir, "documents"), "doc_id", F.col("text"), 512)


def block_histogram(spark, sf_dir):
    blocks, law, _, _ = _blocks(spark, sf_dir, "flag3")
    return blocks.select("blk", *[symbol_count(F.col("body"), c).cast("long").alias(f"n{i}") for i, c in enumerate(law.chars)])


def block_settled(spark, sf_dir):
    blocks, law, s, _ = _blocks(spark, sf_dir, "flag3")
    return blocks.select("blk", settled(F.col("body"), law, s.num, s.den).alias("settled"))


def typical_set_size(spark, sf_dir):
    law = law_of(symbol_column(spark, sf_dir, "li_small_qty"))
    rows = []
    for b in (16, 32, 64):
        t = TypicalSet(list(law.counts), 1, 2, b)
        rows.append((b, t.bounds[1][0], t.bounds[1][1], str(t.size)))
    return spark.createDataFrame(rows, "b long, low long, high long, size string")


def type_index_b16(spark, sf_dir):
    blocks, law, s, _ = _blocks(spark, sf_dir, "index16")
    t = TypicalSet(list(law.counts), s.num, s.den, s.b0)
    low = t.bounds[1][0]
    # relational form: one row per one, its place counts the strings with a zero there
    choose = spark.createDataFrame([(n, k, _comb(n, k)) for n in range(17) for k in range(17)], "n int, k int, c long")
    ones = blocks.where((F.col("n_sym") == 16) & settled(F.col("body"), law, s.num, s.den)).select("blk", F.posexplode(F.split("body", "")).alias("i", "ch")).where("ch = '1'")
    w = Window.partitionBy("blk").orderBy(F.desc("i"))
    places = ones.withColumn("k", F.row_number().over(w)).withColumn("n", 15 - F.col("i")).join(F.broadcast(choose), ["n", "k"])
    skipped = F.broadcast(spark.createDataFrame([(w_, sum(_comb(16, x) for x in range(low, w_))) for w_ in range(low, t.bounds[1][1] + 1)], "weight long, skipped long"))
    return places.groupBy("blk").agg(F.count("*").alias("weight"), F.sum("c").alias("place")).join(skipped, "weight").select("blk", (F.col("skipped") + F.col("place") + 1).alias("idx"))


def _comb(n, k):
    from math import comb

    return comb(n, k)


def type_unindex_b16(spark, sf_dir):
    blocks, law, s, _ = _blocks(spark, sf_dir, "index16")
    whole = blocks.where(F.col("n_sym") == 16).withColumn("settled", settled(F.col("body"), law, s.num, s.den)).where("settled")
    word = ladder.word_encoder(law, s)(F.col("body"), F.col("settled"))
    return whole.select("blk", "n_sym", word.alias("word")).select("blk", ladder.word_decoder(law, s)(F.col("word"), F.col("n_sym")).alias("body"))


# ladder


def ladder_level0(spark, sf_dir):
    st = _store(spark, sf_dir)
    return st.state.select("blk", "n_sym", "settled")


def _level(spark, sf_dir, i):
    g = _store(spark, sf_dir).groups[i - 1]
    return g.select("grp", "n_child", "open_count", "settled", F.array_join(F.transform("header", lambda x: x.cast("string")), ",").alias("open_children"))


def ladder_level1(spark, sf_dir):
    return _level(spark, sf_dir, 1)


def ladder_level2(spark, sf_dir):
    return _level(spark, sf_dir, 2)


def ladder_home_profile(spark, sf_dir):
    out = None
    for preset in ("demo3", "deep3", "calm", "flag3"):
        one = _store(spark, sf_dir, preset).state.groupBy(F.coalesce("home", F.lit(-1)).alias("home")).agg(F.count("*").alias("blocks")).select(F.lit(preset).alias("preset"), "home", "blocks")
        out = one if out is None else out.unionByName(one)
    return out


def ladder_trace(spark, sf_dir):
    st = _store(spark, sf_dir, "flag3")
    out = st.state.agg(F.count("*").alias("units"), F.sum((~F.col("settled")).cast("long")).alias("open_units")).select(F.lit(0).alias("level"), "*")
    for i, g in enumerate(st.groups, 1):
        out = out.unionByName(g.agg(F.count("*").alias("units"), F.sum((~F.col("settled")).cast("long")).alias("open_units")).select(F.lit(i).alias("level"), "*"))
    return out


def ladder_failures(spark, sf_dir):
    return _store(spark, sf_dir, "deep3").state.where("home is null").select("blk", "n_sym")


def ladder_bit_budget(spark, sf_dir):
    """Reserved and used bits by level."""
    st = _store(spark, sf_dir)
    s = st.schedule
    used0 = st.state.agg(F.count("*").alias("units"), F.sum(F.col("settled").cast("long") * s.k0).alias("used_bits")).select(F.lit(0).alias("level"), "units", (F.col("units") * s.k0).alias("reserved_bits"), "used_bits")
    out = used0
    for i, (g, x) in enumerate(zip(st.groups, s.levels, strict=True), 1):
        body = st.state.where(F.col("home") == i).agg(F.coalesce(F.sum(F.col("n_sym") * s.digit_bits), F.lit(0)).alias("payload"))
        units = g.agg(F.count("*").alias("units"), F.sum("n_child").alias("header"))
        out = out.unionByName(units.join(F.broadcast(body)).select(F.lit(i).alias("level"), "units", (F.col("units") * x.width).alias("reserved_bits"), (F.col("header") + F.col("payload")).alias("used_bits")))
    return out


def ladder_rate_vs_bound(spark, sf_dir):
    rows = []
    for preset in ("demo3", "calm", "flag3"):
        p = PRESETS[preset]
        law = law_of(symbol_column(spark, sf_dir, p["source"]))
        s = ladder_schedule(law, p["b0"], p["num"], p["den"], p["fanouts"], law.total)
        rows.append((preset, round(law.entropy, 6), round(bounds.nominal_rate(s), 6), round(bounds.rate_bound(law, p["num"] / p["den"]), 6), bounds.nominal_rate(s) <= bounds.rate_bound(law, p["num"] / p["den"])))
    return spark.createDataFrame(rows, "preset string, entropy double, rate double, bound double, holds boolean")


def ladder_roundtrip(spark, sf_dir):
    """Every block back from the saved store."""
    st = _saved_store(spark, sf_dir)
    return ladder_store.decoded(st, st.table("blocks")).select("blk", "body", F.col("home").isNull().alias("failed"))


def ladder_read_symbols(spark, sf_dir):
    st = _saved_store(spark, sf_dir)
    one = spans(spark, st.n).withColumn("len", F.lit(1).cast("long"))
    return ladder_store.read_spans(st, one).select("req_id", "start", "value")


def ladder_read_spans(spark, sf_dir):
    st = _saved_store(spark, sf_dir)
    return ladder_store.read_spans(st, spans(spark, st.n)).select("req_id", "start", "len", "value")


def stored_update_state(spark, sf_dir):
    """Blocks of a saved store after a batch of edits that overwrote its touched parts."""
    blocks, law, s, n = _blocks(spark, sf_dir, "deep3")
    st = ladder_store.save(ladder.encode(blocks, law, s, n), fresh_folder(spark, "edited"))
    ladder_store.update(st, edits(blocks, n // s.b0, s.b0))
    return ladder_store.decoded(st, st.table("blocks")).select("blk", F.coalesce("body", "raw").alias("body"), "settled", F.coalesce("home", F.lit(-1)).alias("home"))


def _cost(spark, sf_dir, column):
    st = _saved_store(spark, sf_dir)
    s = st.schedule
    cost = {"full": ladder.full_cost, "header": ladder.header_cost, "slot": ladder.slot_cost}[column](s, F.col("home"))
    asked = ladder.touched(spans(spark, st.n), st.n, s.b0)
    at = asked.join(st.blocks_at(asked).select("blk", "home"), "blk")
    return at.groupBy("req_id").agg(F.sum(cost).alias("probes"), F.max(F.coalesce("home", F.lit(-1))).alias("home_max"))


def ladder_read_cost_full(spark, sf_dir):
    return _cost(spark, sf_dir, "full")


def ladder_read_cost_header(spark, sf_dir):
    return _cost(spark, sf_dir, "header")


def ladder_read_cost_slot(spark, sf_dir):
    return _cost(spark, sf_dir, "slot")


def ladder_read_cost_shared(spark, sf_dir):
    st = _store(spark, sf_dir)
    return ladder.shared_cells(st, spans(spark, st.n))


def ladder_read_capped(spark, sf_dir):
    st = _store(spark, sf_dir, "deep3")
    out = None
    for cap in (0, 1, 2):
        one = st.state.agg(F.count("*").alias("blocks"), F.sum((F.coalesce("home", F.lit(9)) > cap).cast("long")).alias("lost"), F.sum(ladder.full_cost(st.schedule, F.least(F.coalesce("home", F.lit(9)), F.lit(cap)))).alias("probes")).select(F.lit(cap).alias("cap"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def ladder_update_state(spark, sf_dir):
    blocks, law, s, n = _blocks(spark, sf_dir, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    return ladder.update_state(st, edits(blocks, n // s.b0, s.b0)).select("blk", "body", "settled", F.coalesce("home", F.lit(-1)).alias("home"))


def ladder_update_cost(spark, sf_dir):
    blocks, law, s, n = _blocks(spark, sf_dir, "demo3")
    st = ladder.encode(blocks, law, s, n, False)
    return ladder.update_costs(st, edits(blocks, n // s.b0, s.b0))


def ladder_update_cases(spark, sf_dir):
    return ladder_update_cost(spark, sf_dir).groupBy("case").agg(F.count("*").alias("edits"), F.sum(F.col("bits_read") + F.col("bits_written")).alias("bits"))


def ladder_cost_rollup(spark, sf_dir):
    """Mean-free cost report by case and home, with totals."""
    return ladder_update_cost(spark, sf_dir).groupBy("case", "old_home").count().rollup("case", "old_home").agg(F.sum("count").alias("edits")).select(F.coalesce("case", F.lit("all")).alias("case"), F.coalesce("old_home", F.lit(-9)).alias("old_home"), "edits")


def top_cost_blocks(spark, sf_dir):
    st = _store(spark, sf_dir)
    return st.state.select("blk", ladder.full_cost(st.schedule, F.col("home")).alias("probes")).orderBy(F.desc("probes"), "blk").limit(20)


def span_curve(spark, sf_dir):
    """Sum and greatest probes over all block-aligned starts, for spans of 1, 2, 4 ... blocks, by sums over stretches of blocks.

    A stretch holds ``STRETCH`` starts and the blocks that their spans reach beyond it, so no window sees the whole table.
    """
    st = _saved_store(spark, sf_dir)
    s, units, most = st.schedule, max(st.n // st.schedule.b0, 1), 32
    costs = st.table("blocks").select("blk", ladder.full_cost(s, F.col("home")).alias("c"))
    own = F.floor(F.col("blk") / STRETCH)
    dealt = costs.select("*", F.explode(F.array_distinct(F.array(own, F.floor(F.greatest(F.col("blk") - most + 1, F.lit(0)) / STRETCH)))).alias("stretch"))
    per = None
    for m in (1 << i for i in range(6)):
        ahead = Window.partitionBy("stretch").orderBy("blk").rowsBetween(0, m - 1)
        one = dealt.select(F.lit(m).cast("long").alias("m"), F.col("blk").alias("first"), "stretch", F.sum("c").over(ahead).alias("c")).where((F.floor(F.col("first") / STRETCH) == F.col("stretch")) & (F.col("first") + m <= units))
        per = one if per is None else per.unionByName(one)
    return per.groupBy((F.col("m") * s.b0).alias("span")).agg(F.count("*").alias("starts"), F.sum("c").alias("sum_probes"), F.max("c").alias("max_probes"))


def eps_curve(spark, sf_dir):
    """Settled blocks and probe sums for tolerances 1/2, 3/8, 1/4 (level 0 only)."""
    placed, law, n = positions(spark, sf_dir, "li_small_qty")
    out = None
    for num, den in ((1, 2), (3, 8), (1, 4)):
        blocks = cut_blocks(placed, n, 512)
        one = blocks.agg(F.count("*").alias("blocks"), F.sum(settled(F.col("body"), law, num, den).cast("long")).alias("settled")).select(F.lit(num * 8 // den).alias("eps_eighths"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def n_curve(spark, sf_dir):
    """Home profile on prefixes of the sequence: probes per block stay level as n grows."""
    placed, law, n = positions(spark, sf_dir, "li_small_qty")
    out = None
    for part in (4, 2, 1):
        m = n // part
        s = ladder_schedule(law, 128, 1, 2, [8, 16], m)
        st = ladder.encode(cut_blocks(placed.where(F.col("pos") < m), m, 128, 128), law, s, m, False)
        one = st.state.agg(F.count("*").alias("blocks"), F.sum((F.col("home") == 0).cast("long")).alias("home0"), F.sum((F.col("home") == 1).cast("long")).alias("home1")).select(F.lit(m).cast("long").alias("n"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def settled_mass_vs_exact(spark, sf_dir):
    """Observed settled share against the exact binomial probability."""
    blocks, law, s, _ = _blocks(spark, sf_dir, "demo3")
    low, high = TypicalSet(list(law.counts), s.num, s.den, s.b0).bounds[1]
    from math import comb

    p = law.counts[1] / law.total
    exact = sum(comb(s.b0, w) * p**w * (1 - p) ** (s.b0 - w) for w in range(low, high + 1))
    got = blocks.where(F.col("n_sym") == s.b0).agg(F.count("*").alias("blocks"), F.sum(settled(F.col("body"), law, s.num, s.den).cast("long")).alias("settled"))
    return got.select("blocks", "settled", F.lit(low).cast("long").alias("low"), F.lit(high).cast("long").alias("high"), F.lit(round(exact, 6)).alias("exact"))


# universal ladder, escape


def lz78_length(spark, sf_dir):
    blocks, law, _, _ = _blocks(spark, sf_dir, "flag3", b0=64)
    return blocks.select("blk", baselines.lz_length(law.k)(F.col("body")).alias("bits"))


def lz_settled(spark, sf_dir):
    """Blocks whose LZ code fits the universal preset's words, which are narrower than raw blocks."""
    return _store(spark, sf_dir, "universal").state.select("blk", "settled")


def universal_ladder_profile(spark, sf_dir):
    """Blocks and symbols by home level (-1: none) of the universal ladder."""
    st = _saved_store(spark, sf_dir, "universal")
    return st.table("blocks").groupBy(F.coalesce("home", F.lit(-1)).alias("home")).agg(F.count("*").alias("blocks"), F.sum("n_sym").alias("symbols"))


def universal_read_spans(spark, sf_dir):
    """Spans from the saved universal store, with the probes that whole cells cost."""
    st = _saved_store(spark, sf_dir, "universal")
    return ladder_store.read_spans(st, spans(spark, st.n)).select("req_id", "start", "len", F.when(~F.col("failed"), F.col("value")).alias("value"), "home_max", "probes_full")


def universal_update_state(spark, sf_dir):
    """Blocks read back after whole-block edits of a saved universal store; a block with no home is its raw escape."""
    blocks, law, s, n = _blocks(spark, sf_dir, "universal")
    st = ladder_store.save(ladder.encode(blocks, law, s, n), fresh_folder(spark, "edited"))
    ladder_store.update(st, edits(blocks, n // s.b0, s.b0))
    return ladder_store.decoded(st, st.table("blocks")).select("blk", F.coalesce("body", "raw").alias("body"), "settled", F.coalesce("home", F.lit(-1)).alias("home"))


def universal_update_cost(spark, sf_dir):
    """Bits that single edits read and write, each against the stored state."""
    blocks, law, s, n = _blocks(spark, sf_dir, "universal")
    return ladder.update_costs(ladder.encode(blocks, law, s, n), edits(blocks, n // s.b0, s.b0)).select("edit_id", "blk", "case", "old_home", "new_home", "bits_read", "bits_written")


def escape_rate(spark, sf_dir):
    """Zero-error wrapper per document over the class alphabet: flag 0 and flat words, or flag 1 and raw digits."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", class_text(F.col("text")).alias("t"))
    counts = docs.agg(*[F.sum(symbol_count(F.col("t"), str(i))).alias(f"c{i}") for i in range(4)]).first()
    law = Law(("0", "1", "2", "3"), tuple(int(c or 0) for c in counts))
    blocks = cut_text(docs, "doc_id", F.col("t"), 256)
    seq = blocks.groupBy("seq_id").agg(F.sum("n_sym").alias("n"), F.bool_and(settled(F.col("body"), law, 1, 2)).alias("fits"), F.count("*").alias("blocks"))
    s = ladder_schedule(law, 256, 1, 2, [])
    return seq.select(F.col("seq_id").alias("doc_id"), "n", "fits", (F.lit(1) + F.when(F.col("fits"), F.col("blocks") * s.k0_nominal).otherwise(F.col("n") * 2)).alias("bits"))


def order_k_entropy(spark, sf_dir):
    """Empirical entropies of order 0, 1 and 2 over the class alphabet of all documents."""
    docs = read_table(spark, sf_dir, "documents").select(class_text(F.col("text")).alias("t"))
    out = None
    for k in (0, 1, 2):
        per_text = docs.select(F.posexplode(baselines.gram_counts(4, k + 1)(F.col("t"))).alias("g", "n"))
        grams = per_text.groupBy("g").agg(F.sum("n").alias("n")).where("n > 0")
        h = grams.withColumn("m", F.sum("n").over(Window.partitionBy(F.floor(F.col("g") / 4))))
        one = h.agg(F.round(-F.sum(F.col("n") * F.log2(F.col("n") / F.col("m"))) / F.sum("n"), 6).alias("entropy"), F.sum("n").alias("grams")).select(F.lit(k).alias("k"), "*")
        out = one if out is None else out.unionByName(one)
    return out


# ranked codec


def _ranked(spark, sf_dir):
    placed, law, n = positions(spark, sf_dir, "li_small_qty")
    p = RANKED_DEMO
    s = ranked_schedule(law, p["b0"], p["b1"], p["num"], p["den"], p["open_num"], p["open_den"])
    return ranked.cut_subblocks(placed, n, s), law, s, n


def ranked_flags(spark, sf_dir):
    subs, law, s, _ = _ranked(spark, sf_dir)
    return ranked.words(subs, law, s).select("blk", "sub", "open")


def _ranked_store(spark, sf_dir):
    placed, law, n = positions(spark, sf_dir, "li_small_qty")
    p = RANKED_DEMO
    return ranked.store_of(placed, n, law, ranked_schedule(law, p["b0"], p["b1"], p["num"], p["den"], p["open_num"], p["open_den"]))


def ranked_lengths(spark, sf_dir):
    subs, law, s, _ = _ranked(spark, sf_dir)
    return ranked.encode(subs, law, s).withColumn("flags", F.col("flags")[0])


def ranked_offsets(spark, sf_dir):
    subs, law, s, _ = _ranked(spark, sf_dir)
    return ranked.words(subs, law, s).select("blk", "sub", "len", "start")


def ranked_rank_select(spark, sf_dir):
    subs, law, s, _ = _ranked(spark, sf_dir)
    blocks = ranked.encode(subs, law, s)
    return ranked.locate(blocks, blocks.select("blk", F.explode(F.sequence(F.lit(0), F.lit(s.subs - 1))).alias("sub")), s).select("blk", "sub", "rank_before", "open", "payload_start")


def ranked_read_spans(spark, sf_dir):
    """Spans of the whole sequence, tail included, from the stored words."""
    store = _ranked_store(spark, sf_dir)
    return ranked.answer(store, spans(spark, store.n)).select("req_id", "start", "len", "value", "probes")


def ranked_select(spark, sf_dir):
    """Where each block's k-th open sub-block lies."""
    subs, law, s, _ = _ranked(spark, sf_dir)
    asked = ranked.encode(subs, law, s).select("blk", "flags", F.explode(F.sequence(F.lit(1), F.lit(s.subs))).alias("k"))
    return asked.select("blk", "k", ranked.select(F.col("flags"), s, F.col("k")).alias("sub")).where("sub IS NOT NULL")


def ranked_update_state(spark, sf_dir):
    """Every block after edits of sub-blocks, decoded from the updated words.

    The store is written first: edits, touched blocks, kept blocks and decoder all read it, and would each cut the source anew.
    """
    store = _ranked_store(spark, sf_dir)
    store = replace(store, blocks=written(store.blocks, "ranked"), tail=written(store.tail, "tail"))
    s, units = store.schedule, store.n // store.schedule.b0 * store.schedule.subs
    k = spark.range(N_EDITS).select(F.col("id").alias("edit_id"), ((F.col("id") * 7919 + 5) % units).alias("cell"), ((F.col("id") * 6007 + 11) % units).alias("src"))
    at = lambda c: [F.floor(F.col(c) / s.subs).alias("blk"), (F.col(c) % s.subs).cast("int").alias("sub")]
    asked = ranked.bodies(store, k.select("edit_id", "cell", *at("src"))).where("body IS NOT NULL").select("edit_id", *at("cell"), "body")
    return ranked.decode(ranked.update_store(store, asked)).select("blk", "body", "failed")


def ranked_read_cost(spark, sf_dir):
    """Worst and summed single reads over every sub-block."""
    subs, law, s, _ = _ranked(spark, sf_dir)
    blocks = ranked.encode(subs, law, s)
    return ranked.locate(blocks, subs.select("blk", "sub"), s).groupBy("open").agg(F.count("*").alias("reads"), F.max("probes").alias("worst"), F.sum("probes").alias("bits"))


def ranked_update_cost(spark, sf_dir):
    subs, law, s, n = _ranked(spark, sf_dir)
    units = n // s.b0 * s.subs
    k = spark.range(N_EDITS).select(F.col("id").alias("edit_id"), ((F.col("id") * 7919 + 5) % units).alias("cell"), ((F.col("id") * 6007 + 11) % units).alias("src"))
    cells = subs.withColumn("src", F.col("blk") * s.subs + F.col("sub"))
    asked = k.join(cells.select("src", "body"), "src").select("edit_id", F.floor(F.col("cell") / s.subs).alias("blk"), (F.col("cell") % s.subs).cast("int").alias("sub"), "body")
    return ranked.update_costs(subs, asked, law, s)


def ranked_errors(spark, sf_dir):
    subs, law, s, _ = _ranked(spark, sf_dir)
    return ranked.encode(subs, law, s).agg(F.count("*").alias("blocks"), F.sum(F.col("failed").cast("long")).alias("failed"), F.sum("used_bits").alias("used_bits"), F.sum("reserved_bits").alias("reserved_bits"))


# baselines


def flat_profile(spark, sf_dir):
    blocks, law, s, _ = _blocks(spark, sf_dir, "demo3")
    return baselines.flat(blocks, law, s).groupBy("failed").agg(F.count("*").alias("blocks"), F.sum("bits").alias("bits"))


def flat_read_update_cost(spark, sf_dir):
    _, _, s, n = _blocks(spark, sf_dir, "demo3")
    return ladder.touched(spans(spark, n), n, s.b0).groupBy("req_id").agg((F.count("*") * s.k0).alias("read_bits"), (F.count("*") * 2 * s.k0).alias("update_bits"))


def whole_lz_cost(spark, sf_dir):
    return baselines.whole_lz(read_table(spark, sf_dir, "documents"), "doc_id", "text")


def block_lz_cost(spark, sf_dir):
    text = cut_text(read_table(spark, sf_dir, "documents"), "doc_id", F.col("text"), 512)
    return text.select("seq_id", "blk", "n_sym", baselines.text_lz_length()(F.col("body")).alias("bits"))


def syndrome_store(spark, sf_dir):
    blocks, *_ = _blocks(spark, sf_dir, "demo3")
    return baselines.syndromes(blocks, 128, 60)


def syndrome_update_bits(spark, sf_dir):
    """Bits of the syndromes that edits of one symbol flip, one edit a block, by the edited column."""
    blocks, *_ = _blocks(spark, sf_dir, "demo3")
    at = (F.col("blk") * 7919 + 5) % 128
    flipped = F.translate(F.substring("body", (at + 1).cast("int"), F.lit(1)), "01", "10")
    edited = blocks.withColumn("body", F.overlay("body", flipped, (at + 1).cast("int")))
    was, now = baselines.syndromes(blocks, 128, 60), baselines.syndromes(edited, 128, 60).withColumnRenamed("syndrome", "edited")
    bits = F.bit_count(F.col("syndrome").bitwiseXOR(F.col("edited"))).cast("long")
    return was.join(now, "blk").groupBy(at.alias("column"), bits.alias("bits")).agg(F.count("*").alias("edits"))


def spill_probe_levels(spark, sf_dir):
    blocks, law, _, _ = _blocks(spark, sf_dir, "demo3")
    return baselines.spill(blocks, law, [80, 120, 160], 8)


def addressed_overhead(spark, sf_dir):
    blocks, law, _, n = _blocks(spark, sf_dir, "demo3")
    words = baselines.addressed(blocks, law, n)
    return words.agg(F.count("*").alias("words"), F.sum("len").alias("bits"), F.max(F.col("address") + F.col("len")).alias("end"))


def raw_cost(spark, sf_dir):
    _, law, _, n = _blocks(spark, sf_dir, "flag3")
    w = baselines.raw_bits(law)
    return spans(spark, n).select("req_id", (F.col("len") * w).alias("read_bits"))


def codec_scoreboard(spark, sf_dir):
    """Bits stored, bits of all single reads and failures of ladder, flat and raw storage."""
    st = _store(spark, sf_dir)
    s = st.schedule
    n = F.col("n_sym").cast("long")
    ladder_row = st.state.agg(F.sum(n * ladder.full_cost(s, F.col("home"))).alias("read_bits"), F.sum(F.col("home").isNull().cast("long")).alias("failed_blocks")).select(F.lit("ladder").alias("codec"), "*")
    flat_row = st.state.agg(F.sum(n * s.k0).alias("read_bits"), F.sum((~F.col("settled")).cast("long")).alias("failed_blocks")).select(F.lit("flat").alias("codec"), "*")
    raw_row = st.state.agg(F.sum(n * s.raw_bits).alias("read_bits"), F.lit(0).cast("long").alias("failed_blocks")).select(F.lit("raw").alias("codec"), "*")
    return ladder_row.unionByName(flat_row).unionByName(raw_row)


# fragments of texts


def gene_fetch(spark, sf_dir):
    """Fragments of 64 characters of every document, through block-wise storage."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text", F.length("text").alias("n")).where("n >= 64")
    want = docs.select(F.col("doc_id").alias("seq_id"), "n", ((F.col("doc_id") * 7919 + 13) % (F.col("n") - 63)).alias("start"))
    blocks = cut_text(docs, "doc_id", F.col("text"), 512)
    last = F.greatest(F.floor(F.col("n") / 512), F.lit(1)) - 1
    cells = want.select("seq_id", "start", F.explode(F.sequence(F.least(F.floor(F.col("start") / 512), last), F.least(F.floor((F.col("start") + 63) / 512), last))).alias("blk"))
    got = cells.join(blocks, ["seq_id", "blk"])
    low = F.greatest(F.col("start") - F.col("blk") * 512, F.lit(0))
    high = F.least(F.col("start") + 64 - F.col("blk") * 512, F.col("n_sym"))
    piece = F.substring("body", (low + 1).cast("int"), (high - low).cast("int"))
    return got.groupBy("seq_id", "start").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("blk", piece.alias("p")))), lambda x: x["p"]), "").alias("value")).select(F.col("seq_id").alias("doc_id"), "start", "value")


def page_fetch(spark, sf_dir):
    pages = read_table(spark, sf_dir, "pages").select("page_id", "html")
    return pages.select("page_id", F.substring("html", ((F.col("page_id") * 7919) % F.greatest(F.length("html") - 50, F.lit(1)) + 1).cast("int"), F.lit(50)).alias("value"))


def doc_splice(spark, sf_dir):
    docs = read_table(spark, sf_dir, "documents").where("length(text) >= 40").select("doc_id", "text")
    at = ((F.col("doc_id") * 7919) % (F.length("text") - 19)).cast("int")
    return docs.select("doc_id", F.md5(F.overlay("text", F.lit("." * 20), at + 1, F.lit(20)).cast("binary")).alias("digest"))


def role_stress(spark, sf_dir):
    """Typicality of an alternating sequence, far from independent symbols."""
    placed, law, n = _conversation(spark, sf_dir)
    blocks = cut_blocks(placed, n, 16)
    return blocks.select("blk", settled(F.col("body"), law, 1, 2).alias("settled"))


def _conversation(spark, sf_dir):
    placed, law, n = positions(spark, sf_dir, "cv_role")
    return placed, law, n


# edits over time


def edit_windows_tumbling(spark, sf_dir):
    ev = read_table(spark, sf_dir, "events")
    return ev.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("edits"), F.count_distinct("user_id").alias("users")).select(F.col("w.start").alias("start"), "edits", "users")


def edit_windows_sliding(spark, sf_dir):
    ev = read_table(spark, sf_dir, "events")
    return ev.groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("edits")).select(F.col("w.start").alias("start"), "edits")


def edit_windows_session(spark, sf_dir):
    ev = read_table(spark, sf_dir, "events")
    return ev.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("edits")).select("user_id", F.col("w.start").alias("start"), "edits")


def edit_asof(spark, sf_dir):
    """For every purchase the user's latest earlier event of any kind."""
    ev = read_table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    return ev.select("event_id", "event_type", F.last("event_id").over(w).alias("before")).where("event_type = 'purchase'").select("event_id", F.coalesce("before", F.lit(-1)).alias("before"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        alphabet_law, source_entropy, dyadic_report, dense_positions, block_cut, block_cut_text, block_histogram, block_settled, typical_set_size, type_index_b16, type_unindex_b16,
        ladder_level0, ladder_level1, ladder_level2, ladder_home_profile, ladder_trace, ladder_failures, ladder_bit_budget, ladder_rate_vs_bound, ladder_roundtrip, ladder_read_symbols, ladder_read_spans,
        ladder_read_cost_full, ladder_read_cost_header, ladder_read_cost_slot, ladder_read_cost_shared, ladder_read_capped, ladder_update_state, stored_update_state, ladder_update_cost, ladder_update_cases, ladder_cost_rollup, top_cost_blocks,
        span_curve, eps_curve, n_curve, settled_mass_vs_exact, lz78_length, lz_settled, universal_ladder_profile, universal_read_spans, universal_update_state, universal_update_cost, escape_rate, order_k_entropy,
        ranked_flags, ranked_lengths, ranked_offsets, ranked_rank_select, ranked_read_spans, ranked_select, ranked_update_state, ranked_read_cost, ranked_update_cost, ranked_errors,
        flat_profile, flat_read_update_cost, whole_lz_cost, block_lz_cost, syndrome_store, syndrome_update_bits, spill_probe_levels, addressed_overhead, raw_cost, codec_scoreboard,
        gene_fetch, page_fetch, doc_splice, role_stress, edit_windows_tumbling, edit_windows_sliding, edit_windows_session, edit_asof,
    )
}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode the skewed binary source and read a grid of spans from the store."""
    st = _saved_store(spark, sf_dir)
    return ladder_store.read_spans(st, spans(spark, st.n)).select("req_id", "start", "len", "value", "home_max", "probes_full", "probes_slot")
