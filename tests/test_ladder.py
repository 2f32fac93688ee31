"""Worked examples, golden counts, round trips and the re-encode invariant of the ladder and ranked codecs."""

import pytest
from pyspark.sql import functions as F

from rungwise import queries as q
from rungwise.operators import baselines, codeword, ladder, ranked
from rungwise.operators.blocks import cut_blocks, cut_text
from rungwise.plans import bounds
from rungwise.plans.schedules import PRESETS, Law, ladder_schedule, paper_levels, ranked_schedule, unit_symbols
from rungwise.sources.catalog import positions

SETTLED, OPEN, OPEN2 = "1000000001", "1111111111", "1111111110"  # 2 of 10 expected, tolerance 1/2
LAW = Law(("a", "b"), (8, 2))


def example(spark, open_blocks=(3, 4, 13, 14)):
    """16 blocks, fan-outs 2 and 4, one open child allowed in both; blocks count from 1 in the example."""
    rows = [(0, i, 10, OPEN if i + 1 in open_blocks else SETTLED) for i in range(16)]
    blocks = spark.createDataFrame(rows, "chunk long, blk long, n_sym int, body string")
    s = ladder_schedule(LAW, 10, 1, 1, [2, 4], 160)
    s = type(s)(**{**s.__dict__, "num": 1, "den": 2})
    return ladder.encode(blocks, LAW, s, 160)


def test_example_groups_reads_and_edits(spark):
    st = example(spark)
    k0, k1, k2 = st.schedule.widths
    assert sorted(r.grp + 1 for r in st.groups[0].where("not settled").collect()) == [2, 7]
    assert st.groups[1].where("not settled").count() == 0
    homes = {r.blk + 1: r.home for r in st.state.collect()}
    assert homes[2] == 0 and homes[3] == 2 and homes[13] == 2
    costs = {r.blk + 1: r.c for r in st.state.select("blk", ladder.full_cost(st.schedule, F.col("home")).alias("c")).collect()}
    assert costs[2] == k0 and costs[3] == k0 + k1 + k2
    edits = spark.createDataFrame([(0, 4, "0110000000"), (1, 4, OPEN2)], "edit_id long, blk long, body string")
    got = {r.edit_id: r for r in ladder.update_costs(st, edits).collect()}
    assert (got[0].case, got[0].bits_read, got[0].bits_written) == ("SS", k0, k0)
    assert (got[1].case, got[1].bits_read, got[1].bits_written) == ("SO", k0 + k1, k0 + k1)


def test_round_trip_failures_and_spans(spark):
    st = example(spark, open_blocks=(1, 2, 3, 4, 5, 6))
    back = {r.blk: r for r in ladder.decode(st).collect()}
    assert [b for b, r in back.items() if r.failed] == [0, 1, 2, 3, 4, 5]
    assert all(r.body == SETTLED for r in back.values() if not r.failed)
    spans = spark.createDataFrame([(0, 60, 0), (1, 65, 12), (2, 155, 20), (3, 0, 3)], "req_id long, start long, len long")
    got = {r.req_id: r for r in ladder.read_spans(st, spans).collect()}
    text = SETTLED * 16
    assert got[0].value == "" and got[0].probes_full == 0 and not got[0].failed
    assert got[1].value == text[65:77] and not got[1].failed
    assert got[2].value == text[155:160] and got[2].failed and got[3].failed
    assert all(r.probes_slot <= r.probes_header <= r.probes_full for r in got.values())


@pytest.mark.parametrize(("preset", "expected"), [("demo3", {0: 450, 1: 18}), ("deep3", {0: 755, 1: 105, 2: 7, -1: 70}), ("calm", {0: 226, 1: 8}), ("flag3", {0: 1631, 1: 208, 2: 26, -1: 10})])
def test_golden_home_levels(spark, preset, expected):
    rows = q._store(spark, "/root/testdata/sf0.01", preset).state.groupBy(F.coalesce("home", F.lit(-1)).alias("h")).count().collect()
    assert {r.h: r["count"] for r in rows} == expected


def test_cell_widths():
    law = Law(("0", "1"), (539853, 60147))
    assert ladder_schedule(law, 128, 1, 2, [8, 16]).widths == [125, 520, 4112]
    assert ladder_schedule(law, 64, 1, 2, [8, 16]).widths == [63, 264, 2064]
    assert unit_symbols(600, 1) == 1_440_000 and paper_levels(10**14, 600) == 2


def test_update_equals_reencoding(spark, sf):
    blocks, law, s, n = q._blocks(spark, sf, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    edits = q.edits(blocks, n // s.b0, s.b0, 60)
    after = ladder.update_state(st, edits)
    again = ladder.encode(after.join(blocks.select("chunk", "blk", "n_sym"), "blk").select("chunk", "blk", "n_sym", "body"), law, s, n, False).state
    key = lambda df: sorted((r.blk, r.body, r.settled, r.home) for r in df.select("blk", "body", "settled", "home").collect())
    assert key(after) == key(again)


def test_rates_stay_below_their_bounds(spark, sf):
    for preset in ("demo3", "calm"):
        p = PRESETS[preset]
        _, law, _ = positions(spark, sf, p["source"])
        s = ladder_schedule(law, p["b0"], p["num"], p["den"], p["fanouts"])
        assert bounds.nominal_rate(s) <= bounds.rate_bound(law, p["num"] / p["den"])


def test_short_and_empty_sequences(spark, sf):
    for name in ("na_region", "su_nation"):
        placed, law, n = positions(spark, sf, name)
        s = ladder_schedule(law, 64, 1, 2, [8, 16], n)
        assert s.levels == () and cut_blocks(placed, n, 64).collect()[0].n_sym == n
    texts = spark.createDataFrame([(1, ""), (2, None), (3, "ab"), (4, "é" * 25)], "doc_id long, text string")
    assert sorted((r.seq_id, r.blk, r.n_sym) for r in cut_text(texts, "doc_id", F.col("text"), 10).collect()) == [(3, 0, 2), (4, 0, 10), (4, 1, 15)]


def test_ranked_example(spark):
    """7 sub-blocks, 4, 5 and 7 open: sub-block 5 lies behind three settled words and one raw word."""
    bodies = [OPEN if i in (4, 5, 7) else SETTLED for i in range(1, 8)]
    placed = spark.createDataFrame([(i, c) for i, c in enumerate("".join(bodies))], "pos long, ch string")
    s = ranked_schedule(LAW, 70, 10, 1, 2, 1, 2)
    subs = ranked.cut_subblocks(placed, 70, s)
    found = ranked.locate(ranked.encode(subs, LAW, s), subs.select("blk", "sub"), s)
    five = found.where("sub = 4").first()
    assert (five.rank_before, five.open, five.payload_start) == (1, 1, 3 * s.word_bits + s.raw_bits)


def test_encode_plan_has_one_exchange_for_nested_levels(spark, sf):
    blocks, law, s, n = q._blocks(spark, sf, "demo3")
    level0 = ladder.with_groups(blocks.withColumn("settled", F.col("body").contains("1")), s, n)
    _, groups = ladder.climb(level0, s)
    plan = groups[0]._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(chunk") <= 1 and "CartesianProduct" not in plan


def test_syndromes_decode_light_patterns():
    for at in ((), (5,), (1, 40)):
        rows = baselines.syndrome_rows(64, 40)
        value = 0
        for i in at:
            for r in rows[i]:
                value ^= 1 << r
        found = baselines.decode_syndrome(value, 64, 40, 2)
        assert found is not None and sum(found) <= len(at)


@pytest.mark.parametrize("tails", [range(128, 176), range(176, 216), range(216, 256)])
def test_every_tail_length_decodes_to_itself(spark, tails):
    """Last blocks of 128 to 255 symbols, all settled: one width for each length, on both sides."""
    import random

    law = Law(("0", "1"), (539853, 60147))
    s = ladder_schedule(law, 128, 1, 2, [8, 16])
    rnd, rows = random.Random(3), []
    for n in tails:
        for part in (0.06, 0.08, 0.1, 0.12, 0.14):
            body = ["1"] * round(part * n) + ["0"] * (n - round(part * n))
            rnd.shuffle(body)
            rows.append((0, len(rows), n, "".join(body)))
    blocks = spark.createDataFrame(rows, "chunk long, blk long, n_sym int, body string")
    st = ladder.encode(blocks, law, s, 128 * len(rows))
    assert st.blocks0.where("not settled").isEmpty()
    back = {r.blk: r.body for r in ladder.decode(st).collect()}
    assert all(back[r[1]] == r[3] for r in rows)
    wide = {r.cell: r.bits for r in codeword.cells(st).where("level = 0").collect()}
    assert all(int(wide[r[1]], 2) and len(wide[r[1]]) >= s.k0 for r in rows)


def test_dense_positions_over_many_buckets(spark, monkeypatch):
    import random

    from rungwise.sources import catalog

    monkeypatch.setattr(catalog, "ROWS_PER_BUCKET", 40)
    monkeypatch.setattr(catalog, "COARSE", 4)
    rnd = random.Random(4)
    rows = [(rnd.choice([None, 1, 2, 3, 10**15]), i) for i in range(1000)]
    got = {(r.k, r.j): r.pos for r in catalog.index_rows(spark.createDataFrame(rows, "k long, j long"), ("k", "j")).collect()}
    assert got == {r: i for i, r in enumerate(sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1])))}
    assert catalog.index_rows(spark.createDataFrame(rows, "k long, j long").where("false"), ("k",)).isEmpty()


@pytest.mark.parametrize(("n", "b0", "b1"), [(700, 70, 10), (1003, 200, 10), (4000, 1300, 10), (6, 70, 10)])
def test_ranked_words_alone_give_back_blocks_spans_and_edits(spark, n, b0, b1):
    """Round trip, span reads and edits against the text, with a tail, and with over 63 sub-blocks a block."""
    import random

    rnd = random.Random(n)
    text = "".join(rnd.choice("0000111" if i // 50 % 4 == 0 else "00001") for i in range(n))
    placed = spark.createDataFrame(list(enumerate(text)), "pos long, ch string")
    s = ranked_schedule(LAW, b0, b1, 1, 2, 3, 4)
    store = ranked.store_of(placed, n, LAW, s)
    back = {r.blk: r for r in ranked.decode(store).collect()}
    assert not any(r.failed for r in back.values()) and "".join(back[i].body for i in sorted(back)) == text
    asked = [(i, rnd.randrange(n), rnd.randrange(1, 90)) for i in range(40)] + [(99, 0, n)]
    got = {r.req_id: r.value for r in ranked.answer(store, spark.createDataFrame(asked, "req_id long, start long, len long")).collect()}
    assert all(got[i] == text[a : a + k] for i, a, k in asked)
    if n >= b0:
        cells = [rnd.randrange(n // b0 * b0 // b1) for _ in range(12)]
        made = [(i, c // (b0 // b1), c % (b0 // b1), "".join(rnd.choice("00001") for _ in range(b1))) for i, c in enumerate(cells)]
        new = text
        for _, blk, sub, body in made:
            new = new[: blk * b0 + sub * b1] + body + new[blk * b0 + sub * b1 + b1 :]
        after = ranked.update_store(store, spark.createDataFrame(made, "edit_id long, blk long, sub int, body string"))
        assert "".join(r.body for r in sorted(ranked.decode(after).collect())) == new
        again = ranked.store_of(spark.createDataFrame(list(enumerate(new)), "pos long, ch string"), n, LAW, s)
        assert sorted(map(str, after.blocks.collect())) == sorted(map(str, again.blocks.collect()))
        flags = store.blocks.select("blk", "flags").collect()
        assert sum(bin(f).count("1") for r in flags for f in r.flags) == sum(not 1 <= text[i : i + b1].count("1") <= 3 for i in range(0, n // b0 * b0, b1))


def failing_store(spark):
    """Block 0 is open but for its last sub-blocks, whose places lie behind its payload; block 1 is settled."""
    text = OPEN * 5 + SETTLED * 2 + SETTLED * 7
    placed = spark.createDataFrame(list(enumerate(text)), "pos long, ch string")
    return ranked.store_of(placed, 140, LAW, ranked_schedule(LAW, 70, 10, 1, 2, 0, 2)), text


def test_ranked_failed_blocks_are_marked_and_the_others_read(spark):
    store, text = failing_store(spark)
    got = {r.blk: r for r in ranked.decode(store).collect()}
    assert got[0].failed and got[0].body is None and not got[1].failed and got[1].body == text[70:]
    asked = spark.createDataFrame([(0, 60, 20), (1, 75, 9)], "req_id long, start long, len long")
    assert {r.req_id: (r.value, r.failed) for r in ranked.answer(store, asked).collect()} == {0: (text[70:80], True), 1: (text[75:84], False)}


def test_ranked_updates_with_failed_blocks(spark):
    """A failed block stays failed; an edit may make another one fail."""
    store, text = failing_store(spark)
    edits = lambda rows: spark.createDataFrame(rows, "edit_id long, blk long, sub int, body string")
    got = {r.blk: r for r in ranked.decode(ranked.update_store(store, edits([(0, 0, 1, SETTLED), (1, 1, 2, SETTLED[::-1])]))).collect()}
    assert got[0].failed and got[0].body is None and got[1].body == text[70:90] + SETTLED[::-1] + text[100:]
    got = ranked.decode(ranked.update_store(store, edits([(i, 1, i, OPEN) for i in range(5)]))).collect()
    assert len(got) == 2 and all(r.failed and r.body is None for r in got)


def test_syndrome_bits_of_edits_count_every_block(spark, sf):
    got = q.syndrome_update_bits(spark, sf).collect()
    blocks = q.syndrome_store(spark, sf).collect()
    weight = [len(c) for c in baselines.syndrome_rows(128, 60)]
    assert sum(r.edits for r in got) == len(blocks) > 40 and all(r.bits == weight[r.column] for r in got)
    assert {r.column for r in got} == {(r.blk * 7919 + 5) % 128 for r in blocks}


def test_ranked_update_query_cuts_its_source_once(spark, sf):
    """What the updated store is made of comes from the written words, not from the table again and again."""
    files = q.ranked_update_state(spark, sf).inputFiles()
    assert files and not [f for f in files if "lineitem" in f or "/ordered-" in f]
