import random

from pyspark.sql import functions as F

from rungwise.operators import dense, ladder
from rungwise.operators.blocks import settled
from rungwise.queries import _blocks, edits


def test_words_of_open_children_round_trip():
    rng = random.Random(7)
    for b, m, size, base in ((1, 0, 4, 3), (6, 3, 2, 3), (8, 2, 64, 3), (17, 17, 1, 4), (40, 5, 30, 26)):
        header = list("1" * m + "0" * (b - m))
        rng.shuffle(header)
        payload = [rng.randrange(base) for _ in range(m * size)]
        sizes = {}
        for variant in dense.VARIANTS:
            word = dense.pack_open_children("".join(header), payload, base, variant)
            assert dense.unpack_open_children(word, b, len(payload), base, variant) == ("".join(header), payload)
            sizes[variant] = len(word)
        assert base & (base - 1) == 0 or m * size < 30 or sizes["radix"] < sizes["plain"]


def test_headers_hold_every_open_child_and_words_decode(spark, sf):
    blocks, law, s, n = _blocks(spark, sf, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    got = {(r.level, r.grp): r for r in dense.open_children(st).collect()}
    for i, groups in enumerate(st.groups, 1):
        for g in groups.where("settled").collect():
            assert got[i, g.grp].header.count("1") == g.open_count and len(got[i, g.grp].header) == g.n_child
    assert dense.dense_words(st).where("not same").isEmpty()


def test_sequential_costs_equal_edits_taken_one_by_one(spark, sf):
    """Brute force: after every edit all states are worked out anew."""
    blocks, law, s, n = _blocks(spark, sf, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    made = edits(blocks, n // s.b0, s.b0, 120).cache()
    asked = made.withColumn("ok", settled(F.col("body"), law, s.num, s.den)).orderBy("edit_id").collect()
    rows = st.state.select("blk", "g1", "g2", "settled").collect() if len(s.levels) > 1 else st.state.select("blk", "g1", F.lit(0).alias("g2"), "settled").collect()
    now, groups = {r.blk: r.settled for r in rows}, {r.blk: (r.g1, r.g2)[: len(s.levels)] for r in rows}

    def home(blk):
        if now[blk]:
            return 0
        state = dict(now)
        for i, level in enumerate(s.levels):
            children = {}
            for b, at in groups.items():
                children.setdefault(at[i], {})[b if i == 0 else at[i - 1]] = state[b if i == 0 else at[i - 1]]
            state = {g: sum(not x for x in c.values()) <= len(c) * level.num // level.den for g, c in children.items()}
            if state[groups[blk][i]]:
                return i + 1
        return -1

    want = {}
    for r in asked:
        old, was = home(r.blk), now[r.blk]
        now[r.blk] = r.ok
        want[r.edit_id] = ("OS"[was] + "OS"[r.ok], old, home(r.blk))
    got = {r.edit_id: (r.case, r.old_home, r.new_home) for r in ladder.update_costs(st, made, sequential=True).collect()}
    alone = {r.edit_id: (r.case, r.old_home, r.new_home) for r in ladder.update_costs(st, made).collect()}
    assert got == want and len(want) > len({r.blk for r in asked}) and got != alone
