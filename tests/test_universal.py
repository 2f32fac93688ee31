import random
from fractions import Fraction

import duckdb
import pytest
from pyspark.sql import functions as F

from rungwise import queries, storage_queries
from rungwise.operators import ladder
from rungwise.operators.blocks import cut_blocks
from rungwise.oracles import ORACLES
from rungwise.plans.schedules import Law, universal_schedule
from rungwise.sources import ladder_store

LAW = Law(("0", "1"), (9, 1))
NAMES = ("lz_settled", "lz_fixed_word", "universal_ladder_profile", "universal_roundtrip", "universal_read_spans", "universal_update_state", "universal_update_cost")


def _encoded(spark, text):
    s = universal_schedule(LAW, 64, Fraction(2, 5), 1, 2, [4, 8], len(text))
    rows = spark.createDataFrame([(i, c) for i, c in enumerate(text)], "pos long, ch string")
    return ladder.encode(cut_blocks(rows, len(text), 64, 32), LAW, s, len(text))


def _mixed(n, seed):
    """Calm blocks with a noisy stretch, so that blocks of every home occur."""
    rnd = random.Random(seed)
    return "".join("01"[rnd.random() < (0.5 if 640 <= i < 1600 else 0.06)] for i in range(n))


@pytest.mark.parametrize("name", NAMES)
def test_queries_match_their_sql(spark, sf, name):
    sf = sf.replace("0.001", "0.01")  # the SQL takes both upper levels to be there
    df = {**queries.QUERIES, **storage_queries.QUERIES}[name](spark, sf)
    cols = sorted(df.columns)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{sf}/lineitem.parquet')")
    want = con.execute("SELECT {} FROM ({})".format(", ".join(f'"{c}"' for c in cols), ORACLES[name])).fetchall()
    assert sorted(map(str, map(tuple, df.select(*cols).collect()))) == sorted(map(str, want))


@pytest.mark.parametrize("n", [64, 100, 4096, 4159, 4160])
def test_blocks_come_back_and_open_ones_climb(spark, tmp_path, n):
    text = _mixed(n, 3)
    st = ladder_store.save(_encoded(spark, text), str(tmp_path / "store"))
    st = ladder_store.load(spark, st.folder)
    rows = ladder_store.decoded(st, st.table("blocks")).orderBy("blk").collect()
    assert "".join(r.body if r.body is not None else r.raw for r in rows) == text
    if n > 4000:
        assert {0, 1, None} <= {r.home for r in rows} and all((r.body is None) == (r.home is None) for r in rows)
        assert all(8 * len(r.word) < r.n_sym + 8 for r in rows if r.settled)  # words are narrower than the raw block


def test_edits_change_the_store_as_encoding_anew_does(spark, tmp_path):
    text = _mixed(4159, 4)
    st = ladder_store.save(_encoded(spark, text), str(tmp_path / "store"))
    new = {3: "01" * 32, 12: "0" * 64, 40: _mixed(1600, 9)[900:964]}
    ladder_store.update(st, spark.createDataFrame([(i, b, t) for i, (b, t) in enumerate(new.items())], "edit_id long, blk long, body string"))
    for b, t in new.items():
        text = text[: 64 * b] + t + text[64 * b + 64 :]
    want = _encoded(spark, text).state.select("blk", "settled", "home")
    assert st.table("blocks").select("blk", "settled", "home").exceptAll(want).isEmpty()
    spans = spark.range(60).select(F.col("id").alias("req_id"), (F.col("id") * 67).alias("start"), F.lit(70).alias("len"))
    for r in ladder_store.read_spans(st, spans).collect():
        assert r.failed or r.value == text[r.start : r.start + 70]


def test_words_that_do_not_beat_raw_blocks_are_refused():
    with pytest.raises(ValueError):
        universal_schedule(Law(("0", "1"), (1, 1)), 64, Fraction(1, 10), 1, 2, [4])
