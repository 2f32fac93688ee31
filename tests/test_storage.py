import random

import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

from rungwise import storage_queries as storage
from rungwise.functions.sql import register, text_bits
from rungwise.operators.baselines import addressed
from rungwise.operators.escape import escaped_texts, prefix_free, unescaped_texts
from rungwise.operators.overlap import multiset_diff, overlapping, valid_at, versions
from rungwise.plans.schedules import Law, read_preamble, write_preamble
from rungwise.sources.ladder_source import LadderSource, save_blocks


def test_overlaps_against_all_pairs(spark):
    rnd = random.Random(5)
    spans = [(i, rnd.randrange(400), rnd.randrange(0, 90)) for i in range(30)]
    cells, at = [], 0
    for i in range(60):
        cells.append((i, at, size := rnd.randrange(0, 30)))
        at += size
    want = sorted((r, c, o) for r, s, n in spans for c, f, z in cells if (o := min(s + n, f + z) - max(s, f)) > 0)
    got = overlapping(spark.createDataFrame(spans, "req_id long, start long, len long"), spark.createDataFrame(cells, "cell long, first long, size long"), 16)
    assert sorted(map(tuple, got.collect())) == want


def test_version_at_a_time_against_a_scan(spark):
    rnd = random.Random(6)
    edits = [(i, rnd.randrange(4), rnd.randrange(50)) for i in range(40)]
    points = [(i, rnd.randrange(5), rnd.randrange(60)) for i in range(80)]
    want = sorted((p, b, max((a, e) for e, eb, a in edits if eb == b and a <= t)[1]) for p, b, t in points if any(eb == b and a <= t for _, eb, a in edits))
    p = spark.createDataFrame(points, "read_id long, blk long, t long")
    v = versions(spark.createDataFrame(edits, "edit_id long, blk long, at long"))
    assert sorted(map(tuple, valid_at(p, v, 7).collect())) == want
    assert valid_at(p.limit(0), v, 7).isEmpty()


def test_multiset_diff_counts_repeats(spark):
    a, b = (spark.createDataFrame([(x,) for x in s], "v string") for s in ("aabc", "abbd"))
    assert {r.side: r.rows for r in multiset_diff(a, b).collect()} == {"gone": 2, "come": 2, "kept": 2}


@pytest.mark.parametrize("words, clashes", [(["0", "10", "11"], 0), (["0", "01", "1", None, "1"], 1), ([], 0)])
def test_prefix_free(spark, words, clashes):
    r = prefix_free(spark.createDataFrame([(w,) for w in words], "word string")).first()
    assert (r.clashes, r.prefix_free) == (clashes, clashes == 0)


def test_escape_keeps_every_text(spark):
    rnd = random.Random(7)
    texts = {1: "0" * 700, 2: "".join(rnd.choice("0123") for _ in range(700)), 3: "3", 4: "", 5: None}
    stored = escaped_texts(spark.createDataFrame(list(texts.items()), "id long, t string"), "id", F.col("t"), 4, 128, 1, 2)
    got = {r.seq_id: (r.flag, r.text) for r in unescaped_texts(stored, 4).collect()}
    assert {k: v[1] for k, v in got.items()} == {k: v for k, v in texts.items() if v}
    assert got[1][0] == 0 and got[2][0] == 1


def test_preamble():
    for b0, k0 in ((1, 1), (128, 60), (64, 4096)):
        bits = write_preamble(b0, k0)
        assert read_preamble(bits + "0101") == (b0, k0, len(bits))


def test_sql_functions(spark):
    register(spark)
    assert spark.sql("SELECT lz78_bits('abababab') AS a, lz78_bits(NULL) AS b").first() == (text_bits("abababab"), None)
    assert [r.bit for r in spark.sql("SELECT * FROM bits_of(X'A1')").orderBy("pos").collect()] == [1, 0, 1, 0, 0, 0, 0, 1]
    assert [tuple(r) for r in spark.sql("SELECT * FROM span_blocks(6, 9, 14, 4)").collect()] == [(1, 2, 2), (2, 0, 6)]
    assert spark.sql("SELECT block_entropy(v) AS h FROM VALUES ('a'), ('b'), ('a'), ('b') AS t(v)").first().h == 1.0


def test_ladder_source_prunes_and_agrees(spark, tmp_path):
    rows = pd.DataFrame({"blk": range(50), "n_sym": 4, "settled": [i % 3 == 0 for i in range(50)], "body": [f"{i:04}" for i in range(50)]})
    df = spark.createDataFrame(rows).selectExpr("blk", "cast(n_sym AS int) AS n_sym", "settled", "body")
    save_blocks(df, str(tmp_path / "store"))
    spark.dataSource.register(LadderSource)
    load = lambda **bounds: spark.read.format("ladder").options(**bounds).load(str(tmp_path / "store"))
    assert sorted(r.blk for r in load(low=10, high=13).where("settled").collect()) == [12]
    assert load().exceptAll(df).isEmpty() and load().count() == 50
    assert [r.body for r in load(low=7).where("blk = 7").collect()] == ["0007"]
    assert load(low=99).isEmpty()


@pytest.mark.parametrize("name", sorted(storage.ORACLES))
def test_queries_match_their_sql(spark, sf, name):
    if name.startswith("ladder"):
        sf = sf.replace("0.001", "0.01")  # the SQL takes both upper levels to be there
    df = storage.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    con = duckdb.connect()
    for t in ("lineitem", "events", "documents"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    want = con.execute("SELECT {} FROM ({})".format(", ".join(f'"{c}"' for c in cols), storage.ORACLES[name])).fetchall()
    assert sorted(map(str, map(tuple, df.select(*cols).collect()))) == sorted(map(str, want))


def test_lz_words_give_their_blocks_back_and_keep_the_bound(spark, sf):
    assert storage.lz_fixed_word(spark, sf).where("NOT same").isEmpty()
    assert storage.lz_bound_gap(spark, sf).where("NOT holds").isEmpty()


@pytest.mark.parametrize("range_chunks", [1, 3, 1_000_000])
def test_addresses_follow_each_other_over_all_ranges(spark, range_chunks):
    rnd = random.Random(8)
    rows = [(i // 4, i, "".join(rnd.choice("01") for _ in range(20))) for i in range(40)]
    got = addressed(spark.createDataFrame(rows, "chunk long, blk long, body string"), Law(("0", "1"), (1, 1)), 800, range_chunks).orderBy("blk").collect()
    at = 0
    for r in got:
        assert r.address == at
        at += r.len
    assert len(got) == 40
