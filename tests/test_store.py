"""The saved ladder store: pruned reads, and updates that touch their parts only."""

from pathlib import Path

import pytest
from pyspark.sql import functions as F

from rungwise import queries as q
from rungwise.operators import ladder
from rungwise.sources import ladder_store


@pytest.fixture(scope="module")
def made(spark, tmp_path_factory):
    blocks, law, s, n = q._blocks(spark, "/root/testdata/sf0.01", "deep3")
    blocks = blocks.cache()
    ladder_store.CHUNKS_A_PART, before = 1, ladder_store.CHUNKS_A_PART
    folder = str(tmp_path_factory.mktemp("store") / "deep3")
    yield ladder_store.save(ladder.encode(blocks, law, s, n), folder), blocks
    ladder_store.CHUNKS_A_PART = before


def files_of(saved):
    return {p.name: sorted(f.name for f in p.glob("*.parquet")) for p in Path(saved.folder, "blocks").glob("part=*")}


def test_reads_equal_the_unsaved_store_and_scan_one_part(spark, made):
    saved, blocks = made
    st = ladder.encode(blocks, saved.law, saved.schedule, saved.n)
    spans = spark.createDataFrame([(1, 100, 500), (2, 0, 0), (3, saved.n - 5, 50), (4, 7000, 1)], "req_id long, start long, len long")
    again = ladder_store.load(spark, saved.folder)
    assert again.schedule == saved.schedule and again.law == saved.law
    for cap in (None, 0):
        assert sorted(map(tuple, ladder_store.read_spans(again, spans, cap).collect())) == sorted(map(tuple, ladder.read_spans(st, spans, cap).collect()))
    near = ladder_store.read_spans(saved, spark.createDataFrame([(1, 100, 500)], "req_id long, start long, len long"))
    plan = near._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan parquet") == 1 and "part#" in plan.split("PartitionFilters: [")[1].split("]")[0] and "GreaterThanOrEqual(blk" in plan
    rows = saved.blocks_at(spark.createDataFrame([(2,), (3,)], "blk long"))
    assert rows.count() == 2


def test_update_overwrites_touched_parts_only(spark, made):
    saved, blocks = made
    parts = files_of(saved)
    assert len(parts) > 3
    edits = q.edits(blocks, 2 * saved.chunk_blocks, saved.schedule.b0, 40)  # the first two chunks
    after = ladder.update_state(ladder.encode(blocks, saved.law, saved.schedule, saved.n, False), edits).cache()
    want = sorted((r.blk, r.body, r.settled, r.home) for r in after.collect())
    ladder_store.update(saved, edits)
    got = ladder_store.decoded(saved, saved.table("blocks")).select("blk", F.coalesce("body", "raw").alias("body"), "settled", "home")
    assert sorted((r.blk, r.body, r.settled, r.home) for r in got.collect()) == want
    now = files_of(saved)
    assert {p for p in parts if parts[p] != now[p]} == {"part=0", "part=1"}
    groups = ladder.encode(after.join(blocks.select("chunk", "blk", "n_sym"), "blk").select("chunk", "blk", "n_sym", "body"), saved.law, saved.schedule, saved.n, False).groups
    stored = saved.table("groups")
    for i, g in enumerate(groups, 1):
        assert sorted(map(str, stored.where(f"level = {i}").select("grp", "n_child", "open_count", "settled", "header").collect())) == sorted(map(str, g.select("grp", "n_child", "open_count", "settled", "header").collect()))
