import os
from datetime import datetime, timedelta

import pandas as pd
from pyspark.sql import functions as F

from rungwise.plans.schedules import Law
from rungwise.streaming.edits import appended_blocks, drift, dropped_late, land, land_net_edits, once, reads_after_edits

DAY = datetime(2024, 1, 1)


def _files(spark, tmp_path, schema, *parts):
    """A stream that takes one file a batch, in the order given."""
    folder = tmp_path / "in"
    folder.mkdir()
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / f"part{i}"))
        (file,) = (tmp_path / f"part{i}").glob("*.parquet")
        file = file.rename(folder / f"{i}.parquet")
        os.utime(file, (1_700_000_000 + i, 1_700_000_000 + i))  # files are taken by age
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(folder))


def test_blocks_fill_up_over_batches(spark, tmp_path):
    a = [(i, "ab"[i % 2]) for i in (0, 2, 5, 1, 4)]
    b = [(i, "ab"[i % 2]) for i in (3, 7, 6, 8)] + [(None, "a"), (9, None)]
    got = land(appended_blocks(_files(spark, tmp_path, "pos long, ch string", a, b), 4), "t").orderBy("blk").collect()
    assert [(r.blk, r.n_sym, r.body) for r in got] == [(0, 4, "abab"), (1, 4, "abab")]


def test_last_edit_of_a_block_wins_in_any_order(spark, tmp_path):
    got = land_net_edits(_files(spark, tmp_path, "edit_id long, blk long, src long", [(5, 1, 50), (2, 2, 20)], [(3, 1, 30), (9, 2, 90)]))
    assert sorted(map(tuple, got.collect())) == [(1, 5, 50), (2, 9, 90)]


def test_repeated_edits_go_once_and_late_ones_are_counted(spark, tmp_path):
    at = lambda h: DAY + timedelta(hours=h)
    stream = _files(spark, tmp_path, "edit_id long, ts timestamp", [(1, at(0)), (2, at(5)), (1, at(0))], [(3, at(9))], [(4, at(1))])  # lateness is judged by the watermark of the batch before
    q = once(stream).writeStream.format("memory").queryName("once_t").option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted(r.edit_id for r in spark.table("once_t").collect()) == [1, 2, 3]
    assert dropped_late(q) == 1


def test_drift_marks_shifted_and_unknown_symbols(spark):
    law = Law(("a", "b"), (50, 50))
    rows = [(DAY + timedelta(days=d, minutes=i), s) for d, syms in enumerate(("ab" * 5, "aaaaaaab", "abc")) for i, s in enumerate(syms)]
    got = drift(spark.createDataFrame(rows, "ts timestamp, symbol string"), law, 1, 8).orderBy("start").collect()
    assert [(r.n, r.drifted) for r in got] == [(10, False), (8, True), (3, True)]


def test_reads_after_edits_against_pairs(spark):
    e = pd.DataFrame({"edit_id": [1, 2], "blk": [7, 8], "ts": [DAY, DAY]})
    r = pd.DataFrame({"read_id": [1, 2, 3, 4], "blk": [7, 7, 8, 9], "ts": [DAY, DAY + timedelta(hours=2), DAY + timedelta(hours=1), DAY]})
    got = reads_after_edits(spark.createDataFrame(e), spark.createDataFrame(r))
    assert sorted(map(tuple, got.collect())) == [(1, 1), (2, 3)]
    assert got.where(F.col("edit_id").isNull()).isEmpty()
