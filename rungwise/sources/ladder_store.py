"""A ladder store on disk: written once, read by block range, and updated by overwriting touched parts only.

``blocks`` has one row per block (its word, or its raw body and home level where it is open), ``groups`` one row per
group and level; both are partitioned by ``part``, a range of chunks, and sorted inside.  All groups nest in their
chunk, so an edit never reaches beyond its part.  ``preamble`` is one row: schedule, law, length and the bits a reader
of the bare codeword would begin with.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import ladder
from ..operators.blocks import group_number
from ..plans.schedules import LadderSchedule, Law, Level, write_preamble
from .shared import written

#: Chunks in one part, and parts that a read names one by one (more are bounded by block number only).
CHUNKS_A_PART, NAMED_PARTS = 8, 1000


@dataclass
class SavedStore:
    spark: SparkSession
    folder: str
    schedule: LadderSchedule
    law: Law
    n: int

    @property
    def chunk_blocks(self) -> int:
        out = 1
        for level in self.schedule.levels:
            out *= level.fanout
        return out

    def table(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/{name}")

    def part_of(self, blk):
        return F.floor(group_number(blk, max(self.n // self.schedule.b0, 1), self.chunk_blocks) / CHUNKS_A_PART).cast("int")

    def blocks_at(self, wanted: DataFrame) -> DataFrame:
        """Rows of ``blocks`` under the numbers ``wanted(blk)``: only their parts and their range of blocks are scanned."""
        asked = wanted.select("blk").distinct()
        parts = sorted(r.part for r in asked.select(self.part_of(F.col("blk")).alias("part")).distinct().limit(NAMED_PARTS + 1).collect())
        low, high = asked.agg(F.min("blk"), F.max("blk")).first()
        if low is None:
            return self.table("blocks").where("false")
        rows = self.table("blocks").where(F.col("blk").between(low, high))
        if len(parts) <= NAMED_PARTS:
            rows = rows.where(F.col("part").isin(parts))
        return rows.join(asked, "blk", "left_semi")


def _rows(store: ladder.LadderStore) -> tuple[DataFrame, DataFrame]:
    raw = store.open_rows.select("chunk", "blk", F.col("body").alias("raw"), "home")
    part = F.floor(F.col("chunk") / CHUNKS_A_PART).cast("int").alias("part")
    blocks = store.blocks0.join(raw, ["chunk", "blk"], "left").select("chunk", "blk", "n_sym", "settled", "word", "raw", F.when(F.col("settled"), F.lit(0)).otherwise(F.col("home")).alias("home"), part)
    groups = None
    for i, g in enumerate(store.groups, 1):
        one = g.select(F.lit(i).alias("level"), "chunk", "grp", "n_child", "open_count", "settled", "header", part)
        groups = one if groups is None else groups.unionByName(one)
    return blocks, groups


def _write(df: DataFrame, path: str, mode: str) -> None:
    df.repartition("part").sortWithinPartitions("part", "blk" if "blk" in df.columns else "grp").write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("part").parquet(path)


def save(store: ladder.LadderStore, folder: str) -> SavedStore:
    """Write ``store`` (with words) to a new ``folder``."""
    spark, s, law = store.blocks0.sparkSession, store.schedule, store.law
    blocks, groups = _rows(store)
    _write(blocks, f"{folder}/blocks", "errorifexists")
    if groups is not None:
        _write(groups, f"{folder}/groups", "errorifexists")
    about = json.dumps({"schedule": asdict(s), "symbols": law.symbols, "counts": law.counts, "n": store.n})
    spark.createDataFrame([(1, about, write_preamble(s.b0, s.k0))], "version int, about string, bits string").write.parquet(f"{folder}/preamble")
    return SavedStore(spark, folder, s, law, store.n)


def load(spark: SparkSession, folder: str) -> SavedStore:
    about = json.loads(spark.read.parquet(f"{folder}/preamble").first().about)
    parts = about["schedule"] | {"levels": tuple(Level(**x) for x in about["schedule"]["levels"])}
    return SavedStore(spark, folder, LadderSchedule(**parts), Law(tuple(about["symbols"]), tuple(about["counts"])), about["n"])


def decoded(store: SavedStore, rows: DataFrame) -> DataFrame:
    """``rows`` of blocks with their ``body``; null where no level settled."""
    body = ladder.word_decoder(store.law, store.schedule)(F.col("word"), F.col("n_sym"))
    return rows.withColumn("body", F.when(F.col("settled"), body).when(F.col("home").isNotNull(), F.col("raw")))


def read_spans(store: SavedStore, spans: DataFrame, max_level: int | None = None) -> DataFrame:
    """As ``ladder.read_spans``, from the saved tables: one scan of the blocks that spans touch."""
    s = store.schedule
    exploded = ladder.clipped(spans, store.n, s.b0)
    return ladder.stitched(spans, exploded, decoded(store, store.blocks_at(exploded)), s, store.n, max_level)


def update(store: SavedStore, edits: DataFrame) -> None:
    """Apply edits ``(edit_id, blk, body)`` of whole blocks, the last edit of a block winning; only touched parts are written."""
    s = store.schedule
    net = written(edits.groupBy("blk").agg(F.max_by("body", "edit_id").alias("new")), "edits")
    parts = [r.part for r in net.select(store.part_of(F.col("blk")).alias("part")).distinct().collect()]
    old = store.table("blocks").where(F.col("part").isin(parts))
    whole = decoded(store, old).select("chunk", "blk", "n_sym", F.coalesce("body", "raw").alias("body"))
    now = whole.join(net, "blk", "left").select("chunk", "blk", "n_sym", F.coalesce("new", "body").alias("body"))
    blocks, groups = _rows(ladder.encode(now, store.law, s, store.n))
    # what is overwritten is also read, so all new rows are written aside before
    aside = {"blocks": written(blocks, "blocks")} | ({} if groups is None else {"groups": written(groups, "groups")})
    for name, rows in aside.items():
        _write(rows, f"{store.folder}/{name}", "overwrite")
