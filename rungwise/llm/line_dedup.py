"""Removal of boilerplate lines by their spread over distinct sites.

Every line is counted by the distinct sites (``source``) it stands on: HyperLogLog sketches per line hash merge in
the aggregation's partial and final steps.  Lines whose estimate is clearly over the threshold are boilerplate,
lines whose estimate is near it get an exact count of distinct sites.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, small_batches

#: Sites from which on a line counts as boilerplate.
MIN_SITES = 10
#: Estimates within this share of the threshold are counted exactly.
NEAR = 0.3
SKETCH_LG_K = 11
#: Boilerplate lines, and bytes of them, that are shipped to every executor at most; beyond it places are joined.
SHIPPED_LINES = 50_000
SHIPPED_BYTES = 20_000_000


def _lines(docs: DataFrame) -> DataFrame:
    """Every non-blank line with its key, place and site."""
    rows = docs.select("doc_id", "rk", "source", F.posexplode(F.split("text", "\n")).alias("pos", "raw"))
    return rows.select("doc_id", "rk", "source", "pos", F.trim("raw").alias("line")).where("line <> ''").withColumn("h", F.xxhash64("line"))


def boilerplate(lines: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """``(h, line)`` of the lines on at least ``min_sites`` distinct sites; a null site is no site."""
    # hashes are counted, and only the lines of spread hashes travel
    sketched = lines.groupBy("h").agg(F.count("source").alias("n"), F.hll_sketch_estimate(F.hll_sketch_agg("source", F.lit(SKETCH_LG_K))).alias("sites"))
    spread = cut(sketched.where((F.col("n") >= min_sites) & (F.col("sites") >= min_sites * (1 - NEAR))).select("h", "sites"))
    near = spread.where(F.col("sites") <= min_sites * (1 + NEAR)).select("h")
    exact = lines.join(near, "h", "left_semi").groupBy("h", "line", "source").agg(F.lit(1).alias("one")).groupBy("h", "line").agg(F.count("source").alias("sites")).where(F.col("sites") >= min_sites)
    over = lines.join(spread.where(F.col("sites") > min_sites * (1 + NEAR)).select("h"), "h", "left_semi").groupBy("h", "line").agg(F.lit(1).alias("one"))
    return cut(over.select("h", "line").unionByName(exact.select("h", "line")))


def _shippable(found: DataFrame) -> bool:
    row = found.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("line")), F.lit(0)).alias("size")).first()
    return row.n <= SHIPPED_LINES and row["size"] <= SHIPPED_BYTES


def _kept(text: str | None, gone) -> tuple[int, int, str]:
    """(lines, removed, text left); ``gone(position, line)`` tells what goes."""
    if text is None:
        return 0, 0, ""
    lines = text.split("\n")
    kept = [x for i, x in enumerate(lines) if not gone(i, x)]
    return len(lines), len(lines) - len(kept), "\n".join(kept)


_RESULT = "doc_id long, n_lines long, n_removed long, kept_sha256 string, kept_text string"


def _batch(ids, done) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [ids, pa.array([d[0] for d in done], pa.int64()), pa.array([d[1] for d in done], pa.int64()), pa.array([hashlib.sha256(d[2].encode("utf-8", "surrogatepass")).hexdigest() for d in done], pa.string()), pa.array([d[2] for d in done], pa.string())],
        ["doc_id", "n_lines", "n_removed", "kept_sha256", "kept_text"],
    )


def remove_boilerplate(docs: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_lines, n_removed, kept_sha256, kept_text.

    Lines are what newlines part; lines of every length are judged, and a line's spread counts by its text without
    outer spaces.  Blank lines and null texts stay as they are (a null text has no lines and an empty kept text).
    Repeated rows are judged alike, an empty table gives an empty result, other columns are ignored.
    """
    spark = docs.sparkSession
    small_batches(spark)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("source").cast("string").alias("source")).withColumn("rk", F.xxhash64("text"))
    found = boilerplate(_lines(keyed), min_sites)
    if _shippable(found):
        shipped = spark.sparkContext.broadcast(frozenset(r.line for r in found.select("line").collect()))

        def by_line(batches):
            known = shipped.value
            for batch in batches:
                yield _batch(batch.column("doc_id"), [_kept(t, lambda _, x: x.strip(" ") in known) for t in batch.column("text").to_pylist()])

        return keyed.select("doc_id", "text").mapInArrow(by_line, _RESULT)

    def by_place(batches):
        for batch in batches:
            gone = [set(g or ()) for g in batch.column("gone").to_pylist()]
            yield _batch(batch.column("doc_id"), [_kept(t, lambda i, _, g=g: i in g) for t, g in zip(batch.column("text").to_pylist(), gone, strict=True)])

    places = _lines(keyed).join(found, ["h", "line"]).groupBy("doc_id", "rk").agg(F.collect_set("pos").alias("gone"))
    return keyed.join(places, ["doc_id", "rk"], "left").select("doc_id", "text", "gone").mapInArrow(by_place, _RESULT)


def without_boilerplate(docs: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """``docs`` with boilerplate lines taken out of ``text`` (and ``n_chars`` adapted); all columns and rows stay.
    Lines of every length are judged.

    A document whose lines would all go keeps its text: it has no other content, and its copies on other sites
    are the business of near-duplicate search.
    """
    spark = docs.sparkSession
    small_batches(spark)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("source").cast("string").alias("source")).withColumn("rk", F.xxhash64("text"))
    found = boilerplate(_lines(keyed), min_sites)
    small = _shippable(found)
    names = docs.columns

    def rewritten(batch: pa.RecordBatch, texts: list) -> pa.RecordBatch:
        cols = {n: batch.column(n) for n in names}
        cols["text"] = pa.array(texts, pa.string())
        if "n_chars" in cols:
            cols["n_chars"] = pa.array([None if t is None else len(t) for t in texts], pa.int64()).cast(cols["n_chars"].type)
        return pa.RecordBatch.from_arrays(list(cols.values()), names)

    def left(text, gone):
        kept = _kept(text, gone)[2]
        return kept if text is not None and kept.strip() else text

    if small:
        shipped = spark.sparkContext.broadcast(frozenset(r.line for r in found.select("line").collect()))

        def by_line(batches):
            known = shipped.value
            for batch in batches:
                yield rewritten(batch, [left(t, lambda _, x: x.strip(" ") in known) for t in batch.column("text").cast(pa.string()).to_pylist()])

        return docs.mapInArrow(by_line, docs.schema)

    def by_place(batches):
        for batch in batches:
            gone = [set(g or ()) for g in batch.column("__gone").to_pylist()]
            yield rewritten(batch, [left(t, lambda i, _, g=g: i in g) for t, g in zip(batch.column("text").cast(pa.string()).to_pylist(), gone, strict=True)])

    places = _lines(keyed).join(found, ["h", "line"]).groupBy(F.col("doc_id").alias("__id"), F.col("rk").alias("__rk")).agg(F.collect_set("pos").alias("__gone"))
    joined = docs.join(places, (F.col("doc_id") == F.col("__id")) & (F.xxhash64(docs["text"].cast("string")) == F.col("__rk")), "left").drop("__id", "__rk")
    return joined.mapInArrow(by_place, docs.schema)
