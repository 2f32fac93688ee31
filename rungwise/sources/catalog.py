"""Table columns as symbol sequences: reading, symbolising, and dense positions without a global window."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.schedules import Law
from .shared import written

LI_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")


@dataclass(frozen=True)
class Source:
    """A column of a table as a sequence: ``expr`` gives the symbol, ``key`` the unique order."""

    table: str
    expr: str
    key: tuple[str, ...]
    dense: bool = False  # the key counts 0..n-1 itself


SOURCES = {
    "li_flag": Source("lineitem", "l_returnflag", LI_KEY),
    "li_status": Source("lineitem", "l_linestatus", LI_KEY),
    "li_small_qty": Source("lineitem", "CASE WHEN l_quantity <= 5 THEN '1' ELSE '0' END", LI_KEY),
    "li_zero_tax": Source("lineitem", "CASE WHEN l_tax = 0 THEN '1' ELSE '0' END", LI_KEY),
    "li_line": Source("lineitem", "CAST(l_linenumber AS STRING)", LI_KEY),
    "od_status": Source("orders", "o_orderstatus", ("o_orderkey",), True),
    "od_prio": Source("orders", "o_orderpriority", ("o_orderkey",), True),
    "ev_type": Source("events", "event_type", ("event_id",), True),
    "cu_seg": Source("customer", "c_mktsegment", ("c_custkey",)),
    "cu_nation": Source("customer", "CAST(c_nationkey AS STRING)", ("c_custkey",)),
    "pt_type": Source("part", "p_type", ("p_partkey",)),
    "pt_brand": Source("part", "p_brand", ("p_partkey",)),
    "pt_size": Source("part", "CAST(p_size AS STRING)", ("p_partkey",)),
    "su_nation": Source("supplier", "CAST(s_nationkey AS STRING)", ("s_suppkey",)),
    "na_region": Source("nation", "CAST(n_regionkey AS STRING)", ("n_nationkey",)),
    "lb_quality": Source("labels", "CAST(quality AS STRING)", ("doc_id",)),
    "lb_toxic": Source("labels", "CAST(toxic AS STRING)", ("doc_id",)),
    "dc_lang": Source("documents", "lang", ("doc_id",)),
    "dc_source": Source("documents", "source", ("doc_id",)),
    "cv_role": Source("conversations", "role", ("conv_id", "turn")),
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def symbol_column(spark: SparkSession, sf_dir: str, name: str, null_symbol: str = "<null>") -> DataFrame:
    """``(key columns, symbol)``; a null is a symbol of its own."""
    s = SOURCES[name]
    return read_table(spark, sf_dir, s.table).select(*s.key, F.coalesce(F.expr(s.expr).cast("string"), F.lit(null_symbol)).alias("symbol"))


def law_of(symbols: DataFrame) -> Law:
    """Counts by symbol: one partial aggregation, an alphabet's worth of rows on the driver."""
    rows = sorted((r.symbol, r.n) for r in symbols.groupBy("symbol").agg(F.count("*").alias("n")).collect())
    return Law(tuple(r[0] for r in rows), tuple(r[1] for r in rows))


def coded(law: Law) -> Column:
    """The symbol's character; unseen symbols under a declared law raise no error, they are no admitted character."""
    if not law.k:
        return F.lit("")
    table = F.create_map(*[x for i, s in enumerate(law.symbols) for x in (F.lit(s), F.lit(law.chars[i]))])
    return F.coalesce(F.element_at(table, F.col("symbol")), F.lit("~"))


#: Rows that one ordering task numbers, about.
ROWS_PER_BUCKET = 100_000
COARSE = 2048


def index_rows(df: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """``pos``: dense position from 0 in the order of the whole key, nulls first; equal keys in any order.

    Beyond one bucket's rows the table is range-partitioned by the whole key (its own sampled bounds, so outliers and
    uneven keys don't fill a bucket) and written to the shared folder, since a second evaluation could draw other
    bounds.  Rows are numbered within their bucket and shifted by the counts before it; counts are summed within coarse
    ranges of buckets and across them, so that no window sees the whole table.
    """
    n = df.count()
    order = [F.col(k).asc_nulls_first() for k in key]
    if not n:
        return df.withColumn("pos", F.lit(0).cast("long"))
    buckets = -(-n // ROWS_PER_BUCKET)
    if buckets == 1:
        return df.withColumn("pos", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*order)).cast("long") - 1)
    bucketed = written(df.repartitionByRange(buckets, *order).withColumn("bucket", F.spark_partition_id().cast("long")), "ordered")
    span = -(-buckets // COARSE)
    counts = bucketed.groupBy("bucket").agg(F.count("*").alias("n")).withColumn("range", F.floor(F.col("bucket") / span))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("range").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sums = sorted((r.range, r.n) for r in counts.groupBy("range").agg(F.sum("n").alias("n")).collect())
    starts, at = [], 0
    for k, c in sums:
        starts.append((k, at))
        at += c
    table = F.broadcast(df.sparkSession.createDataFrame(starts, "range long, start long"))
    shifts = counts.withColumn("within", before).join(table, "range").select("bucket", (F.col("within") + F.col("start")).alias("shift"))
    numbered = bucketed.withColumn("nth", F.row_number().over(Window.partitionBy("bucket").orderBy(*order)))
    return numbered.join(shifts, "bucket").withColumn("pos", F.col("shift") + F.col("nth") - 1).drop("bucket", "shift", "nth")


def positions(spark: SparkSession, sf_dir: str, name: str, law: Law | None = None) -> tuple[DataFrame, Law, int]:
    """``(pos, ch)`` of a source, its law and its length."""
    s = SOURCES[name]
    symbols = symbol_column(spark, sf_dir, name)
    known = law or law_of(symbols)
    n = known.total if law is None else symbols.count()
    placed = symbols.withColumn("pos", F.col(s.key[0]).cast("long")) if s.dense else index_rows(symbols, s.key)
    return placed.select("pos", coded(known).alias("ch")), known, n


def class_text(text: Column) -> Column:
    """Characters mapped to 4 classes: 0 space, 1 vowel, 2 other ASCII letter, 3 anything else."""
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(text, r"[^A-Za-z ]", "3"), "[AEIOUaeiou]", "1"), "[A-Za-z]", "2"), " ", "0")
