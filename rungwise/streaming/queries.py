"""Registered streaming queries over ``events`` and the DuckDB SQL of their final results."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as sql
from ..queries import _blocks, _store
from ..sources.catalog import coded, law_of, symbol_column
from .edits import appended_blocks, drift, land, land_net_edits, once, reads_after_edits, table_stream, wall_clock, windowed

UNITS = 500  # blocks that events edit where no store is at hand


def _edit_stream(spark, sf_dir, units: int):
    """One edit per event: it gives block ``blk`` the body of block ``src``."""
    return table_stream(spark, sf_dir, "events").select(F.col("event_id").alias("edit_id"), ((F.col("event_id") * 7919 + 5) % units).alias("blk"), ((F.col("event_id") * 6007 + 11) % units).alias("src"), "ts", "event_type")


def stream_append_blocks(spark, sf_dir):
    law = law_of(symbol_column(spark, sf_dir, "ev_type"))
    symbols = table_stream(spark, sf_dir, "events").select(F.col("event_id").alias("pos"), F.coalesce("event_type", F.lit("<null>")).alias("symbol"))
    return land(appended_blocks(symbols.select("pos", coded(law).alias("ch")), 64), "append-blocks")


def stream_edits_final(spark, sf_dir):
    """Bodies of all blocks after the whole edit stream."""
    blocks, _, s, n = _blocks(spark, sf_dir, "demo3")
    units = n // s.b0
    net = land_net_edits(_edit_stream(spark, sf_dir, units)).select("blk", "src")
    bodies = blocks.where(F.col("n_sym") == s.b0).select("blk", "body")
    edited = net.join(bodies.select(F.col("blk").alias("src"), F.col("body").alias("new")), "src").join(bodies.select("blk"), "blk", "left_semi").select("blk", "new")
    return blocks.join(edited, "blk", "left").select("blk", F.coalesce("new", "body").alias("body"))


def stream_edits_once(spark, sf_dir):
    """Every edit sent twice, taken once."""
    edits = _edit_stream(spark, sf_dir, UNITS).select("edit_id", "blk", "ts")
    return land(once(edits.unionByName(edits)), "edits-once").select("edit_id", "blk")


def stream_edit_windows(spark, sf_dir):
    return land(windowed(_edit_stream(spark, sf_dir, UNITS), F.count("*").alias("edits"), F.sum("blk").alias("blk_sum")), "edit-windows").select(wall_clock("start"), "edits", "blk_sum")


def stream_drift(spark, sf_dir):
    law = law_of(symbol_column(spark, sf_dir, "ev_type"))
    symbols = table_stream(spark, sf_dir, "events").select("ts", F.coalesce("event_type", F.lit("<null>")).alias("symbol"))
    return land(drift(symbols, law, 1, 8), "drift").select(wall_clock("start"), "n", "drifted")


def stream_edit_homes(spark, sf_dir):
    """Stream-static join: the home level that every edit finds."""
    st = _store(spark, sf_dir)
    homes = st.state.select("blk", F.coalesce("home", F.lit(-1)).alias("home"))
    return land(_edit_stream(spark, sf_dir, st.n // st.schedule.b0).select("edit_id", "blk").join(homes, "blk").select("edit_id", "blk", "home"), "edit-homes")


def stream_reads_after_edits(spark, sf_dir):
    """Stream-stream join: purchases edit a user's block, the user's other events within an hour read it."""
    ev = table_stream(spark, sf_dir, "events").withColumnRenamed("user_id", "blk")
    edits = ev.where("event_type = 'purchase'").withColumnRenamed("event_id", "edit_id")
    reads = ev.where("event_type <> 'purchase'").withColumnRenamed("event_id", "read_id")
    return land(reads_after_edits(edits, reads), "reads-after-edits")


QUERIES = {f.__name__: f for f in (stream_append_blocks, stream_edits_final, stream_edits_once, stream_edit_windows, stream_drift, stream_edit_homes, stream_reads_after_edits)}

_CLOSED = "start + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR"
_LAW = "ev AS (SELECT date_trunc('day', ts) AS start, coalesce(event_type, '<null>') AS symbol FROM events), law AS (SELECT symbol, count(*) AS c FROM ev GROUP BY symbol)"
ORACLES = {
    "stream_append_blocks": sql._with(sql._sym("ev_type")) + "SELECT pos // 64 AS blk, CAST(64 AS INTEGER) AS n_sym, string_agg(ch, '' ORDER BY pos) AS body FROM coded GROUP BY 1 HAVING count(*) = 64",
    "stream_edits_final": sql._with(sql._sym("li_small_qty"), sql._blk(128), "net AS (SELECT (event_id * 7919 + 5) % (n // 128) AS blk, arg_max((event_id * 6007 + 11) % (n // 128), event_id) AS src FROM events, nn GROUP BY 1)")
    + "SELECT b.blk, CASE WHEN b.n_sym = 128 AND z.n_sym = 128 THEN z.body ELSE b.body END AS body FROM blk b LEFT JOIN net USING (blk) LEFT JOIN blk z ON z.blk = net.src",
    "stream_edits_once": f"SELECT event_id AS edit_id, (event_id * 7919 + 5) % {UNITS} AS blk FROM events",
    "stream_edit_windows": f"SELECT * FROM (SELECT date_trunc('day', ts) AS start, count(*) AS edits, CAST(sum((event_id * 7919 + 5) % {UNITS}) AS BIGINT) AS blk_sum FROM events GROUP BY 1) WHERE {_CLOSED}",
    "stream_drift": f"""WITH {_LAW}, t AS (SELECT start, count(*) AS n FROM ev GROUP BY start)
SELECT start, n, bool_or(abs(cnt * total - n * c) * 8 > n * c) AS drifted FROM (SELECT t.start, t.n, law.c, (SELECT count(*) FROM events) AS total, (SELECT count(*) FROM ev WHERE ev.start = t.start AND ev.symbol = law.symbol) AS cnt FROM t, law) WHERE {_CLOSED} GROUP BY start, n""",
    "stream_edit_homes": sql._demo("sent AS (SELECT event_id AS edit_id, (event_id * 7919 + 5) % (n // 128) AS blk FROM events, nn)") + "SELECT edit_id, blk, CAST(coalesce(home, -1) AS INTEGER) AS home FROM sent JOIN home USING (blk)",
    "stream_reads_after_edits": "SELECT e.event_id AS edit_id, r.event_id AS read_id FROM events e JOIN events r ON e.user_id = r.user_id AND r.ts BETWEEN e.ts AND e.ts + INTERVAL 1 HOUR WHERE e.event_type = 'purchase' AND r.event_type <> 'purchase'",
}
