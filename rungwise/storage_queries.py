"""Registered queries around the stores: joins over ranges, differences, escapes and round trips, with their SQL."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from . import oracles as sql
from .operators import baselines, codeword, dense, escape, ladder, overlap, ranked
from .operators.blocks import cut_blocks, settled, symbol_count
from .plans.schedules import ladder_schedule
from .queries import _blocks, _ranked_store, _saved_store, _store, edits, spans
from .sources import ladder_store
from .sources.catalog import SOURCES, class_text, index_rows, positions, read_table

UNITS = 97


def edit_range_join(spark, sf_dir):
    """The version of a block that every purchase finds, by validity intervals of the other events' edits."""
    ev = read_table(spark, sf_dir, "events").withColumn("t", F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', cast(ts AS timestamp_ntz))"))
    made = ev.where("event_type <> 'purchase'").select(F.col("event_id").alias("edit_id"), (F.col("event_id") * 7919 % UNITS).alias("blk"), F.col("t").alias("at"))
    points = ev.where("event_type = 'purchase'").select(F.col("event_id").alias("read_id"), (F.col("event_id") * 6007 % UNITS).alias("blk"), "t")
    return overlap.valid_at(points, overlap.versions(made), 3600)


def cell_overlap(spark, sf_dir):
    """Orders as cells of varying size in the line sequence, and the spans that meet them."""
    lines = index_rows(read_table(spark, sf_dir, "lineitem").select(*SOURCES["li_flag"].key), SOURCES["li_flag"].key)
    cells = lines.groupBy(F.col("l_orderkey").alias("cell")).agg(F.min("pos").alias("first"), F.count("*").alias("size"))
    n = lines.count()
    return overlap.overlapping(spans(spark, n), cells, 64)


def store_diff(spark, sf_dir):
    blocks, law, s, n = _blocks(spark, sf_dir, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    after = ladder.update_state(st, edits(blocks, n // s.b0, s.b0)).select("body", "settled")
    return overlap.multiset_diff(st.state.select("body", "settled"), after)


def _event_edits(spark, sf_dir, blocks, units, b0):
    """One whole-block edit per event."""
    whole = blocks.where(F.col("n_sym") == b0)
    asked = read_table(spark, sf_dir, "events").select(F.col("event_id").alias("edit_id"), ((F.col("event_id") * 7919 + 5) % units).alias("blk"), ((F.col("event_id") * 6007 + 11) % units).alias("src"))
    return asked.join(whole.select(F.col("blk").alias("src"), "body"), "src").join(whole.select("blk"), "blk", "left_semi").select("edit_id", "blk", "body")


def ladder_update_batch_net(spark, sf_dir):
    """State after one edit per event, the last edit of a block counting."""
    blocks, law, s, n = _blocks(spark, sf_dir, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    return ladder.update_state(st, _event_edits(spark, sf_dir, blocks, n // s.b0, s.b0)).select("blk", "body", "settled", F.coalesce("home", F.lit(-1)).alias("home"))


def ladder_update_sequential(spark, sf_dir):
    """What one edit per event costs if every edit meets the state that its predecessors left."""
    blocks, law, s, n = _blocks(spark, sf_dir, "deep3")
    st = ladder.encode(blocks, law, s, n, False)
    return ladder.update_costs(st, _event_edits(spark, sf_dir, blocks, n // s.b0, s.b0), sequential=True)


def _dense(spark, sf_dir, *variants):
    words = dense.dense_words(_store(spark, sf_dir, "deep3"), variants)
    return words.groupBy("level", "variant").agg(F.count("*").alias("cells"), F.sum("bits").alias("bits"), F.min("same").alias("same"))


def dense_headers(spark, sf_dir):
    """Bits of all settled groups' words, plain and by weighed headers with radix payloads."""
    return _dense(spark, sf_dir, "plain", "radix")


def dense_headers_lz(spark, sf_dir):
    """The same with LZ-coded payloads."""
    return _dense(spark, sf_dir, "lz")


def runtime_curve(spark, sf_dir):
    """Seconds to encode, decode and read spans on growing parts of the sequence; no SQL gives times."""
    placed, law, n = positions(spark, sf_dir, "li_small_qty")
    rows = []
    for part in (8, 4, 2, 1):
        m = n // part
        s = ladder_schedule(law, 128, 1, 2, [8, 16], m)
        st = ladder.encode(cut_blocks(placed.where(F.col("pos") < m), m, 128, 128), law, s, m)
        took = []
        for made in (st.blocks0, ladder.decode(st), ladder.read_spans(st, spans(spark, m))):
            began = time.perf_counter()
            made.write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - began)
        rows.append((m, *took))
    return spark.createDataFrame(rows, "n long, encode_s double, decode_s double, read_s double")


def ladder_read_scattered(spark, sf_dir):
    """Requests of 16 single symbols far apart: each is a read of its own."""
    blocks, law, s, n = _blocks(spark, sf_dir, "demo3")
    st = ladder.encode(blocks, law, s, n, False)
    points = spark.range(50).select(F.col("id").alias("req_id"), F.explode(F.sequence(F.lit(0), F.lit(15))).alias("j")).select("req_id", ((F.col("req_id") * 7919 + F.col("j") * 104729 + 13) % n).alias("start"), F.lit(1).cast("long").alias("len"))
    at = ladder.touched(points, n, s.b0).join(st.state.select("blk", "home"), "blk")
    return at.groupBy("req_id").agg(F.count("*").alias("reads"), F.sum(ladder.full_cost(s, F.col("home"))).alias("probes"))


def source_stress(spark, sf_dir):
    """Typicality of the documents' sources in order."""
    placed, law, n = positions(spark, sf_dir, "dc_source")
    return cut_blocks(placed, n, 16).select("blk", settled(F.col("body"), law, 1, 2).alias("settled"))


def lz_fixed_word(spark, sf_dir):
    """LZ words of the universal preset, their bits beside raw ones, and whether they give their block back."""
    st = _saved_store(spark, sf_dir, "universal")
    blocks, *_ = _blocks(spark, sf_dir, "universal")
    words = ladder_store.decoded(st, st.table("blocks").where("settled")).select("blk", F.col("body").alias("back"))
    return words.join(blocks, "blk").select("blk", F.floor(F.col("n_sym") * st.schedule.k0 / st.schedule.b0).alias("bits"), F.col("n_sym").cast("long").alias("raw_bits"), (F.col("back") == F.col("body")).alias("same"))


def universal_roundtrip(spark, sf_dir):
    """Every block back from the saved LZ words and open rows; a block that no level settled comes from its raw escape."""
    st = _saved_store(spark, sf_dir, "universal")
    return ladder_store.decoded(st, st.table("blocks")).select("blk", F.coalesce("body", "raw").alias("body"), F.col("home").isNull().alias("escaped"))


def lz_bound_gap(spark, sf_dir):
    """LZ bits of every document's class text beside the bound by its order-0 entropy (constant 4)."""
    docs = read_table(spark, sf_dir, "documents").where("length(text) >= 64").select("doc_id", class_text(F.col("text")).alias("t"))
    shares = [symbol_count(F.col("t"), str(i)) / F.length("t") for i in range(4)]
    h = sum((F.when(p > 0, -p * F.log2(p)).otherwise(0.0) for p in shares), F.lit(0.0))
    n = F.length("t").cast("double")
    bound = n * h + 4.0 * n * F.log2(F.log2(n)) / F.log2(n)
    return docs.select("doc_id", F.length("t").alias("n"), baselines.lz_length(4)(F.col("t")).alias("bits"), bound.alias("bound")).select("doc_id", "n", "bits", (F.col("bits") <= F.col("bound")).alias("holds"))


def escape_roundtrip(spark, sf_dir):
    """Class texts of all documents, stored with a flag per document, back without an error."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", class_text(F.col("text")).alias("t"))
    stored = escape.escaped_texts(docs, "doc_id", F.col("t"), 4, 512, 19, 20)
    return escape.unescaped_texts(stored, 4).select(F.col("seq_id").alias("doc_id"), F.md5(F.col("text").cast("binary")).alias("digest"))


def prefix_free_check(spark, sf_dir):
    """Fixed LZ words and raw bodies behind a flag: no codeword begins another."""
    blocks, law, _, _ = _blocks(spark, sf_dir, "flag3", b0=64)
    whole = blocks.where("n_sym = 64")
    short = escape.lz_word(law.k)(F.col("body"), F.lit(150))
    words = whole.select(F.coalesce(F.concat(F.lit("0"), short), F.concat(F.lit("1"), F.col("body"))).alias("word"))
    return escape.prefix_free(words).select("prefix_free")


def ranked_roundtrip(spark, sf_dir):
    """Every block and the tail back from the stored words; a failed block is marked and has no body."""
    return ranked.decode(_ranked_store(spark, sf_dir))


def ladder_codeword_bits(spark, sf_dir):
    """The whole codeword, cell by cell."""
    return codeword.codeword(_store(spark, sf_dir, "deep3", words=True))


def _edited(spark, sf_dir, preset):
    """Stores before and after a batch of edits."""
    blocks, law, s, n = _blocks(spark, sf_dir, preset)
    made = edits(blocks, n // s.b0, s.b0).groupBy("blk").agg(F.max_by("body", "edit_id").alias("new"))
    after = blocks.join(made, "blk", "left").select("chunk", "blk", "n_sym", F.coalesce("new", "body").alias("body"))
    return ladder.encode(blocks, law, s, n), ladder.encode(after, law, s, n)


def ladder_flipped_bits(spark, sf_dir):
    """What a batch of edits rewrites, by whole cells and by bits that differ."""
    return codeword.flipped(*_edited(spark, sf_dir, "deep3"))


QUERIES = {f.__name__: f for f in (edit_range_join, cell_overlap, store_diff, ladder_update_batch_net, ladder_update_sequential, dense_headers, dense_headers_lz, runtime_curve, ladder_read_scattered, source_stress, lz_fixed_word, universal_roundtrip, lz_bound_gap, escape_roundtrip, prefix_free_check, ranked_roundtrip, ladder_codeword_bits, ladder_flipped_bits)}

_after = (sql._blk(64), "last_ed AS (SELECT blk, arg_max(body, edit_id) AS nb FROM ed GROUP BY blk)", "after AS (SELECT blk, n_sym, coalesce(nb, body) AS body FROM blk LEFT JOIN last_ed USING (blk))", sql._set(1, 2, "after"))
_event_made = "ed AS (SELECT event_id AS edit_id, a.blk, z.body FROM (SELECT event_id, (event_id * 7919 + 5) % (n // 64) AS tb, (event_id * 6007 + 11) % (n // 64) AS sb FROM events, nn) e JOIN blk a ON a.blk = e.tb JOIN blk z ON z.blk = e.sb WHERE a.n_sym = 64 AND z.n_sym = 64)"
ORACLES = {
    "edit_range_join": f"""WITH v AS (SELECT event_id AS edit_id, event_id * 7919 % {UNITS} AS blk, date_trunc('second', ts) AS t FROM events WHERE event_type <> 'purchase'),
w AS (SELECT *, lead(t) OVER (PARTITION BY blk ORDER BY t, edit_id) AS until FROM v), p AS (SELECT event_id AS read_id, event_id * 6007 % {UNITS} AS blk, date_trunc('second', ts) AS t FROM events WHERE event_type = 'purchase')
SELECT read_id, blk, edit_id FROM p JOIN w USING (blk) WHERE p.t >= w.t AND (until IS NULL OR p.t < until)""",
    "cell_overlap": sql._with(sql._sym("li_flag"), sql._SPANS, f"lines AS (SELECT l_orderkey, row_number() OVER (ORDER BY {', '.join(SOURCES['li_flag'].key)}) - 1 AS pos FROM lineitem)")
    + "SELECT req_id, l_orderkey AS cell, count(*) AS overlap FROM spans JOIN lines ON pos >= start AND pos < start + len GROUP BY ALL",
    "store_diff": sql._with(sql._sym("li_small_qty"), _after[0], sql._edits(64), *_after[1:3], sql._set(1, 2), sql._set(1, 2, "after", "sa"))
    + "SELECT 'gone' AS side, count(*) AS rows FROM (SELECT body, settled FROM st EXCEPT ALL SELECT body, settled FROM sa) UNION ALL SELECT 'come', count(*) FROM (SELECT body, settled FROM sa EXCEPT ALL SELECT body, settled FROM st) UNION ALL SELECT 'kept', count(*) FROM (SELECT body, settled FROM st INTERSECT ALL SELECT body, settled FROM sa)",
    "ladder_update_batch_net": sql._with(sql._sym("li_small_qty"), _after[0], _event_made, *_after[1:], sql._levels(64)) + "SELECT blk, body, settled, CAST(coalesce(home, -1) AS INTEGER) AS home FROM home",
    "ladder_update_sequential": sql._with(sql._sym("li_small_qty"), _after[0], _event_made, sql._set(1, 2), sql._levels(64), sql._widths(64), sql._set(1, 2, "ed", "es", "edit_id"), f"""pre AS (SELECT e.edit_id, e.settled AS es, h.blk = e.blk AS own, h.g1, h.g1 = t.g1 AS near, coalesce(p.settled, h.settled) AS so
  FROM es e JOIN home t ON t.blk = e.blk JOIN home h ON h.g2 = t.g2 ASOF LEFT JOIN es p ON p.blk = h.blk AND e.edit_id > p.edit_id),
p1 AS (SELECT edit_id, g1, bool_or(near) AS near, bool_or(own AND so) AS so, bool_or(es) AS sn, count(*) FILTER (NOT so) <= count(*) // 4 AS s1, count(*) FILTER (NOT CASE WHEN own THEN es ELSE so END) <= count(*) // 4 AS t1 FROM pre GROUP BY edit_id, g1),
p2 AS (SELECT edit_id, bool_or(so) AS so, bool_or(sn) AS sn, bool_or(near AND s1) AS s1, bool_or(near AND t1) AS t1, count(*) FILTER (NOT s1) <= count(*) // 8 AS s2, count(*) FILTER (NOT t1) <= count(*) // 8 AS t2 FROM p1 GROUP BY edit_id),
p3 AS (SELECT edit_id, (CASE WHEN so THEN 'S' ELSE 'O' END) || (CASE WHEN sn THEN 'S' ELSE 'O' END) AS kind, CASE WHEN so THEN 0 WHEN s1 THEN 1 WHEN s2 THEN 2 END AS home, CASE WHEN sn THEN 0 WHEN t1 THEN 1 WHEN t2 THEN 2 END AS nh FROM p2)""")
    + f"""SELECT edit_id, blk, kind AS "case", CAST(coalesce(home, -1) AS INTEGER) AS old_home, CAST(coalesce(nh, -1) AS INTEGER) AS new_home,
  CAST(CASE kind WHEN 'SS' THEN k0 WHEN 'OO' THEN {sql._FULL.format(h="coalesce(home, 2)")} ELSE {sql._FULL.format(h="greatest(coalesce(home, 2), coalesce(nh, 2))")} END AS BIGINT) AS bits_read,
  CAST(CASE kind WHEN 'SS' THEN k0 WHEN 'OO' THEN CASE coalesce(home, 2) WHEN 1 THEN k1 ELSE k2 END ELSE {sql._FULL.format(h="greatest(coalesce(home, 2), coalesce(nh, 2))")} END AS BIGINT) AS bits_written
FROM p3 JOIN ed USING (edit_id), kk""",
    "dense_headers": sql._with(sql._sym("li_small_qty"), _after[0], sql._set(1, 2), sql._levels(64), """cells AS (SELECT 1 AS level, g1 AS grp, any_value(n1) AS b, any_value(o1) AS m, coalesce(sum(n_sym) FILTER (NOT settled), 0) AS len FROM home WHERE s1 GROUP BY g1
  UNION ALL SELECT 2, g2, any_value(n2), any_value(o2), coalesce(sum(n_sym) FILTER (NOT s1), 0) FROM home, nn WHERE s2 AND n // 64 // 8 // 16 >= 1 GROUP BY g2),
priced AS (SELECT level, unnest(['plain', 'radix']) AS variant, unnest([b + 2 * len, CAST(floor(log2(b)) + 1 + ceil(log2(factorial(CAST(b AS INTEGER)) / (factorial(CAST(m AS INTEGER)) * factorial(CAST(b - m AS INTEGER))))) + ceil(len * log2(3)) AS BIGINT)]) AS bits FROM cells)""")
    + "SELECT level, variant, count(*) AS cells, CAST(sum(bits) AS BIGINT) AS bits, true AS same FROM priced GROUP BY level, variant",
    "ladder_read_scattered": sql._demo(sql._widths(128), "pts AS (SELECT r AS req_id, (r * 7919 + j * 104729 + 13) % n AS p FROM range(50) a(r), range(16) b(j), nn)")
    + f"SELECT req_id, count(*) AS reads, CAST(sum({sql._FULL.format(h='home')}) AS BIGINT) AS probes FROM (SELECT req_id, least(p // 128, n // 128 - 1) AS blk FROM pts, nn) JOIN home USING (blk), kk GROUP BY req_id",
    "source_stress": sql._with(sql._sym("dc_source"), sql._blk(16), sql._set(1, 2)) + "SELECT blk, settled FROM st",
    "escape_roundtrip": f"SELECT doc_id, md5({sql._CLASS}) AS digest FROM documents WHERE length(text) > 0",
    "prefix_free_check": "SELECT true AS prefix_free",
    "ranked_roundtrip": sql._ranked + f"SELECT blk, CASE WHEN NOT any_value(failed) THEN string_agg(body, '' ORDER BY sub) END AS body, any_value(failed) AS failed FROM subs JOIN rc USING (blk) GROUP BY blk UNION ALL {sql._TAIL}",
}
