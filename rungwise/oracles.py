"""DuckDB SQL for the queries that SQL expresses; every level of the codec is a CTE over the source itself."""

from __future__ import annotations

from .queries import LAW_SOURCES, N_EDITS, N_SPANS
from .sources.catalog import SOURCES

ORACLES: dict[str, str] = {}


def _sym(name: str) -> str:
    s = SOURCES[name]
    return f"""sym AS (SELECT row_number() OVER (ORDER BY {", ".join(s.key)}) - 1 AS pos, coalesce(CAST({s.expr} AS VARCHAR), '<null>') AS symbol FROM {s.table}),
law AS (SELECT symbol, count(*) AS c, row_number() OVER (ORDER BY symbol) - 1 AS code FROM sym GROUP BY symbol),
nn AS (SELECT count(*) AS n FROM sym),
coded AS (SELECT pos, chr(CAST(48 + code AS INTEGER)) AS ch FROM sym JOIN law USING (symbol))"""


def _blk(b0: int) -> str:
    return f"""blk AS (SELECT least(pos // {b0}, greatest(n // {b0}, 1) - 1) AS blk, count(*) AS n_sym, string_agg(ch, '' ORDER BY pos) AS body FROM coded, nn GROUP BY 1)"""


def _set(num: int, den: int, table: str = "blk", out: str = "st", key: str = "blk") -> str:
    return f"""{out} AS (SELECT b.*, t.settled FROM {table} b JOIN (SELECT {key}, bool_and(abs((length(body) - length(replace(body, chr(CAST(48 + code AS INTEGER)), ''))) * n - length(body) * c) * {den} <= {num} * length(body) * c) AS settled
  FROM {table}, law, nn GROUP BY {key}) t USING ({key}))"""


def _levels(b0: int, fans=(8, 16), num: int = 1, den: int = 2, base: str = "st", tag: str = "") -> str:
    f1, f2 = fans
    return f"""gr{tag} AS (SELECT s.*, least(s.blk // {f1}, n // {b0} // {f1} - 1) AS g1, least(least(s.blk // {f1}, n // {b0} // {f1} - 1) // {f2}, n // {b0} // {f1} // {f2} - 1) AS g2 FROM {base} s, nn),
l1{tag} AS (SELECT g1, g2, count(*) AS n_child, count(*) FILTER (NOT settled) AS open_count, count(*) FILTER (NOT settled) <= count(*) * {num} // {den * 2} AS settled, coalesce(string_agg(CAST(blk AS VARCHAR), ',' ORDER BY blk) FILTER (NOT settled), '') AS open_children FROM gr{tag} GROUP BY g1, g2),
l2{tag} AS (SELECT g2, count(*) AS n_child, count(*) FILTER (NOT settled) AS open_count, count(*) FILTER (NOT settled) <= count(*) * {num} // {den * 4} AS settled, coalesce(string_agg(CAST(g1 AS VARCHAR), ',' ORDER BY g1) FILTER (NOT settled), '') AS open_children FROM l1{tag} GROUP BY g2),
home{tag} AS (SELECT g.*, l1{tag}.settled AS s1, l2{tag}.settled AS s2, l1{tag}.open_count AS o1, l1{tag}.n_child AS n1, l2{tag}.open_count AS o2, l2{tag}.n_child AS n2, CASE WHEN g.settled THEN 0 WHEN l1{tag}.settled THEN 1 WHEN l2{tag}.settled THEN 2 END AS home FROM gr{tag} g JOIN l1{tag} USING (g1, g2) JOIN l2{tag} USING (g2))"""


def _widths(b0: int, fans=(8, 16), k: int = 2) -> str:
    digit = max(1, k.bit_length())
    slots1, slots2 = fans[0] // 4, fans[1] // 8
    w1, w2 = fans[0] + slots1 * b0 * digit, fans[1] + slots2 * b0 * fans[0] * digit
    return f"""kk AS (SELECT k0, {w1} AS k1, {w2} AS k2, {fans[0]} AS h1, {fans[1]} AS h2, {b0 * digit} AS slot FROM (SELECT CAST(ceil((-sum(CAST(c AS DOUBLE) / n * log2(CAST(c AS DOUBLE) / n)) + 0.5) * {b0}) AS BIGINT) AS k0 FROM law, nn))"""


_FULL = "CASE {h} WHEN 0 THEN k0 WHEN 1 THEN k0 + k1 ELSE k0 + k1 + k2 END"
_SPANS = f"spans AS (SELECT r AS req_id, (r * 7919 + 13) % n AS start, least(1 + (r * 104729) % 97, n - (r * 7919 + 13) % n) AS len FROM (SELECT unnest(range({N_SPANS})) AS r), nn)"


def _touch(b0: int) -> str:
    last = f"greatest(n // {b0}, 1) - 1"
    return f"touch AS (SELECT req_id, start, len, unnest(generate_series(least(start // {b0}, {last}), least((start + len - 1) // {b0}, {last}))) AS blk FROM spans, nn)"


def _edits(b0: int) -> str:
    return f"""ed AS (SELECT k AS edit_id, a.blk, z.body FROM (SELECT k, (k * 7919 + 5) % (n // {b0}) AS tb, (k * 6007 + 11) % (n // {b0}) AS sb FROM (SELECT unnest(range({N_EDITS})) AS k), nn) e JOIN blk a ON a.blk = e.tb JOIN blk z ON z.blk = e.sb WHERE a.n_sym = {b0} AND z.n_sym = {b0})"""


def _with(*parts: str) -> str:
    return "WITH " + ",\n".join(parts) + "\n"


def _demo(*more: str, source="li_small_qty", b0=128, **kw) -> str:
    return _with(_sym(source), _blk(b0), _set(1, 2), _levels(b0), *more)


_all_laws = " UNION ALL ".join(f"SELECT '{n}' AS source, coalesce(CAST({SOURCES[n].expr} AS VARCHAR), '<null>') AS symbol, count(*) AS cnt FROM {SOURCES[n].table} GROUP BY 2" for n in LAW_SOURCES)
ORACLES["alphabet_law"] = _all_laws
ORACLES["source_entropy"] = f"""WITH a AS ({_all_laws}), t AS (SELECT *, sum(cnt) OVER (PARTITION BY source) AS total FROM a)
SELECT source, count(*) AS k, CAST(max(total) AS BIGINT) AS n, round(-sum(cnt / CAST(total AS DOUBLE) * log2(cnt / CAST(total AS DOUBLE))), 6) AS entropy FROM t GROUP BY source"""
ORACLES["dyadic_report"] = f"""WITH a AS ({_all_laws}), t AS (SELECT *, CAST(sum(cnt) OVER (PARTITION BY source) AS BIGINT) AS total FROM a)
SELECT source, bool_and(total % cnt = 0 AND bit_count(total // cnt) = 1) AS dyadic, max(round(log2(CAST(total AS DOUBLE) / cnt), 6)) AS max_self_information FROM t GROUP BY source"""
ORACLES["dense_positions"] = f"SELECT row_number() OVER (ORDER BY {', '.join(SOURCES['li_small_qty'].key)}) - 1 AS pos, l_orderkey, l_partkey FROM lineitem"
ORACLES["block_cut"] = _with(_sym("li_small_qty"), _blk(128)) + "SELECT blk, CAST(n_sym AS INTEGER) AS n_sym, body FROM blk"
ORACLES["block_cut_text"] = """WITH d AS (SELECT doc_id, text, greatest(length(text) // 512, 1) AS nb FROM documents WHERE length(text) > 0),
c AS (SELECT doc_id, text, nb, unnest(range(nb)) AS blk FROM d)
SELECT doc_id AS seq_id, blk, CAST(CASE WHEN blk = nb - 1 THEN length(text) - blk * 512 ELSE 512 END AS INTEGER) AS n_sym, substr(text, blk * 512 + 1, CASE WHEN blk = nb - 1 THEN length(text) - blk * 512 ELSE 512 END) AS body FROM c"""
ORACLES["block_histogram"] = _with(_sym("li_flag"), _blk(32)) + "SELECT blk, " + ", ".join(f"CAST(length(body) - length(replace(body, '{i}', '')) AS BIGINT) AS n{i}" for i in range(3)) + " FROM blk"
ORACLES["block_settled"] = _with(_sym("li_flag"), _blk(32), _set(1, 2)) + "SELECT blk, settled FROM st"
_choose = "choose AS (SELECT n AS r, k, CASE WHEN k = 0 THEN CAST(1 AS HUGEINT) ELSE CAST(list_reduce(list_prepend(CAST(1 AS HUGEINT), list_transform(range(1, k + 1), lambda i: CAST(i AS HUGEINT))), lambda acc, i: acc * (n - k + i) // i) AS HUGEINT) END AS v FROM range(65) t(n), range(65) u(k) WHERE k <= n)"
ORACLES["typical_set_size"] = _with(_sym("li_small_qty"), _choose, "p AS (SELECT c, n FROM law, nn WHERE code = 1)", "q AS (SELECT c AS c0 FROM law WHERE code = 0)") + """SELECT b, min(w) AS low, max(w) AS high, CAST(sum(v) AS VARCHAR) AS size
FROM (SELECT unnest([16, 32, 64]) AS b), choose, p, q, (SELECT unnest(range(65)) AS w)
WHERE r = b AND k = w AND abs(w * n - b * c) * 2 <= b * c AND abs((b - w) * n - b * c0) * 2 <= b * c0 GROUP BY b"""
ORACLES["type_index_b16"] = _with(_sym("li_small_qty"), _blk(16), _set(1, 2), _choose, "ones AS (SELECT blk, i, row_number() OVER (PARTITION BY blk ORDER BY i DESC) AS k FROM (SELECT blk, body, unnest(range(16)) AS i FROM st WHERE settled AND n_sym = 16) WHERE substr(body, i + 1, 1) = '1')", "low AS (SELECT min(w) AS low FROM (SELECT unnest(range(17)) AS w), law, nn WHERE code = 1 AND abs(w * n - 16 * c) * 2 <= 16 * c)", "pl AS (SELECT blk, count(*) AS weight, sum(v) AS place FROM ones JOIN choose ON choose.r = 15 - i AND choose.k = ones.k GROUP BY blk)", "pl2 AS (SELECT o.blk, count(*) AS weight, coalesce(sum(v), 0) AS place FROM ones o LEFT JOIN choose c ON c.r = 15 - o.i AND c.k = o.k GROUP BY o.blk)") + """SELECT blk, CAST((SELECT coalesce(sum(v), 0) FROM choose, low WHERE r = 16 AND k >= low AND k < weight) + place + 1 AS BIGINT) AS idx FROM pl2"""
ORACLES["type_unindex_b16"] = _with(_sym("li_small_qty"), _blk(16), _set(1, 2)) + "SELECT blk, body FROM st WHERE settled AND n_sym = 16"
ORACLES["ladder_level0"] = _demo() + "SELECT blk, CAST(n_sym AS INTEGER) AS n_sym, settled FROM st"
for _i in (1, 2):
    ORACLES[f"ladder_level{_i}"] = _demo() + f"SELECT g{_i} AS grp, n_child, open_count, settled, open_children FROM l{_i}"
_presets = (("demo3", "li_small_qty", 128), ("deep3", "li_small_qty", 64), ("calm", "li_zero_tax", 256), ("flag3", "li_flag", 32))
ORACLES["ladder_home_profile"] = " UNION ALL ".join(f"SELECT '{p}' AS preset, home, blocks FROM ({_demo(source=s, b0=b)} SELECT CAST(coalesce(home, -1) AS INTEGER) AS home, count(*) AS blocks FROM home GROUP BY 1)" for p, s, b in _presets)
ORACLES["ladder_trace"] = _demo(source="li_flag", b0=32) + """SELECT CAST(0 AS INTEGER) AS level, count(*) AS units, count(*) FILTER (NOT settled) AS open_units FROM st UNION ALL
SELECT 1, count(*), count(*) FILTER (NOT settled) FROM l1 UNION ALL SELECT 2, count(*), count(*) FILTER (NOT settled) FROM l2"""
ORACLES["ladder_failures"] = _demo(b0=64) + "SELECT blk, CAST(n_sym AS INTEGER) AS n_sym FROM home WHERE home IS NULL"
ORACLES["ladder_bit_budget"] = _demo(_widths(128)) + """SELECT CAST(0 AS INTEGER) AS level, count(*) AS units, CAST(count(*) * max(k0) AS BIGINT) AS reserved_bits, CAST(count(*) FILTER (settled) * max(k0) AS BIGINT) AS used_bits FROM st, kk UNION ALL
SELECT 1, count(*), CAST(count(*) * max(k1) AS BIGINT), CAST(sum(n_child) + (SELECT coalesce(sum(n_sym * 2), 0) FROM home WHERE home = 1) AS BIGINT) FROM l1, kk UNION ALL
SELECT 2, count(*), CAST(count(*) * max(k2) AS BIGINT), CAST(sum(n_child) + (SELECT coalesce(sum(n_sym * 2), 0) FROM home WHERE home = 2) AS BIGINT) FROM l2, kk"""
ORACLES["ladder_roundtrip"] = _demo() + "SELECT blk, CASE WHEN home IS NOT NULL THEN body END AS body, home IS NULL AS failed FROM home"
_src = "src AS (SELECT string_agg(ch, '' ORDER BY pos) AS s FROM coded)"
ORACLES["ladder_read_spans"] = _with(_sym("li_small_qty"), _src, _SPANS) + "SELECT req_id, start, len, substr(s, start + 1, len) AS value FROM spans, src"
ORACLES["ladder_read_symbols"] = _with(_sym("li_small_qty"), _src, _SPANS) + "SELECT req_id, start, substr(s, start + 1, 1) AS value FROM spans, src"
for _name, _expr in (("full", _FULL.format(h="home")), ("header", "CASE home WHEN 0 THEN k0 WHEN 1 THEN k0 + k1 ELSE k0 + h1 + k2 END"), ("slot", "CASE home WHEN 0 THEN k0 WHEN 1 THEN k0 + h1 + slot ELSE k0 + h1 + h2 + slot END")):
    ORACLES[f"ladder_read_cost_{_name}"] = _demo(_widths(128), _SPANS, _touch(128)) + f"SELECT req_id, CAST(sum({_expr}) AS BIGINT) AS probes, CAST(max(coalesce(home, -1)) AS INTEGER) AS home_max FROM touch JOIN home USING (blk), kk GROUP BY req_id"
ORACLES["ladder_read_cost_shared"] = _demo(_widths(128), _SPANS, _touch(128)) + """, cells AS (SELECT DISTINCT req_id, lv, CASE lv WHEN 0 THEN blk WHEN 1 THEN g1 ELSE g2 END AS cell, CASE lv WHEN 0 THEN k0 WHEN 1 THEN k1 ELSE k2 END AS bits
  FROM (SELECT *, unnest(range(coalesce(home, 2) + 1)) AS lv FROM touch JOIN home USING (blk)), kk) SELECT req_id, count(*) AS cells, CAST(sum(bits) AS BIGINT) AS bits FROM cells GROUP BY req_id"""
ORACLES["ladder_read_cost_shared"] = ORACLES["ladder_read_cost_shared"].replace("\n, cells AS", ", cells AS")
ORACLES["ladder_read_capped"] = _demo(_widths(64), b0=64) + f"SELECT CAST(cap AS INTEGER) AS cap, count(*) AS blocks, count(*) FILTER (coalesce(home, 9) > cap) AS lost, CAST(sum({_FULL.format(h='least(coalesce(home, 9), cap)')}) AS BIGINT) AS probes FROM home, kk, (SELECT unnest([0, 1, 2]) AS cap) GROUP BY cap"
ORACLES["ladder_update_state"] = _with(_sym("li_small_qty"), _blk(64), _edits(64), "last_ed AS (SELECT blk, arg_max(body, edit_id) AS nb FROM ed GROUP BY blk)", "after AS (SELECT blk, n_sym, coalesce(nb, body) AS body FROM blk LEFT JOIN last_ed USING (blk))", _set(1, 2, "after"), _levels(64)) + "SELECT blk, body, settled, CAST(coalesce(home, -1) AS INTEGER) AS home FROM home"
ORACLES["stored_update_state"] = ORACLES["ladder_update_state"]
_COSTS = f"""c1 AS (SELECT e.edit_id, h.blk, h.settled AS so, e.settled AS sn, h.home, o1, n1, s1, o2, n2, s2, CAST(h.settled AS INT) - CAST(e.settled AS INT) AS d1 FROM es e JOIN home h USING (blk)),
c2 AS (SELECT *, o1 + d1 <= n1 * 1 // 4 AS t1 FROM c1), c3 AS (SELECT *, o2 + CAST(s1 AS INT) - CAST(t1 AS INT) <= n2 * 1 // 8 AS t2 FROM c2),
c4 AS (SELECT *, CASE WHEN sn THEN 0 WHEN t1 THEN 1 WHEN t2 THEN 2 END AS nh, (CASE WHEN so THEN 'S' ELSE 'O' END) || (CASE WHEN sn THEN 'S' ELSE 'O' END) AS kind FROM c3),
costs AS (SELECT edit_id, blk, kind, coalesce(home, -1) AS old_home, coalesce(nh, -1) AS new_home,
  CASE kind WHEN 'SS' THEN k0 WHEN 'OO' THEN {_FULL.format(h="coalesce(home, 2)")} ELSE {_FULL.format(h="greatest(coalesce(home, 2), coalesce(nh, 2))")} END AS bits_read,
  CASE kind WHEN 'SS' THEN k0 WHEN 'OO' THEN CASE coalesce(home, 2) WHEN 1 THEN k1 ELSE k2 END ELSE {_FULL.format(h="greatest(coalesce(home, 2), coalesce(nh, 2))")} END AS bits_written FROM c4, kk)"""
_cost = _demo(_widths(128), _edits(128), _set(1, 2, "ed", "es", "edit_id"), _COSTS)
ORACLES["ladder_update_cost"] = _cost + 'SELECT edit_id, blk, kind AS "case", CAST(old_home AS INTEGER) AS old_home, CAST(new_home AS INTEGER) AS new_home, CAST(bits_read AS BIGINT) AS bits_read, CAST(bits_written AS BIGINT) AS bits_written FROM costs'
ORACLES["ladder_update_cases"] = _cost + 'SELECT kind AS "case", count(*) AS edits, CAST(sum(bits_read + bits_written) AS BIGINT) AS bits FROM costs GROUP BY kind'
ORACLES["ladder_cost_rollup"] = _cost + "SELECT coalesce(kind, 'all') AS \"case\", CAST(coalesce(old_home, -9) AS INTEGER) AS old_home, count(*) AS edits FROM costs GROUP BY ROLLUP (kind, old_home)"
ORACLES["top_cost_blocks"] = _demo(_widths(128)) + f"SELECT blk, CAST({_FULL.format(h='home')} AS BIGINT) AS probes FROM home, kk ORDER BY probes DESC, blk LIMIT 20"
ORACLES["span_curve"] = _demo(_widths(128), f"cost AS (SELECT blk, {_FULL.format(h='home')} AS c FROM home, kk)") + """SELECT m * 128 AS span, count(*) AS starts, CAST(sum(c) AS BIGINT) AS sum_probes, CAST(max(c) AS BIGINT) AS max_probes FROM (
  SELECT m, a.blk, sum(b.c) AS c FROM (SELECT unnest([1, 2, 4, 8, 16, 32]) AS m) CROSS JOIN cost a JOIN cost b ON b.blk BETWEEN a.blk AND a.blk + m - 1, nn WHERE a.blk + m <= n // 128 GROUP BY m, a.blk) GROUP BY m"""
ORACLES["eps_curve"] = " UNION ALL ".join(f"SELECT CAST({a * 8 // b} AS INTEGER) AS eps_eighths, blocks, settled FROM ({_with(_sym('li_small_qty'), _blk(512), _set(a, b))} SELECT count(*) AS blocks, count(*) FILTER (settled) AS settled FROM st)" for a, b in ((1, 2), (3, 8), (1, 4)))
_prefix = lambda part: _demo().replace("nn AS (SELECT count(*) AS n FROM sym)", f"full_n AS (SELECT count(*) AS n FROM sym), nn AS (SELECT n // {part} AS n FROM full_n)").replace("law, nn GROUP BY blk", "law, full_n GROUP BY blk").replace("FROM coded, nn GROUP BY 1", "FROM coded, nn WHERE pos < n GROUP BY 1")
ORACLES["n_curve"] = " UNION ALL ".join(f"SELECT n, blocks, home0, home1 FROM ({_prefix(p)} SELECT max(n) AS n, count(*) AS blocks, count(*) FILTER (home = 0) AS home0, count(*) FILTER (home = 1) AS home1 FROM home, nn)" for p in (4, 2, 1))
_CLASS = "regexp_replace(regexp_replace(regexp_replace(regexp_replace(text, '[^A-Za-z ]', '3', 'g'), '[AEIOUaeiou]', '1', 'g'), '[A-Za-z]', '2', 'g'), ' ', '0', 'g')"
ORACLES["order_k_entropy"] = f"WITH d AS (SELECT {_CLASS} AS t FROM documents)" + "".join(f", g{k} AS (SELECT g, count(*) AS n, sum(count(*)) OVER (PARTITION BY substr(g, 1, {k})) AS m FROM (SELECT substr(t, i, {k + 1}) AS g FROM (SELECT t, unnest(generate_series(1, length(t) - {k})) AS i FROM d WHERE length(t) > {k})) GROUP BY g)" for k in range(3)) + " " + " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, round(-sum(n * log2(n / CAST(m AS DOUBLE))) / sum(n), 6) AS entropy, CAST(sum(n) AS BIGINT) AS grams FROM g{k}" for k in range(3))
_ranked = _with(_sym("li_small_qty"), "subs AS (SELECT pos // 1024 AS blk, CAST(pos % 1024 // 64 AS INTEGER) AS sub, pos // 64 AS cell, string_agg(ch, '' ORDER BY pos) AS body FROM coded, nn WHERE pos < n // 1024 * 1024 GROUP BY 1, 2, 3)", _set(1, 2, "subs", "rs", "cell"), _choose, "wb AS (SELECT CAST(ceil(log2(CAST(sum(v) AS DOUBLE))) AS BIGINT) AS w FROM choose, nn, (SELECT c AS c1 FROM law WHERE code = 1), (SELECT c AS c0 FROM law WHERE code = 0) WHERE r = 64 AND abs(k * n - 64 * c1) * 2 <= 64 * c1 AND abs((64 - k) * n - 64 * c0) * 2 <= 64 * c0)", "wd AS (SELECT *, CASE WHEN settled THEN 0 ELSE 1 END AS op, CASE WHEN settled THEN w ELSE 64 END AS len FROM rs, wb)", "wo AS (SELECT *, coalesce(sum(len) OVER p, 0) AS start, coalesce(sum(op) OVER p, 0) AS before FROM wd WINDOW p AS (PARTITION BY blk ORDER BY sub ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))", "rb AS (SELECT blk, CAST(sum(op * (1 << sub)) AS BIGINT) AS flags, sum(op) AS n_open, sum(len) AS used, max(w) AS w FROM wd GROUP BY blk)", "rc AS (SELECT blk, flags, CAST(n_open AS BIGINT) AS n_open, CAST(used + 16 AS BIGINT) AS used_bits, CAST(8 * 64 + 8 * w + 16 AS BIGINT) AS reserved_bits, n_open > 8 OR used > 8 * 64 + 8 * w AS failed FROM rb)")
ORACLES["ranked_flags"] = _ranked + "SELECT blk, sub, CAST(op AS INTEGER) AS open FROM wd"
ORACLES["ranked_lengths"] = _ranked + "SELECT * FROM rc"
ORACLES["ranked_offsets"] = _ranked + "SELECT blk, sub, CAST(len AS BIGINT) AS len, CAST(start AS BIGINT) AS start FROM wo"
ORACLES["ranked_rank_select"] = _ranked + "SELECT blk, sub, CAST(before AS BIGINT) AS rank_before, CAST(op AS BIGINT) AS open, CAST(start AS BIGINT) AS payload_start FROM wo"
ORACLES["ranked_read_cost"] = _ranked + "SELECT CAST(op AS BIGINT) AS open, count(*) AS reads, CAST(max(16 + len) AS BIGINT) AS worst, CAST(sum(16 + len) AS BIGINT) AS bits FROM wd GROUP BY op"
ORACLES["ranked_errors"] = _ranked + "SELECT count(*) AS blocks, count(*) FILTER (failed) AS failed, CAST(sum(used_bits) AS BIGINT) AS used_bits, CAST(sum(reserved_bits) AS BIGINT) AS reserved_bits FROM rc"
_TAIL = "SELECT n // 1024 AS blk, string_agg(ch, '' ORDER BY pos) AS body, false AS failed FROM coded, nn WHERE pos >= n // 1024 * 1024 GROUP BY n"
ORACLES["ranked_read_spans"] = _ranked.rstrip() + ", " + _src + ", " + _SPANS + """, parts AS (SELECT req_id, sum(16 + wd.len) AS c FROM spans JOIN wd ON cell BETWEEN spans.start // 64 AND (spans.start + spans.len - 1) // 64 GROUP BY 1)
SELECT req_id, spans.start, spans.len, CASE WHEN NOT EXISTS (SELECT 1 FROM rc WHERE failed AND rc.blk BETWEEN spans.start // 1024 AND (spans.start + spans.len - 1) // 1024) THEN substr(s, spans.start + 1, spans.len) ELSE (SELECT coalesce(string_agg(ch, '' ORDER BY pos), '') FROM coded LEFT JOIN rc ON rc.blk = pos // 1024 WHERE pos >= spans.start AND pos < spans.start + spans.len AND NOT coalesce(failed, false)) END AS value,
  CAST(coalesce(c, 0) + greatest(spans.start + spans.len - greatest(spans.start, n // 1024 * 1024), 0) AS BIGINT) AS probes FROM spans LEFT JOIN parts USING (req_id), src, nn"""
ORACLES["ranked_select"] = _ranked + "SELECT blk, CAST(row_number() OVER (PARTITION BY blk ORDER BY sub) AS INTEGER) AS k, CAST(sub AS INTEGER) AS sub FROM wd WHERE op = 1"
_ranked_edits = f""", ee AS (SELECT k AS edit_id, (k * 7919 + 5) % (n // 1024 * 16) AS t, (k * 6007 + 11) % (n // 1024 * 16) AS s FROM (SELECT unnest(range({N_EDITS})) AS k), nn),
last_e AS (SELECT t, arg_max(z.body, edit_id) AS nb FROM ee JOIN subs z ON z.cell = s JOIN rc ON rc.blk = z.blk WHERE NOT rc.failed GROUP BY t),
after AS (SELECT subs.blk, sub, cell, CASE WHEN f.failed THEN body ELSE coalesce(nb, body) END AS body FROM subs JOIN rc f ON f.blk = subs.blk LEFT JOIN last_e ON t = cell)"""
ORACLES["ranked_update_state"] = _ranked.rstrip() + _ranked_edits + ", " + _set(1, 2, "after", "ra", "cell") + f""", am AS (SELECT ra.blk, count(*) FILTER (NOT settled) > 8 OR sum(CASE WHEN settled THEN w ELSE 64 END) > 8 * 64 + 8 * max(w) AS bad, string_agg(body, '' ORDER BY sub) AS body FROM ra, wb GROUP BY ra.blk)
SELECT am.blk, CASE WHEN NOT (bad OR rc.failed) THEN body END AS body, bad OR rc.failed AS failed FROM am JOIN rc ON rc.blk = am.blk UNION ALL {_TAIL}"""
ORACLES["ranked_update_cost"] = _ranked.rstrip() + f""", ee AS (SELECT k AS edit_id, (k * 7919 + 5) % (n // 1024 * 16) AS t, (k * 6007 + 11) % (n // 1024 * 16) AS s FROM (SELECT unnest(range({N_EDITS})) AS k), nn)
SELECT edit_id, a.blk, a.sub, (CASE WHEN a.settled THEN 'S' ELSE 'O' END) || (CASE WHEN z.settled THEN 'S' ELSE 'O' END) AS "case", CAST(CASE WHEN a.settled = z.settled THEN 16 + 2 * a.len ELSE 32 + 2 * used - a.len + z.len END AS BIGINT) AS bits
FROM ee JOIN wd a ON a.cell = t JOIN wd z ON z.cell = s JOIN rb ON rb.blk = a.blk"""
ORACLES["flat_profile"] = _demo(_widths(128)) + "SELECT NOT settled AS failed, count(*) AS blocks, CAST(sum(k0) AS BIGINT) AS bits FROM st, kk GROUP BY 1"
ORACLES["flat_read_update_cost"] = _demo(_widths(128), _SPANS, _touch(128)) + "SELECT req_id, CAST(sum(k0) AS BIGINT) AS read_bits, CAST(sum(2 * k0) AS BIGINT) AS update_bits FROM touch, kk GROUP BY req_id"
ORACLES["raw_cost"] = _with(_sym("li_flag"), _SPANS) + "SELECT req_id, len * 2 AS read_bits FROM spans"
ORACLES["syndrome_store"] = _with(_sym("li_small_qty"), _blk(128), "one AS (SELECT blk, pos % 128 AS j FROM coded, blk WHERE false UNION ALL SELECT blk, i FROM (SELECT blk, body, unnest(range(128)) AS i FROM blk WHERE n_sym = 128) WHERE substr(body, i + 1, 1) = '1')", "cols AS (SELECT j, bit_or(CAST(1 AS BIGINT) << CAST((7919 * (j + 1) + 104729 * (t + 1) * (j + 3) + 31 * t) % 60 AS INTEGER)) AS m FROM range(128) a(j), range(3) b(t) GROUP BY j)") + "SELECT b.blk, coalesce(s, 0) AS syndrome FROM (SELECT blk FROM blk WHERE n_sym = 128) b LEFT JOIN (SELECT blk, bit_xor(m) AS s FROM one JOIN cols USING (j) GROUP BY blk) x USING (blk)"
_cols = "cols AS (SELECT j, bit_or(CAST(1 AS BIGINT) << CAST((7919 * (j + 1) + 104729 * (t + 1) * (j + 3) + 31 * t) % 60 AS INTEGER)) AS m FROM range(128) a(j), range(3) b(t) GROUP BY j)"
ORACLES["syndrome_update_bits"] = _with(_sym("li_small_qty"), _blk(128), _cols, "ed AS (SELECT blk, (blk * 7919 + 5) % 128 AS spot, body FROM blk WHERE n_sym = 128)", "forms AS (SELECT blk, 0 AS side, body FROM ed UNION ALL SELECT blk, 1, substr(body, 1, spot) || CASE WHEN substr(body, spot + 1, 1) = '1' THEN '0' ELSE '1' END || substr(body, spot + 2) FROM ed)", "syn AS (SELECT blk, side, bit_xor(m) AS s FROM (SELECT blk, side, body, unnest(range(128)) AS j FROM forms) JOIN cols USING (j) WHERE substr(body, j + 1, 1) = '1' GROUP BY blk, side)") + 'SELECT spot AS "column", CAST(bit_count(xor(coalesce(x.s, 0), coalesce(y.s, 0))) AS BIGINT) AS bits, count(*) AS edits FROM ed LEFT JOIN syn x ON x.blk = ed.blk AND x.side = 0 LEFT JOIN syn y ON y.blk = ed.blk AND y.side = 1 GROUP BY 1, 2'
ORACLES["codec_scoreboard"] = _demo(_widths(128)) + f"SELECT 'ladder' AS codec, CAST(sum(n_sym * {_FULL.format(h='home')}) AS BIGINT) AS read_bits, count(*) FILTER (home IS NULL) AS failed_blocks FROM home, kk UNION ALL SELECT 'flat', CAST(sum(n_sym * k0) AS BIGINT), count(*) FILTER (NOT settled) FROM home, kk UNION ALL SELECT 'raw', CAST(sum(n_sym) AS BIGINT), 0 FROM home"
ORACLES["gene_fetch"] = "SELECT doc_id, (doc_id * 7919 + 13) % (length(text) - 63) AS start, substr(text, (doc_id * 7919 + 13) % (length(text) - 63) + 1, 64) AS value FROM documents WHERE length(text) >= 64"
ORACLES["page_fetch"] = "SELECT page_id, substr(html, (page_id * 7919) % greatest(length(html) - 50, 1) + 1, 50) AS value FROM pages"
ORACLES["doc_splice"] = "SELECT doc_id, md5(substr(text, 1, p) || repeat('.', 20) || substr(text, p + 21)) AS digest FROM (SELECT doc_id, text, (doc_id * 7919) % (length(text) - 19) AS p FROM documents WHERE length(text) >= 40)"
ORACLES["role_stress"] = _with(_sym("cv_role"), _blk(16), _set(1, 2)) + "SELECT blk, settled FROM st"
ORACLES["edit_windows_tumbling"] = "SELECT date_trunc('day', ts) AS start, count(*) AS edits, count(DISTINCT user_id) AS users FROM events GROUP BY 1"
ORACLES["edit_windows_sliding"] = "SELECT start, count(*) AS edits FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL (6 * i) HOUR FOR i IN range(4)]) AS start FROM events) GROUP BY start"
ORACLES["edit_asof"] = "SELECT event_id, coalesce(before, -1) AS before FROM (SELECT event_id, event_type, lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS before FROM events) WHERE event_type = 'purchase'"
ORACLES["edit_windows_session"] = """WITH marked AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events),
told AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM marked) SELECT user_id, min(ts) AS start, count(*) AS edits FROM told GROUP BY user_id, sid"""
ORACLES["escape_rate"] = f"""WITH d AS (SELECT doc_id, {_CLASS} AS t FROM documents WHERE length(text) > 0),
law AS (SELECT code, CAST(sum(length(t) - length(replace(t, CAST(code AS VARCHAR), ''))) AS BIGINT) AS c FROM d, range(4) r(code) GROUP BY code), nn AS (SELECT CAST(sum(c) AS BIGINT) AS n FROM law),
b AS (SELECT doc_id, t, greatest(length(t) // 256, 1) AS nb, unnest(range(greatest(length(t) // 256, 1))) AS blk FROM d),
bb AS (SELECT doc_id, blk, substr(t, blk * 256 + 1, CASE WHEN blk = nb - 1 THEN length(t) - blk * 256 ELSE 256 END) AS body FROM b),
ok AS (SELECT doc_id, blk, any_value(length(body)) AS len, bool_and(abs((length(body) - length(replace(body, CAST(code AS VARCHAR), ''))) * n - length(body) * c) * 2 <= length(body) * c) AS s FROM bb, law, nn GROUP BY doc_id, blk),
kk AS (SELECT CAST(ceil((-sum(CASE WHEN c > 0 THEN CAST(c AS DOUBLE) / n * log2(CAST(c AS DOUBLE) / n) ELSE 0 END) + 0.5) * 256) AS BIGINT) AS k0 FROM law, nn)
SELECT doc_id, CAST(sum(len) AS BIGINT) AS n, bool_and(s) AS fits, CAST(1 + CASE WHEN bool_and(s) THEN count(*) * max(k0) ELSE sum(len) * 2 END AS BIGINT) AS bits FROM ok, kk GROUP BY doc_id"""


def _lz(width: int, table: str = "blk", tag: str = "") -> str:
    """LZ78 bits of every body: a step a symbol, the book of phrases as a list."""
    return f"""lz{tag} AS (SELECT blk, body, 1 AS i, '' AS cur, CAST([] AS VARCHAR[]) AS book, CAST(0 AS BIGINT) AS bits FROM {table}
  UNION ALL SELECT blk, body, i + 1, CASE WHEN known THEN nxt ELSE '' END, CASE WHEN known THEN book ELSE list_append(book, nxt) END, bits + CASE WHEN known THEN 0 ELSE CAST(ceil(log2(len(book) + 1)) AS BIGINT) + {width} END
  FROM (SELECT *, cur || substr(body, i, 1) AS nxt, list_contains(book, cur || substr(body, i, 1)) AS known FROM lz{tag} WHERE i <= length(body))),
lzb{tag} AS (SELECT blk, length(body) AS n_sym, bits + CASE WHEN cur <> '' THEN CAST(ceil(log2(len(book) + 1)) AS BIGINT) ELSE 0 END AS bits FROM lz{tag} WHERE i = length(body) + 1)"""


_recursive = lambda *parts: _with(*parts).replace("WITH ", "WITH RECURSIVE ", 1)
ORACLES["lz78_length"] = _recursive(_sym("li_flag"), _blk(64), _lz(2)) + "SELECT blk, bits FROM lzb"
ORACLES["spill_probe_levels"] = _recursive(_sym("li_small_qty"), _blk(128), _lz(1), "s0 AS (SELECT blk AS u, bits AS len FROM lzb)", "s1 AS (SELECT u // 8 AS u, sum(greatest(len - 80, 0)) AS len FROM s0 GROUP BY 1)", "s2 AS (SELECT u // 8 AS u, sum(greatest(len - 120, 0)) AS len FROM s1 GROUP BY 1)") + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS level, count(*) AS units, CAST(sum(least(len, {k})) AS BIGINT) AS kept_bits, CAST(sum(greatest(len - {k}, 0)) AS BIGINT) AS spilled_bits FROM s{i}" for i, k in enumerate((80, 120, 160)))
ORACLES["addressed_overhead"] = _recursive(_sym("li_small_qty"), _blk(128), _lz(1)) + 'SELECT count(*) AS words, CAST(sum(bits) AS BIGINT) AS bits, CAST(sum(bits) AS BIGINT) AS "end" FROM lzb'
ORACLES["settled_mass_vs_exact"] = _with(_sym("li_small_qty"), _blk(128), _set(1, 2), "p AS (SELECT c, n, CAST(c AS DOUBLE) / n AS p FROM law, nn WHERE code = 1)", "q AS (SELECT c AS c0 FROM law WHERE code = 0)", "w AS (SELECT w, exp(lgamma(129) - lgamma(w + 1) - lgamma(129 - w) + w * ln(p) + (128 - w) * ln(1 - p)) AS m FROM p, q, range(129) t(w) WHERE abs(w * n - 128 * c) * 2 <= 128 * c AND abs((128 - w) * n - 128 * c0) * 2 <= 128 * c0)") + "SELECT (SELECT count(*) FROM st WHERE n_sym = 128) AS blocks, (SELECT count(*) FROM st WHERE settled AND n_sym = 128) AS settled, min(w) AS low, max(w) AS high, round(sum(m), 6) AS exact FROM w"
ORACLES["ladder_rate_vs_bound"] = " UNION ALL ".join(f"""SELECT '{p}' AS preset, round(h, 6) AS entropy, round(rate, 6) AS rate, round(h + 0.5 * (2 + log2({k} + 1)), 6) AS bound, rate <= h + 0.5 * (2 + log2({k} + 1)) AS holds FROM ({_with(_sym(src), _widths(b0, k=k))} SELECT max(h) AS h, max(CAST(k0 AS DOUBLE) / {b0} + CASE WHEN n // {b0} // 8 >= 1 THEN CAST(k1 AS DOUBLE) / {8 * b0} ELSE 0 END + CASE WHEN n // {b0} // 8 // 16 >= 1 THEN CAST(k2 AS DOUBLE) / {128 * b0} ELSE 0 END) AS rate FROM kk, nn, (SELECT -sum(CAST(c AS DOUBLE) / n * log2(CAST(c AS DOUBLE) / n)) AS h FROM law, nn))""" for p, src, b0, k in (("demo3", "li_small_qty", 128, 2), ("calm", "li_zero_tax", 256, 2), ("flag3", "li_flag", 32, 3)))


def _universal(table: str = "blk", *before: str) -> str:
    """The universal preset: blocks of 256 whose LZ bits fit words of entropy plus 0.4 bits a symbol, and their groups."""
    words = _widths(256).replace("+ 0.5)", "+ 0.4)")
    fits = f"st AS (SELECT a.*, z.bits <= k0 * a.n_sym // 256 - 1 AS settled FROM {table} a JOIN lzb z USING (blk), kk)"
    return _recursive(_sym("li_zero_tax"), _blk(256), words, *before, _lz(1, table), fits, _levels(256)).rstrip()


_after = "after AS (SELECT blk, n_sym, coalesce(nb, body) AS body FROM blk LEFT JOIN (SELECT blk, arg_max(body, edit_id) AS nb FROM ed GROUP BY blk) USING (blk))"
_edit_fits = "es AS (SELECT e.*, z.bits <= k0 * length(e.body) // 256 - 1 AS settled FROM ed e JOIN lzbe z ON z.blk = e.edit_id, kk)"
ORACLES["lz_settled"] = _universal() + " SELECT blk, settled FROM home"
ORACLES["lz_fixed_word"] = _universal() + " SELECT blk, CAST(k0 * n_sym // 256 AS BIGINT) AS bits, n_sym AS raw_bits, true AS same FROM home, kk WHERE settled"
ORACLES["universal_ladder_profile"] = _universal() + " SELECT CAST(coalesce(home, -1) AS INTEGER) AS home, count(*) AS blocks, CAST(sum(n_sym) AS BIGINT) AS symbols FROM home GROUP BY 1"
ORACLES["universal_roundtrip"] = _universal() + " SELECT blk, body, home IS NULL AS escaped FROM home"
ORACLES["universal_read_spans"] = _universal() + f""", {_src}, {_SPANS}, {_touch(256)}, got AS (SELECT req_id, start, len, bool_or(home IS NULL) AS failed, max(coalesce(home, -1)) AS home_max, sum({_FULL.format(h="home")}) AS probes FROM touch JOIN home USING (blk), kk GROUP BY req_id, start, len)
SELECT req_id, start, len, CASE WHEN NOT failed THEN substr(s, start + 1, len) END AS value, CAST(home_max AS INTEGER) AS home_max, CAST(probes AS BIGINT) AS probes_full FROM got, src"""
ORACLES["universal_update_state"] = _universal("after", _edits(256), _after) + " SELECT blk, body, settled, CAST(coalesce(home, -1) AS INTEGER) AS home FROM home"
ORACLES["universal_update_cost"] = _universal() + f""", {_edits(256)}, {_lz(1, "(SELECT edit_id AS blk, body FROM ed)", "e")}, {_edit_fits}, {_COSTS}
SELECT edit_id, blk, kind AS "case", CAST(old_home AS INTEGER) AS old_home, CAST(new_home AS INTEGER) AS new_home, CAST(bits_read AS BIGINT) AS bits_read, CAST(bits_written AS BIGINT) AS bits_written FROM costs"""
