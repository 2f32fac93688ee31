"""Thin queries over the operators, and DuckDB SQL for those that SQL expresses."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontamination, html_wrappers, image_descriptors, language_id, line_dedup, packing, repeated_phrases, sanitize, sharding, simhash
from .common import table


def op1_label_propagation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(table(spark, sf_dir, "documents"))


def op2_disclosing_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sanitize.find_personal_data(table(spark, sf_dir, "documents")).drop("rk")


def op3_wu_manber(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_image_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return image_descriptors.image_copies(table(spark, sf_dir, "embeddings"))


def op5_repeated_phrases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_phrases.remove_repeats(table(spark, sf_dir, "documents"), with_text=False)


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.hex_digits(found["fp"]).alias("fingerprint"), "component_id")


def op7_page_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_wrappers.extract(table(spark, sf_dir, "pages"))


def op8_tiered_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def op9_site_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.remove_boilerplate(table(spark, sf_dir, "documents")).drop("kept_text")


def op10_language_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_label_propagation, op2_disclosing_terms, op3_wu_manber, op4_image_copies, op5_repeated_phrases, op6_simhash, op7_page_wrappers, op8_tiered_packing, op9_site_spread, op10_language_codes)
}

_FOLD_WORDS = r"regexp_extract_all(translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

ORACLES: dict[str, str] = {
    "op3_wu_manber": f"""
WITH docs AS (SELECT doc_id, row_number() OVER () AS r, {_FOLD_WORDS.format("coalesce(text, '')")} AS w FROM documents),
items AS (SELECT item_id, {_FOLD_WORDS.format("coalesce(text, '')")} AS w FROM benchmark),
windows AS (
  SELECT DISTINCT item_id, least(13, len(w)) AS size, list_slice(w, i, i + least(13, len(w)) - 1) AS win
  FROM (SELECT *, unnest(generate_series(1, len(w) - least(13, len(w)) + 1)) AS i FROM items WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT size FROM windows),
places AS (
  SELECT doc_id, r, size, i, list_slice(w, i, i + size - 1) AS win
  FROM (SELECT doc_id, r, w, size, unnest(generate_series(1, len(w) - size + 1)) AS i FROM docs, sizes WHERE len(w) >= size)),
found AS (SELECT p.doc_id, p.r, p.size, p.i, x.item_id FROM places p JOIN windows x ON p.size = x.size AND p.win = x.win),
hits AS (SELECT r, count(DISTINCT pos) AS n_hit FROM (SELECT r, unnest(generate_series(i, i + size - 1)) AS pos FROM found) GROUP BY r),
named AS (SELECT r, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS names FROM (SELECT DISTINCT r, CAST(item_id AS VARCHAR) AS item_id FROM found) GROUP BY r)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(d.w) AS contaminated
FROM docs d LEFT JOIN hits h ON d.r = h.r LEFT JOIN named m ON d.r = m.r""",
    "op5_repeated_phrases": r"""
WITH docs AS (SELECT doc_id, row_number() OVER () AS r, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
wins AS (SELECT doc_id, r, i, md5(array_to_string(list_slice(w, i, i + 49), ' ')) AS h
  FROM (SELECT *, unnest(generate_series(1, len(w) - 49)) AS i FROM docs WHERE len(w) >= 50)),
least AS (SELECT h, min(doc_id) AS owner FROM wins GROUP BY h),
gone AS (SELECT DISTINCT r, pos FROM (SELECT r, unnest(generate_series(i, i + 49)) AS pos FROM wins JOIN least USING (h) WHERE owner < doc_id)),
lists AS (SELECT r, list(pos) AS spots FROM gone GROUP BY r),
kept AS (SELECT d.r, string_agg(d.word, ' ' ORDER BY d.pos) AS body
  FROM (SELECT r, unnest(w) AS word, unnest(generate_series(1, len(w))) AS pos FROM docs) d LEFT JOIN gone g ON d.r = g.r AND d.pos = g.pos WHERE g.r IS NULL GROUP BY d.r)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(len(l.spots), 0) AS BIGINT) AS n_removed, sha256(coalesce(k.body, '')) AS kept_sha256
FROM docs d LEFT JOIN lists l ON d.r = l.r LEFT JOIN kept k ON d.r = k.r""",
    "op9_site_spread": """
WITH docs AS (SELECT doc_id, row_number() OVER () AS r, source, text, string_split(text, chr(10)) AS ls FROM documents),
lines AS (SELECT r, source, unnest(ls) AS raw, unnest(generate_series(1, len(ls))) AS pos FROM docs WHERE text IS NOT NULL),
bad AS (SELECT trim(raw, ' ') AS line FROM lines WHERE trim(raw, ' ') <> '' GROUP BY 1 HAVING count(DISTINCT source) >= 10),
judged AS (SELECT l.*, b.line IS NOT NULL AS gone FROM lines l LEFT JOIN bad b ON trim(l.raw, ' ') = b.line),
kept AS (SELECT r, count(*) AS n_lines, count(*) FILTER (gone) AS n_removed, coalesce(string_agg(raw, chr(10) ORDER BY pos) FILTER (NOT gone), '') AS body FROM judged GROUP BY r)
SELECT doc_id, CAST(coalesce(n_lines, 0) AS BIGINT) AS n_lines, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(body, '')) AS kept_sha256
FROM docs d LEFT JOIN kept k ON d.r = k.r""",
}
