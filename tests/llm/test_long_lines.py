"""Boilerplate lines of any length."""

from rungwise.llm import line_dedup

NOTICE = "This notice is the same on every site and has far more characters than a short menu line. " * 3


def test_long_notice_goes_on_both_routes(spark, monkeypatch):
    rows = [(i, f"own text {i}\n {NOTICE}\nrare {NOTICE}{i % 9}", f"s{i}") for i in range(14)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    want = {i: f"own text {i}\nrare {NOTICE}{i % 9}" for i, _, _ in rows}
    assert {r.doc_id: r.text for r in line_dedup.without_boilerplate(docs).collect()} == want
    monkeypatch.setattr(line_dedup, "SHIPPED_BYTES", 10)
    assert {r.doc_id: r.text for r in line_dedup.without_boilerplate(docs).collect()} == want


def test_query_judges_long_lines_too(spark, monkeypatch):
    docs = spark.createDataFrame([(i, f"own text {i}\n {NOTICE}\nrare {NOTICE}{i % 9}", f"s{i}") for i in range(14)], "doc_id long, text string, source string")
    one = sorted(map(tuple, line_dedup.remove_boilerplate(docs).collect()))
    assert all(r[1:3] == (3, 1) for r in one)
    monkeypatch.setattr(line_dedup, "SHIPPED_BYTES", 10)
    assert sorted(map(tuple, line_dedup.remove_boilerplate(docs).collect())) == one
