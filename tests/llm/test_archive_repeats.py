"""A page_id that repeats with another payload makes no records of its own."""

from __future__ import annotations

from passage_engine.llm import warc


def test_repeated_page_with_two_payloads(spark):
    rows = [(3, "u", "one"), (3, "u", "two"), (5, "u", "one"), (6, "u", "two"), (2, "u", "two")]
    pages = spark.createDataFrame([(*r, "x", 1) for r in rows], "page_id long, url string, html string, of string, first int")
    got = sorted((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in warc.archive(pages).collect())
    assert got == sorted([(2, 3, "response", None), (3, 3, "response", None), (3, 3, "revisit", 2), (5, 3, "revisit", 3), (6, 3, "revisit", 2)], key=lambda r: (r[0], r[1], r[2]))
