"""What the ratios of lines decide in pages of several regions, and long and odd pages."""

from __future__ import annotations

import numpy as np

from passage_engine.llm import html_text

LONG = "many words of the text in one line " * 6


def test_headline_and_lead_beside_the_article_stay():
    links = "<ul><li><a href=x>more</a><li><a href=y>less</a><li><a href=z>next</a></ul>"
    page = f"<body><main><h1>{LONG}A</h1><p>{LONG}B</p>{links}<article>" + f"<p>{LONG}C</p>" * 6 + "<p>Short end.</p></article></main></body>"
    got = html_text.main_text(page).split("\n\n")
    assert [x[-1] for x in got[:2]] == ["A", "B"] and got[2:] == [f"{LONG}C"] * 6 + ["Short end."]


def test_parts_of_an_article_in_sibling_elements_stay():
    page = "<body>" + "".join(f"<article><p>{LONG}{c}</p><p>{LONG}{c}</p></article>" for c in "ABC") + "<article><a href=x>next</a></article></body>"
    got = html_text.main_text(page).split("\n\n")
    assert [x[-1] for x in got] == list("AABBCC")


def test_the_clusters_decide(monkeypatch):
    menu = "".join(f"<div><a href=x>{w}</a> <a href=y>{w}</a></div>" for w in ("one", "two", "three"))
    page = f"<body>{menu}" + "".join(f"<p>{LONG}{c}</p>" for c in "ABCDEF") + f"{menu}</body>"
    want = html_text.main_text(page)
    assert {x[-1] for x in want.split("\n\n")} <= set("ABCDEF") and "one one" not in want
    monkeypatch.setattr(html_text, "content_lines", lambda lines: np.ones(len(lines), bool))
    assert html_text.main_text(page) != want


def test_long_page_empty_table_and_clashing_columns(spark):
    rows = [(1, "u", "<body><article>" + "".join(f"<p>{LONG}{i}</p>" for i in range(3000)) + "</article></body>", "t", 7), (2, None, None, None, None), (3, "u", "", "t", 1)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars long")
    got = {r.page_id: r for r in html_text.extract(pages).collect()}
    assert len(got[1].text.split("\n\n")) == 3000 and got[1].n_chars == len(got[1].text) > 600_000
    assert got[2].text == "" and got[2].url is None and got[3].n_chars == 0
    assert html_text.extract(pages.limit(0)).count() == 0
