"""Main text against a plain reading of the article element, on the pages as they are and without what marks their parts."""

import html
import re

import duckdb
import pytest

from symbits.llm import htmlmain, queries

SF = "/root/testdata/sf0.01"
BLOCK = re.compile(r"</?(?:h[1-6]|p|li|ul|ol|div|blockquote|pre|table|tr|td|section|figure|figcaption)\b[^>]*>")


def _plain(page):
    """Blocks of the article element, by their tags alone."""
    body = re.search(r"<article>(.*?)(?:</article>|$)", page, re.S)[1]
    parts = [re.sub(r"<[^>]*>", "", re.sub(r"<!--.*?-->", "", re.sub(r"<br\s*/?>", " ", x), flags=re.S)) for x in BLOCK.split(body)]
    return "\n".join(x for x in (" ".join(html.unescape(x).split()) for x in parts) if x)


@pytest.fixture(scope="module")
def pages():
    return [r[0] for r in duckdb.sql(f"SELECT html FROM '{SF}/pages.parquet' ORDER BY page_id").fetchall() if r[0] and "<article>" in r[0]]


VARIANTS = {
    "as they are": (lambda p: p, 1.0),
    "div for article": (lambda p: p.replace("<article>", "<div>").replace("</article>", "</div>"), 1.0),
    "no class names": (lambda p: p.replace(' class="ad"', ""), 0.99),
    "a note beside the article": (lambda p: p.replace("<footer>", "<div><p>Short note, with a comma.</p></div><footer>"), 0.99),
    "a teaser article": (lambda p: p.replace("<article>", "<article><h3><a href=x>Other</a></h3></article><article>", 1), 0.9),
    "neither article nor class names": (lambda p: p.replace("<article>", "<section>").replace("</article>", "</section>").replace(' class="ad"', ""), 0.8),
}


@pytest.mark.parametrize("name", VARIANTS)
def test_pages(pages, name):
    change, least = VARIANTS[name]
    same = [htmlmain.main_text(change(p)) == _plain(p) for p in pages]
    assert len(pages) == 250 and sum(same) >= least * len(same)


def test_ratios_decide(pages, monkeypatch):
    """Without the thresholds on ratios, unmarked parts come in: they are what keeps them out."""
    change, _ = VARIANTS["no class names"]
    monkeypatch.setattr(htmlmain, "THRESHOLD", 0.0)
    monkeypatch.setattr(htmlmain, "HEADING", 0.0)
    assert sum(htmlmain.main_text(change(p)) == _plain(p) for p in pages) < 0.2 * len(pages)


def test_query(spark, pages):
    rows = {r.page_id: r for r in queries.op6_main_text(spark, SF).collect()}
    whole = duckdb.sql(f"SELECT page_id, url, html FROM '{SF}/pages.parquet'").fetchall()
    assert len(rows) == len(whole)
    for key, url, page in whole:
        assert (rows[key].url, rows[key].text, rows[key].n_chars) == (url, _plain(page), len(_plain(page)))
