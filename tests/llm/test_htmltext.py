"""Main text: the cut decides, names are evidence, broken pages are linear."""

import time

import pytest
from pyspark.sql import functions as F

from cellgraph.llm import htmltext

SENTENCE = "It was written that the long winter of that year had closed every road to the northern villages for weeks."


def _page(body):
    return f"<html><head><title>t</title><script>var a=1;</script></head><body>{body}</body></html>"


def test_names_that_only_look_like_boilerplate():
    for name in ("related-work", "share-price", "search-theory", "social-history", "comment-free-zone"):
        page = _page(f'<article><h1>Title of it</h1><p>{SENTENCE}</p><div class="{name}"><p>{SENTENCE} Again.</p></div></article>')
        assert htmltext.extract(page) == f"Title of it\n{SENTENCE}\n{SENTENCE} Again.", name
    for name in ("share-bar", "comments", "ad", "ad-slot", "related-posts", "cookie-notice", "sidebar", "newsletter-box"):
        page = _page(f'<article><h1>Title of it</h1><p>{SENTENCE}</p></article><div class="{name}"><p>Click now</p><p><a href="x">More of it</a></p></div>')
        assert htmltext.extract(page) == f"Title of it\n{SENTENCE}", name


def test_the_cut_overrules_single_blocks():
    """A two-word paragraph amid an article without an article tag, and a sentence amid link lists."""
    kept = _page(f"<div><p>{SENTENCE}</p><div>So ended</div><p>{SENTENCE}</p></div>")
    assert htmltext.extract(kept) == f"{SENTENCE}\nSo ended\n{SENTENCE}"
    links = "".join(f'<li><a href="/{i}">Another page {i}</a></li>' for i in range(3))
    dropped = _page(f"<ul>{links}<li>See all of the other pages here.</li>{links}</ul><div><p>{SENTENCE}</p></div>")
    assert htmltext.extract(dropped) == SENTENCE
    for page in (kept, dropped):
        blocks = htmltext.blocks_of(page)
        odds, edges = htmltext.page_costs(blocks, htmltext.Weights())
        assert htmltext.min_cut(odds, edges) != [o > 0 for o in odds]
        assert htmltext.cut_effect(page)[1] >= 1


def test_max_flow_runs(monkeypatch):
    calls = []
    inner = htmltext._source_side
    monkeypatch.setattr(htmltext, "_source_side", lambda *a: calls.append(1) or inner(*a))
    htmltext.extract(_page(f"<div><p>{SENTENCE}</p><div>So ended</div><div>Or not</div><p>{SENTENCE}</p></div>"))
    assert calls


def test_unclosed_elements_are_linear():
    for tag in ("svg", "noscript", "object"):
        began = time.perf_counter()
        assert htmltext.extract(f"<article><p>{SENTENCE}</p></article>" + f"<{tag}>" * 40_000).startswith(SENTENCE)
        assert time.perf_counter() - began < 5


def test_hidden_and_controls():
    page = _page(f'<article><p>{SENTENCE}</p><p style="display:none">{SENTENCE} Two.</p><form><label>Your name</label><select><option>A</option></select></form></article>')
    assert htmltext.extract(page) == f"{SENTENCE}\n{SENTENCE} Two."


def _truth(html):
    """Article text of the given tables' pages, by string search: they have one article each."""
    import re
    from html import unescape

    inside = re.search(r"<article>(.*)</article>", html, re.S)[1]
    parts = re.split(r"<(?:/?p|/?h1)>", inside)
    lines = (" ".join(unescape(re.sub(r"<[^>]*>", lambda m: " " if m[0].startswith("<br") else "", x)).split()) for x in parts)
    return "\n".join(x for x in lines if x)


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_pages_against_their_article_tags(spark, sf):
    pages = spark.read.parquet(f"/root/testdata/{sf}/pages.parquet")
    want = {r["page_id"]: _truth(r["html"]) for r in pages.collect()}
    got = {r["page_id"]: r["text"] for r in htmltext.extract_text(pages).collect()}
    assert got == want


def test_fit_moves_and_keeps_weights(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    fitted, prior = htmltext.fit_weights(pages), htmltext.Weights()
    assert fitted.text != prior.text and fitted.text[htmltext.TEXT_FEATURES.index("linked")] < 0 < fitted.text[htmltext.TEXT_FEATURES.index("long")]
    assert htmltext.fit_weights(pages.where("false")) == prior == htmltext.fit_text_weights({(1, 1): 5})


def test_awkward_rows(spark):
    rows = [(1, "u", None), (1, "u", None), (None, None, ""), (2, "v", "<p>" * 100_000), (3, "w", "plain text only, without any markup at all.")]
    got = htmltext.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("x"))).collect()
    assert sorted((r["page_id"] or 0, r["text"], r["n_chars"]) for r in got) == [(0, "", 0), (1, "", 0), (1, "", 0), (2, "", 0), (3, "plain text only, without any markup at all.", 43)]
