import html
import re

import pytest

from blockgraph.llm.html_text import extract, main_text

PROSE = "The first long sentence of the story, which goes on for a while, has commas, and ends here. And so does the second one."

PAGE = f"""<!DOCTYPE html><html><head><title>T</title><style>p{{}}</style><script>var t="</p><p>no</p>";</script></head><body class="page">
<header class="site-header"><a href="/">Home</a> Site name, with, many, commas, in, a, long, header line of text</header>
<nav><ul><li><a href="/a">Menu A</a><li><a href="/b">Menu B</a></ul></nav><div class="cookie-notice">We use cookies, as everybody does, on this page and on others.</div>
<div id="wrap"><div class="content"><h1>Head &amp; line</h1><p>{PROSE}<p>Short.<br>After break&nbsp;x<p><b>Bold <i>un</b>closed</i> &lt;tag&gt; &#233;&eacute;
<ul><li>one<li>two <a href="#">link</a></ul><div class="ad">Buy this, buy that, and buy some more of all these things.</div><table><tr><td>c1<td>c2</table>
<form>Name <input name=q> <button>Go</button></form><blockquote>{PROSE}</blockquote><!-- <p>not this</p> --></div></div>
<div class="sidebar"><p>Side text that is long enough to be scored, with a comma or two, but is in a sidebar.</p></div>
<div id="comments"><p>A reader's comment, which is long enough to be scored, and has commas, too.</p></div><footer>&copy; Footer, with, commas</footer></body></html>"""


def test_furniture_goes_and_blocks_stay_in_order():
    assert main_text(PAGE).split("\n") == ["Head & line", PROSE, "Short. After break x", "Bold unclosed <tag> éé", "one", "two link", "c1", "c2", PROSE]


@pytest.mark.parametrize(("page", "text"), [(None, ""), ("", ""), ("plain words only", "plain words only"), ("<p>a<p>b", "a\nb"), ("<", "<"), ("<article><h1>x</h1></article><footer>y</footer>", "x"), ("<div><p>unclosed <b>bold", "unclosed bold"), ("<script>only", ""), ("</p></div>stray", "stray")])
def test_odd_pages(page, text):
    assert main_text(page) == text


LONG = "Another sentence of the same article, long enough to be scored, which goes on and on until it ends. And one more, of course."
#: Pages without an article element, and what a reader would take as their main text.
LABELLED = {
    "science": (f'<body><div class="social-science"><p>{PROSE}</p><p>{LONG}</p></div><div class="box"><p>Unrelated words, some of them, in a box of its own.</p></div>', [PROSE, LONG]),
    "sections": (f"<body><div id=wrap><section><h2>A</h2><p>{PROSE}</p></section><section><h2>B</h2><p>{LONG}</p></section><section><h2>C</h2><p>{PROSE}</p></section></div>", ["A", PROSE, "B", LONG, "C", PROSE]),
    "form": (f'<body><div class="content"><p>{PROSE}</p><div class="form"><p>{LONG}</p></div><p>{PROSE}</p></div>', [PROSE, LONG, PROSE]),
    "related": (f'<article><p>{PROSE}</p><section class="related-work"><h2>Related work</h2><p>{LONG}</p></section></article>', [PROSE, "Related work", LONG]),
    "title": (f'<body><h1>The title</h1><div class="text"><p>{PROSE}</p><p>{LONG}</p></div>', ["The title", PROSE, LONG]),
    "related links": (f'<div class="post"><p>{PROSE}</p><p>{LONG}</p><div class="related"><ul><li><a href=a>One more story, to be read</a><li><a href=b>Another story</a></ul></div></div>', [PROSE, LONG]),
    "table layout": (f'<table><tr><td class="menu"><a href=a>Home</a><td><p>{PROSE}</p><p>{LONG}</p><td class="sidebar"><p>Latest news, offers, and prices of the day, and more.</p></table>', [PROSE, LONG]),
    "deep": (f"<div><div><div><p>{PROSE}</p></div></div><div><div><p>{LONG}</p></div></div></div><div class=footer>Imprint, contact, terms, and so on, and so forth</div>", [PROSE, LONG]),
    "few links": (f'<div id=a><p>{PROSE} <a href=x>See this</a>.</p><p>{LONG}</p></div><div id=b><a href=1>List, of, many, links, and, more</a> <a href=2>and, others, of, this, kind, here</a></div>', [f"{PROSE} See this.", LONG]),
    "comments": (f'<div class="story"><p>{PROSE}</p></div><div id="comments"><p>I read this, and I do not agree, with any of it. Not at all.</p></div>', [PROSE]),
    "notice": (f'<div class="notice">Our offices, and shops, are closed on Sunday. Please, come back on Monday morning.</div><div><p>{PROSE}</p><p>{LONG}</p></div>', [PROSE, LONG]),
    "own header": (f"<article><header><h1>Head</h1><p>By someone, today, for this paper</p></header><p>{PROSE}</p><footer>Filed under x</footer></article>", ["Head", PROSE]),
    "list in the text": (f"<div><div><p>{PROSE}</p></div><ul><li>first point<li>second point</ul><div><p>{LONG}</p></div></div>", [PROSE, "first point", "second point", LONG]),
}


@pytest.mark.parametrize("name", LABELLED)
def test_labelled_layouts(name):
    page, want = LABELLED[name]
    assert main_text(page).split("\n") == want


HOSTILE = {"lists": "<li><ul>", "open tags": "<a ", "divs": "<div>", "quotes": "<a x=\"y><b z='>", "paragraphs": "<p><b>", "cells": "<table><tr><td>", "ends": "</div></p>", "inline": "<i>x", "signs": "<<", "comments": "<!-- - --", "entities": "&amp", "classes": '<div class="ad related form">x, y. ', "names": f'<div class="related form">{"x, y " * 20}. '}


@pytest.mark.parametrize("name", HOSTILE)
def test_a_hostile_megabyte_takes_linear_time(name):
    import time

    page = HOSTILE[name] * (1_000_000 // len(HOSTILE[name]))
    began = time.perf_counter()
    main_text(page + "<p>Some words, and some more of them, to be found.</p>")
    assert time.perf_counter() - began < 20


def test_long_and_deep_pages():
    assert main_text("<div>" * 20_000 + "x" * 100) == "x" * 100
    many = "".join(f"<p>Sentence number {i}, which has a comma.</p>" for i in range(20_000))
    assert main_text(f"<body><article>{many}</article></body>").count("\n") == 19_999


def test_whole_pages_table(spark, sf):
    """The given pages have one article each: its blocks, read off by plain patterns."""
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    got = {r.page_id: r for r in extract(pages).collect()}
    rows = pages.collect()
    assert len(got) == len(rows)
    for r in rows:
        inner = re.search(r"<article>(.*?)(?:</article>|<footer>|$)", r.html, re.S)[1]
        parts = [" ".join(html.unescape(re.sub(r"<br>", " ", re.sub(r"</?b>", "", x))).split()) for x in re.split(r"</?(?:p|h1)>", inner)]
        want = "\n".join(x for x in parts if x)
        assert got[r.page_id].text == want and got[r.page_id].n_chars == len(want)


def test_null_rows_and_clashing_names(spark):
    df = spark.createDataFrame([(1, None, None, "q"), (None, "u", "<p>a</p>", "q"), (None, "u", "<p>a</p>", "q")], "page_id long, url string, html string, text string")
    assert sorted(tuple(r) for r in extract(df).fillna(-1, ["page_id"]).fillna("", ["url"]).collect()) == [(-1, "u", "a", 1), (-1, "u", "a", 1), (1, "", "", 0)]
    assert extract(df.limit(0)).count() == 0
