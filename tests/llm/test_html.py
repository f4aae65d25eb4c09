import random
import time

import pytest

from navspark.llm import html_layout as H


def test_layout():
    html = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body>
    <h1>Head &amp; <b>shoulders</b></h1><p>One<p>Two <br>three  <span style="display: none">no</span> <i hidden>no</i>four
    <ul><li>a<li>b<ul><li>c</ul><li>d</ul><ol start=3><li>x<li>y</ol>
    <table><caption>Cap</caption><tr><th>Name<th>Count<tr><td>apples<td>3<tr><td colspan=2>both</table>
    <pre>  keep
    this</pre><div>in<div>out</div>last</div><!-- c --><noscript>no</noscript>end</body></html>"""
    assert H.render(html) == (
        "Head & shoulders\n\nOne\n\nTwo\nthree four\n\n- a\n- b\n  - c\n- d\n\n3. x\n4. y\n\nCap\nName   | Count\napples | 3\nboth   |"
        "\n\n  keep\n    this\n\nin\nout\nlast\nend"
    )


def test_broken_markup():
    for h in ("<p", "<<b>>x", "</p></div>x", "<td>x<tr><td>y", "<script>never closed", "<!-- never closed", "<p a='b>c", "a < b > c", "&#x110000;&bogus;&#0;"):
        H.render(h)
    assert H.render("x</b></p>y") == "xy"
    assert H.render("<div>" * 50_000 + "deep") == "deep"
    assert H.render("<table>" * 3000 + "<tr><td>deep") == "deep"
    assert H.render(None) == H.render("") == ""
    H.render("<" * 100_000)
    H.render("<a '" * 20_000)


def test_query(spark):
    df = spark.createDataFrame([(1, "<p>a</p><p>b"), (None, None), (1, "<p>a</p><p>b"), (2, "")], "page_id long, html string").selectExpr("*", "'clash' as text")
    got = sorted(((r.page_id, r.text, r.n_chars, r.n_lines) for r in H.op5_result(df).collect()), key=str)
    assert got == sorted([(1, "a\n\nb", 4, 3), (1, "a\n\nb", 4, 3), (None, "", 0, 0), (2, "", 0, 0)], key=str)
    assert H.op5_result(df.limit(0)).count() == 0


def test_all_visible_words_come_out(spark):
    import re

    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select("html").collect()
    for r in pages[:100]:
        bare = re.sub(r"(?is)<(script|style|title|noscript)\b.*?</\1\s*>|<!--.*?-->|<head\b.*?</head>", " ", r.html)
        if re.search(r"(?i)hidden|display|<table|<li|<img|<input|<select|<svg|<iframe|<template", bare):
            continue
        from html import unescape

        want = re.sub(r"\s+", "", unescape(re.sub(r"<[^>]*>", " ", bare)))
        assert re.sub(r"\s+", "", H.render(r.html)) == want


def test_visibility_rules():
    page = '<div style="visibility:hidden">a<span style="visibility: visible">B</span>c</div><i style="backface-visibility: hidden">seen</i>'
    assert H.render(page) == "B\nseen"
    assert H.render('<p style="display:none">x<b style="display:block">y</b></p><p style="color:red; DISPLAY : None !important">z') == ""
    assert H.render('<p style="display:none!important;display:block">x</p><p hidden style="display:block">y</p><p data-hidden>z') == "y\n\nz"
    assert H.render('<table style="visibility:collapse"><tr><td>a<td style="visibility:visible">b</table>') == " | b".rjust(4)


def test_unclosed_quotes_end_at_the_tag():
    assert H.render('<a href="foo>text</a> more') == "text more"
    assert H.render("<p class='x>one <b>two</b>") == "one two"
    assert H.render('<a title="a > b">c</a><i x=y"z>d</i>') == "cd"


def test_cells_are_rendered_like_the_rest():
    page = "<table><tr><td rowspan=2>A<td><img alt=pic> <input value=go><tr><td><ul><li>x<li>y</ul><tr><td colspan=2>z<td>w</table>"
    assert H.render(page) == "A | pic go\n  | - x - y\nz |         | w"
    assert H.render("<table>before<tr><td>1<td>2</tr>between<tr><td>33</table>") == "before\n1  | 2\nbetween\n33"


HOSTILE = {
    "open tags": "<a " * 330_000, "divs": "<div>" * 200_000, "unmatched ends": "<b>" * 150_000 + "</i>" * 150_000, "quotes": '<a b="' * 160_000,
    "odd quotes": "<a b='" * 160_001, "lists": "<ul><li>x" * 110_000, "tables": "<table>" * 140_000 + "<tr><td>x", "comments": "<!--" * 250_000, "angles": "<" * 1_000_000,
    "spans": "<table><tr>" + "<td rowspan=65534 colspan=100>x" * 2000 + "<tr><td>y" * 100_000, "walls": "<p><table><tr><td>" + "<i>" * 100_000 + "<div>" * 140_000,
    "spaces": "<a" + " " * 1_000_000, "equals": "<a" + " =" * 500_000 + ">", "titles": "<title>" * 140_000, "styles": "<p style='" + "a:b;" * 250_000 + "'>x", "paragraphs": "<p>" * 330_000,
}


@pytest.mark.parametrize("kind", sorted(HOSTILE))
def test_a_megabyte_of_bad_markup_takes_seconds(kind):
    assert len(HOSTILE[kind]) > 900_000
    began = time.time()
    H.render(HOSTILE[kind])
    assert time.time() - began < 15


def _page(rnd, depth, shown):
    """Markup, and the words that must come out, in order."""
    tag = rnd.choice(["div", "p", "span", "b", "ul", "table", "section", "pre", "blockquote"]) if depth else ""
    if not tag:
        word = f"w{rnd.randrange(10**9)}"
        return (f"{rnd.choice(['', ' ', chr(10)])}{word} <!-- no --> ", [word] if shown else [])
    style, below = rnd.choice([("", shown)] * 5 + [(" hidden", None), (" style='Display:none'", None), (" style='visibility: hidden;'", False), (' style="x:y; visibility:visible"', True)])
    gone = below is None
    inner, want = "", []
    for _ in range(rnd.randrange(1, 4)):
        part, words = _page(rnd, rnd.randrange(depth), False if gone else below)
        if tag == "p" and "<" in part.replace("<!--", ""):
            part, words = "plain ", ["plain"] if not gone and below else []
        part = {"ul": f"<li>{part}", "table": f"<tr><td>{part}</td>"}.get(tag, part)
        inner += part
        want += words
    return f"<{tag}{style}>{inner}</{tag}>", [] if gone else want


def test_words_of_random_pages_equal_a_reference():
    rnd = random.Random(11)
    for _ in range(400):
        page, want = _page(rnd, 5, True)
        got = [w for w in H.render(page).split() if w not in ("|", "-")]
        assert got == want, page
