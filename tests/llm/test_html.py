import html
import itertools
import re
import time

import numpy as np

from sealed_frames.llm import html_extract as H
from sealed_frames.llm.dom import parse


def shape(node):
    return (node.tag, [x if isinstance(x, str) else shape(x) for x in node.items])


def test_parser_supplies_what_is_left_out():
    assert shape(parse("<p>a<p>b")) == ("#page", [("p", ["a"]), ("p", ["b"])])
    assert shape(parse("<p><b>a<br><p>b</p>")) == ("#page", [("p", [("b", ["a", ("br", [])])]), ("p", ["b"])])
    assert shape(parse("<ul><li>a<li>b<ul><li>c</ul></ul>d")) == ("#page", [("ul", [("li", ["a"]), ("li", ["b", ("ul", [("li", ["c"])])])]), "d"])
    assert shape(parse("a</div>b</p>")) == ("#page", ["a", "b"])
    assert shape(parse('x<script>var t="</p>";if(a<b){}</script>y')) == ("#page", ["x", ("script", []), "y"])
    assert shape(parse("a<!-- <p> -->b<!doctype x>c &amp;lt; d < e")) == ("#page", ["a", "b", "c &lt; d < e"])
    assert shape(parse('<a title="1 > 2">t</a>')) == ("#page", [("a", ["t"])])
    assert shape(parse("<table><tr><td>a<td>b<tr><td>c</table>"))[1][0][1] == [("tr", [("td", ["a"]), ("td", ["b"])]), ("tr", [("td", ["c"])])]
    assert shape(parse("<div><script>never closed <p>x")) == ("#page", [("div", [("script", [])])])
    assert parse("<" * 50_000) and parse("<div>" * 3000)


def test_quotes_and_brackets_in_tags():
    assert shape(parse('<p title=don\'t>a</p><p class="x"">b</p>')) == ("#page", [("p", ["a"]), ("p", ["b"])])
    assert shape(parse('<a title="never closed>t</a>u')) == ("#page", [("a", ["t"]), "u"])
    long = parse(f'<div data-x="{"<b>" * 3000}" class="article">t</div>')
    assert shape(long) == ("#page", [("div", ["t"])]) and long.items[0].named()["class"] == "article"
    assert shape(parse("<b><p>x</b>y</p>z</b>w")) == ("#page", [("b", [("p", ["x", "y"]), "z"]), "w"])


def test_broken_pages_take_linear_time():
    """A megabyte of each takes seconds, and gives the text that is left."""
    tool = H.train()
    body = "<article><h1>Title</h1><p>Some words of the article, with a mark. And some more of them follow here.</p>{}</article>"
    whole = tool.texts([body.format("")])[0]
    n = 100_000
    for inner in ("<span>" * n, "<b>" * n + "</b>" * n, "<span>" * n + "</i>" * n, "<b><div>" + "<i>" * n + "</b>" * n):
        assert tool.texts([body.format(inner)])[0] == whole
    for junk in ('<a "' * n, '<a x="' * (n + 1), "<a x='\">" * n, "<a" * n, "<!" * n, "<!--" * n, "<script>" + "</script " * n, "<ul>" + "<i>" * n + "<li>" * n):
        begin = time.time()
        assert tool.texts([body.format("") + junk])[0].startswith("Title\n\nSome words")
        assert time.time() - begin < 30


def test_decoding_is_the_best_consistent_choice():
    rng = np.random.default_rng(0)
    for _ in range(60):
        n = int(rng.integers(2, 7))
        parents = [-1] + [int(rng.integers(0, i)) for i in range(1, n)]
        margin = rng.normal(0, 2, n)
        inside, rest = -np.logaddexp(0, -margin), -np.logaddexp(0, margin)
        best = -np.inf
        for states in itertools.product((0, 1, 2), repeat=n):
            if states[0] != 0 or any((states[parents[i]], states[i]) not in {(0, 0), (0, 1), (1, 1), (1, 2), (2, 2)} for i in range(1, n)):
                continue
            best = max(best, sum(inside[i] if s == 1 else rest[i] for i, s in enumerate(states)))
        got = H.decode(parents, margin)
        assert got[0] == 0
        assert abs(sum(inside[i] if s == 1 else rest[i] for i, s in enumerate(got)) - best) < 1e-9


def article(page):
    inner = re.search(r"<article>(.*?)</article>", page, re.S)[1]
    parts = re.split(r"</?(?:p|h1|h2|h3|li|ul|ol|div|section|blockquote|pre|table|tr)\b[^>]*>", inner)
    blocks = [" ".join(html.unescape(re.sub(r"<br>", " ", x).replace("<b>", "").replace("</b>", "")).split()) for x in parts]
    return "\n\n".join(b for b in blocks if b)


def test_pages(spark, tiny):
    pages = spark.read.parquet(f"{tiny}/pages.parquet")
    got = {r.page_id: r for r in H.main_text(pages).collect()}
    rows = pages.collect()
    right = sum(got[r.page_id].text == article(r.html) for r in rows)
    assert right == len(rows)
    assert all(r.n_chars == len(r.text) for r in got.values())


def test_pages_by_class_names_only():
    tool = H.train()
    page = (
        '<html><body><div class="menu"><a href="/">Home</a> <a href="/a">About us</a></div><div class="cookie-consent">We use cookies. Accept?</div>'
        '<div class="post-content"><h1>A title</h1><p>First paragraph of the story, with some words in it.</p><p>Second one; it goes on for a while.</p></div>'
        '<div class="comments"><h3>Comments</h3><div class="comment"><p>I do not agree.</p></div></div><div class="footer">&copy; 2020 Someone</div></body></html>'
    )
    assert tool.texts([page]) == ["A title\n\nFirst paragraph of the story, with some words in it.\n\nSecond one; it goes on for a while."]


def test_held_out_blocks():
    tool, hits, n = H.train(), 0, 0
    for seed in range(20_000, 20_080):
        page, marks = H.compose(seed)
        words = set(tool.texts([page])[0].split())
        hits += sum((w in words) == inside for w, inside in marks)
        n += len(marks)
    assert hits / n > 0.93


def test_edge_rows(spark):
    rows = [(1, "u", None), (2, None, ""), (None, "v", "plain text"), (4, "w", "<p>" * 2000), (5, "x", "<article><h1>T</h1><p>" + "long words here. " * 20_000 + "</p></article>"), (5, "x", "<script>x</script>")]
    df = spark.createDataFrame([(*r, "clash", 0) for r in rows], "page_id long, url string, html string, text string, n_chars int")
    got = H.main_text(df).collect()
    assert len(got) == 6 and all(r.text is not None for r in got)
    assert {r.page_id: r.text for r in got}[1] == "" and H.main_text(df.limit(0)).count() == 0
