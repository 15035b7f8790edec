"""Pages that are deep, long, hostile or oddly built."""

import os
import re
import time
from html.parser import HTMLParser

import pytest

from neargraph.llm import html_extract as x


def test_comments_are_dropped_however_deep():
    page = "<body>" + "<div>" * 600 + "<div class='comments'><p>" + "reader words " * 50 + "</p></div>" + "</div>" * 600 + "<article><h1>T</h1><p>" + "body text " * 30 + "</p></article>"
    assert x.extract(page, [x.vote(page)]) == "T\n\n" + ("body text " * 30).strip()
    inner = "<article>" + "<div>" * 700 + "<p>deep text</p><div class=comments>no</div>" + "</div>" * 700 + "</article>"
    assert x.extract(inner, [x.vote(inner)]) == "deep text"


def test_an_article_keeps_its_title_and_short_sections():
    page = "<article><h1>Title</h1><div class='content'><p>" + "long text " * 400 + "</p></div><section><p>short</p></section></article>"
    assert x.vote(page) == "html>article"
    assert x.extract(page, [x.vote(page)]) == "Title\n\n" + ("long text " * 400).strip() + "\n\nshort"


def test_an_article_keeps_formulas_drawings_and_its_own_parts():
    page = "<article><p>let <math><mi>x</mi><mo>=</mo><mn>1</mn></math> be</p><svg><text>axis</text></svg><div class='legal'>clause</div><div class='widget'>box</div><div class='related'>more</div></article><div class='legal'>imprint</div>"
    assert x.extract(page, [x.vote(page)]) == "let x=1 be\n\naxis\n\nclause\n\nbox"


@pytest.mark.parametrize(
    "page",
    [
        "<div>" * 60_000 + "text",
        "<b>" * 60_000 + "<p>a</p>" * 2_000,
        "<div>" * 30_000 + "</span>" * 60_000 + "x",
        "<p>" * 60_000 + "x",
        "<a href='" * 20_000 + "x",
        '<a b="' * 20_001 + "x",
        "<li>" * 60_000 + "x",
        "<" * 200_000,
        "<!--" * 50_000,
        "<div class='" + "a" * 300_000 + "'>x</div>",
        "<article><p>" + "long words &amp; more " * 100_000 + "</p></article>",
    ],
)
def test_hostile_pages_take_time_in_proportion(page):
    began = time.process_time()
    x.extract(page, [x.vote(page) or ""])
    assert time.process_time() - began < 8


def test_hosts_with_many_paths_keep_the_most_voted(spark):
    rows = [(i, "http://h.example/x", f"<article class='c{'abcdefghij'[i % 10]}{'klmnopqrst'[i // 10 % 10]}'><p>words here</p></article>") for i in range(100)]
    rows += [(200 + i, "http://h.example/x", "<article class='main'><p>words here</p></article>") for i in range(40)]
    (row,) = x.host_paths(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert (row.host, row.paths) == ("h.example", ["html>article.main"])


class _Plain(HTMLParser):
    """A second, independent way for pages whose article is an ``article`` element: the standard library's tokenizer, blocks cut at block tags."""

    BLOCKS = {"p", "h1", "h2", "h3", "div", "ul", "ol", "li", "article", "section", "blockquote", "table", "tr", "td", "nav", "footer", "header", "aside"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.inside = self.dropped = 0
        self.blocks, self.held = [], []

    def cut(self):
        text = " ".join("".join(self.held).split())
        self.held.clear()
        if text:
            self.blocks.append(text)

    def handle_starttag(self, tag, attrs):
        marks = " ".join(v or "" for k, v in attrs if k in ("class", "id")).split()
        if tag in ("script", "style", "nav", "footer", "aside", "form") or {"ad", "ads", "comments", "sidebar"} & set(marks):
            self.dropped += tag not in ("br",)
        if tag == "article":
            self.inside += 1
        if tag in self.BLOCKS:
            self.cut()
        elif tag == "br":
            self.handle_data(" ")

    def handle_endtag(self, tag):
        if tag in self.BLOCKS:
            self.cut()
        if tag == "article":
            self.inside -= 1
        if tag in ("script", "style", "nav", "footer", "aside", "form"):
            self.dropped -= 1

    def handle_data(self, data):
        if self.inside and not self.dropped:
            self.held.append(data)


@pytest.mark.parametrize("folder", ["/root/testdata/sf0.001", "/root/testdata/sf0.01"])
def test_given_pages_equal_a_second_way(spark, folder):
    if not os.path.exists(f"{folder}/pages.parquet"):
        pytest.skip("the given tables are not here")
    pages = spark.read.parquet(f"{folder}/pages.parquet")
    got = {r.page_id: r for r in x.extract_pages(pages).collect()}
    assert len(got) == pages.count()
    for r in pages.collect():
        # an advert outside the article is an element of its own: its end brings the parser's count back
        plain = _Plain()
        plain.feed(re.sub(r'<div class="ad">.*?</div>', "", r.html, flags=re.DOTALL))
        plain.close()
        plain.cut()
        want = "\n\n".join(plain.blocks)
        assert (got[r.page_id].text, got[r.page_id].n_chars, got[r.page_id].url) == (want, len(want), r.url)
