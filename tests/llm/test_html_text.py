import html as h
import random
import re
from html.parser import HTMLParser

from pyspark.sql import types as T

from patternwalk.llm import html_text as H

SCHEMA = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("html", T.StringType()), T.StructField("text", T.StringType())])
LONG = "Once, in a long sentence, with several commas, something was told at length and then told again, slowly."


def test_menus_forms_comments_and_adverts_go():
    page = f"""<html><head><title>No</title><style>p{{}}</style></head><body class="page has-sidebar">
    <header><h2>Site</h2></header><nav><p>{LONG}</p></nav><div class="cookie-notice">{LONG}</div>
    <div id="content"><h1>Head&shy;line &amp; more</h1><p>{LONG}<p>Short one.<script>if (a < b) x("<p>no</p>")</script>
    <form><p>{LONG}</p><textarea>{LONG}</textarea></form><div class="ad">{LONG}</div>
    <ul><li>first <a href=x>link</a><li>second</ul><blockquote>Said&nbsp;so,   twice.</blockquote>
    <table><tr><td>cell one<td>cell two</table></div>
    <section id="comments"><p>{LONG}</p></section><aside>{LONG}</aside><div class="sidebar">{LONG}</div>
    <footer>&copy; all, of, us</footer></body></html>"""
    assert H.main_text(page) == "\n\n".join(["Head\xadline & more", LONG, "Short one.", "first link", "second", "Said so, twice.", "cell one", "cell two"])


def test_loose_markup():
    assert H.main_text(None) == "" and H.main_text("") == "" and H.main_text("<p>  </p><!-- x") == ""
    assert H.main_text("no markup, at all &lt;b&gt; &#233;&#xe9; &bogus;") == "no markup, at all <b> éé &bogus;"
    assert H.main_text(f"<div><p><b>{LONG}<br>x<p>{LONG}</div>") == f"{LONG} x\n\n{LONG}"
    assert H.main_text(f"<article><header><h1>Own</h1></header><p>{LONG}</p></article>") == f"Own\n\n{LONG}"
    assert H.main_text("<div>" * 5000 + LONG) == LONG
    assert len(H.main_text(f"<article>{'<p>' + LONG}{'x' * 2_000_000}")) > 2_000_000


def test_links_do_not_win():
    links = "".join(f"<p><a href=x>{LONG}</a></p>" for _ in range(20))
    assert H.main_text(f"<body><div>{links}</div><div><p>{LONG}</p><p>{LONG}</p></div></body>") == f"{LONG}\n\n{LONG}"


def test_given_pages_against_their_articles(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    html = {r.page_id: r.html for r in pages.collect()}
    got = H.extract(pages).collect()
    assert len(got) == len(html)
    for r in got:
        article = re.sub(r"</article>.*|<footer.*", "", html[r.page_id].split("<article>", 1)[1], flags=re.S)
        parts = [re.sub(r"\s+", " ", h.unescape(re.sub("<[^>]*>", "", x.replace("<br>", " ")))).strip() for x in re.split("</?(?:p|h1)>", article)]
        assert r.text == "\n\n".join(x for x in parts if x) and r.n_chars == len(r.text)


def test_odd_rows(spark):
    rows = [(1, None, None, "t"), (1, None, None, "t"), (None, "u", "<p>x", "t")]
    got = H.extract(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted((r.page_id or 0, r.text, r.n_chars) for r in got) == [(0, "x", 1), (1, "", 0), (1, "", 0)]
    assert H.extract(spark.createDataFrame([], SCHEMA)).count() == 0


def test_a_head_left_open(spark):
    body = f"<div><p>{LONG}</p><p>{LONG}</p></div>"
    for page in (
        f"<html><head><title>No</title><meta charset=utf-8><body>{body}</body></html>",
        f"<head><title>No</title><link rel=x href=y>{body}",
        f"<html><head><title>No</title><custom-x></head><body>{body}</body></html>",
        f"<html><head><meta name=a><style>p{{}}</style><div></head><body>{body}</body></html>",
        f"<html><head></head><body>{body}</body></html>",
    ):
        assert H.main_text(page) == f"{LONG}\n\n{LONG}", page
    assert H.main_text(f"<head><title>No</title>{LONG}") == LONG


def test_tags_with_an_unmatched_quote():
    assert H.main_text(f'<article><p class="x>{LONG}</p><p>{LONG}</p></article>') == f"{LONG}\n\n{LONG}"
    assert H.main_text(f"<article><p>{LONG}</p><p id='a>{LONG}</p></article>") == f"{LONG}\n\n{LONG}"


def test_headers_of_the_article_by_name():
    assert H.main_text(f'<div class="site-header">Shop</div><article><div class="entry-header"><h1>Own</h1></div><p>{LONG}</p></article>') == f"Own\n\n{LONG}"
    assert H.main_text(f'<header>Shop</header><main><header><h1>Own</h1></header><p class="legal">{LONG}</p><p class="side">{LONG}</p></main>') == f"Own\n\n{LONG}\n\n{LONG}"


class Plain(HTMLParser):
    """A second implementation for pages whose article is an element: its blocks, without what never belongs to it."""

    OUT = {"nav", "footer", "aside", "form", "script", "style", "menu"}
    BREAKS = {"p", "h1", "h2", "ul", "li", "blockquote", "div", "article", "header", "pre"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.stack, self.blocks, self.run = [], [], []

    def end(self):
        text = " ".join("".join(self.run).split())
        self.run = []
        if text:
            self.blocks.append(text)

    def handle_starttag(self, tag, attrs):
        if tag in self.BREAKS:
            self.end()
        if tag == "br":
            self.run.append(" ")
        else:
            names = dict(attrs).get("class") or ""
            self.stack.append((tag, tag in self.OUT or names in ("comments", "advert", "share")))

    def handle_endtag(self, tag):
        if tag in self.BREAKS:
            self.end()
        while self.stack and self.stack.pop()[0] != tag:
            pass

    def handle_data(self, data):
        if any(t == "article" for t, _ in self.stack) and not any(out for _, out in self.stack):
            self.run.append(data)


def test_made_pages_against_a_second_implementation():
    rng = random.Random(11)
    word = lambda: rng.choice(["alpha", "b&amp;b", "caf\u00e9", "d&#233;j&agrave;", "x &lt; y", "five,", "six", "seven."])
    say = lambda n: " ".join(word() for _ in range(n))
    inline = lambda: rng.choice([say(9), f"<b>{say(3)}</b> {say(9)}", f"{say(5)} <a href='x'>{say(2)}</a> {say(6)}", f"{say(4)}<br>{say(8)}", f"{say(6)} <!-- {say(3)} --> {say(4)}"])
    junk = lambda: rng.choice([f"<nav><ul><li><a href=/>{say(2)}</a></li></ul></nav>", f"<aside>{say(12)}</aside>", f"<script>var a = '<p>{say(3)}</p>';</script>", f"<form><p>{say(5)}</p></form>", f'<div class="advert"><p>{say(20)}</p></div>', f'<div class="comments"><p>{say(20)}</p><p>{say(20)}</p></div>'])
    block = lambda: rng.choice([f"<p>{inline()} {inline()}</p>", f"<h2>{say(4)}</h2><p>{inline()} {say(8)}</p>", f"<blockquote><p>{inline()}</p></blockquote>", f"<ul><li>{inline()}</li><li>{inline()}</li></ul>", f"<div><p>{inline()} {say(10)}</p></div>"])
    for _ in range(300):
        inside = "".join(junk() if rng.random() < 0.2 else block() for _ in range(rng.randrange(2, 9)))
        page = f"<html><head><title>{say(3)}</title></head><body><header>{say(4)}</header>{junk()}<article><header><h1>{say(5)}</h1></header><p>{say(40)}</p>{inside}</article>{junk()}<footer><p>{say(15)}</p></footer></body></html>"
        plain = Plain()
        plain.feed(page)
        plain.close()
        assert H.main_text(page) == "\n\n".join(plain.blocks), page
