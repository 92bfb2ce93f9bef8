import re

from rpqspark.llm import pages

PAGE = """<!DOCTYPE html><html lang="en"><head><title>T &amp; x</title><style>p{}</style><script>var t="</p>";</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href="/a">home</a></li></ul></nav><!-- ad 1 --><div class="ad">Buy</div><div id="cookie-notice">We use</div>
<article><h1>Title &eacute;</h1><p>One  <b>bo</b>ld
word &lt;tag&gt; 3 < 4<p>Two&nbsp;x<br>y<div class="share">Share it</div><ul><li>i1<li>i2</ul><section class="comments"><p>Nice!</p></section><form><input>Send</form></article>
<aside>More</aside><section id="comments"><article class="comment">First</article></section><footer>&copy; s</footer></body></html>"""


def test_main_text():
    assert pages.main_text(PAGE) == "Title é One bold word <tag> 3 < 4 Two x y i1 i2"
    assert pages.main_text(None) == pages.main_text("") == pages.main_text("<p>") == ""
    assert pages.main_text("plain text &amp; more") == "plain text & more"
    assert pages.main_text("<article><p>cut of") == "cut of"
    assert pages.main_text("<div><p>a</p><p>b</div>c") == "a b c"
    assert pages.main_text("<article>" + "<p>" * 3 + "x" + "<b>" * 4000 + "y") == "xy"


def test_repeated_branches_go_and_articles_stay(spark):
    def page(i):
        return f"<html><body><div class='top'>Welcome to our site</div><div class='story'><p>Story number {i} is new</p></div><div class='end'>All rights</div></body></html>"

    rows = [(i, f"http://h.example/{i}", page(i)) for i in range(12)] + [(i, f"http://c.example/{i}", "<body><article><p>Same text</p></article></body>") for i in range(12, 24)]
    rows += [(30, None, page(7)), (31, "http://one.example/", page(8)), (None, "http://one.example/2", None), (5, "http://h.example/5", page(5))]
    got = pages.extract(spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, host string")).collect()
    assert len(got) == len(rows)
    for r in got:
        if r.url and "h.example" in r.url:
            assert r.text == f"Story number {r.page_id} is new"
        if r.url and "c.example" in r.url:
            assert r.text == "Same text" and r.n_chars == 9
        if r.page_id == 31:
            assert r.text == "Welcome to our site Story number 8 is new All rights"
    assert pages.extract(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []


def test_given_pages_keep_their_articles(spark, sf_dir):
    given = spark.read.parquet(f"{sf_dir}/pages.parquet")
    got = {r.page_id: r.text for r in pages.extract(given).collect()}
    for r in given.collect():
        part = re.search(r"<article>(.*?)(</article>|$)", r.html, re.S)[1]
        part = re.sub(r"</?(?:p|h1|br|li|ul)[^>]*>", " ", part)
        part = re.sub(r"</?[a-z][^>]*>", "", part)
        import html

        assert got[r.page_id] == " ".join(html.unescape(part).split()), r.page_id


def made(spark, rows):
    return spark.createDataFrame(rows, "page_id long, url string, html string")


def test_the_tree_decides_inside_articles_too(spark):
    """Repeated parts of a host go, whatever their place; without the tree they stay."""
    page = lambda i: f"<body><article><h1 class='post-header'>Title {i}</h1><div class='box'>Read our house rules</div><p>Text {i} here</p><p>And more</p></article></body>"
    table = made(spark, [(i, f"http://h.example/{i}", page(i)) for i in range(20)])
    for importance, rules in ((pages.IMPORTANCE, ""), (0, "Read our house rules ")):
        got = {r.page_id: r.text for r in pages.extract(table, importance).collect()}
        assert all(got[i] == f"Title {i} {rules}Text {i} here And more" for i in range(20))


def test_copies_do_not_make_an_article_furniture(spark):
    same = "<body><div class='story'><p>The one story</p></div></body>"
    own = lambda i: f"<body><div class='story'><p>A story of its own, {i}</p></div></body>"
    rows = [(i, f"http://h.example/{i}", same) for i in range(90)] + [(i, f"http://h.example/{i}", own(i)) for i in range(90, 100)] + [(i, f"http://k.example/{i}", same) for i in range(100, 130)]
    got = {r.page_id: r.text for r in pages.extract(made(spark, rows)).collect()}
    assert all(got[i] == ("The one story" if i < 90 or i >= 100 else f"A story of its own, {i}") for i in range(130))


def test_tree_equals_a_plain_count(spark):
    import math
    from collections import Counter, defaultdict

    rows = [(i, f"http://h{i % 2}.example/{i}", f"<body><div class='a'>same{i % 3}</div><p><b>x{i % 5}</b></p><p>y{i}</p></body>") for i in range(14)]
    got = {(r.host, r.node): r for r in pages.style_tree(made(spark, rows)).collect()}
    for at in ("h0.example", "h1.example"):
        own, shown = {r[2] for r in rows if f"//{at}" in r[1]}, defaultdict(Counter)
        for page in own:
            for kind in (0, 1):
                for node, x in {(b[0], b[3] if kind == 0 else b[1]) for b in pages.blocks(page)}:
                    shown[node, kind][x] += 1
        m = len(own)
        for node in {n for n, _ in shown}:
            measure = [1 - (m - 1) / m * sum(c * math.log(c) for c in shown[node, k].values()) / sum(shown[node, k].values()) / math.log(m) for k in (0, 1)]
            w = 1 - 0.9 ** len(shown[node, 1])
            r = got[at, node]
            assert r.pages == m and abs(r.content - measure[0]) < 1e-9 and abs(r.presentation - measure[1]) < 1e-9
            assert abs(r.importance - max(measure[0], w * measure[1] + (1 - w) * measure[0])) < 1e-9


def test_salted_join_and_deep_pages(spark, monkeypatch):
    import time

    page = lambda i: f"<body><div class='top'>Hello</div><p>{i}</p></body>"
    table = made(spark, [(i, "http://h.example/", page(i)) for i in range(20)])
    monkeypatch.setattr(pages, "SENT", 0)
    assert {r.page_id: r.text for r in pages.extract(table).collect()} == {i: str(i) for i in range(20)}
    deep = "".join(f"<div>t{i}" for i in range(20_000))
    began = time.time()
    assert pages.main_text(deep).startswith("t0 t1 ") and time.time() - began < 5
