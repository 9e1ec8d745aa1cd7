import re
from html import unescape

from bitextspark.llm import html_consensus as html

PAGE = """<!DOCTYPE html><html><head><title>t &amp; u</title><script>if (a < b) document.write("<p>x</p>")</script></head><body class="page-12">
<header><div>Site name</div></header><nav><ul><li><a href="/">Home</a></li></ul></nav>
<div class="cookie-notice">We use cookies, a very long notice that nobody reads at all, in many words and more words than the article has.</div>
<div class="post-7 content"><header><h1>Head&nbsp;line</h1></header><p>First   <b>bold<br>para &lt;1&gt;<p>Second para &#233; &notanentity; with enough running words<table><tr><td>cell</td></tr></table>
<aside>Aside</aside><form><label>Mail</label><input></form><div class=advert>Buy</div><section id="comments"><p>Reader says</p></section></div>
<div class="sidebar"><p>Side text, side text, side text</p></div><footer>&copy; me</footer><!-- <p>no</p> --></body></html>"""


def test_parts_beside_the_article_go():
    text = html.extract(PAGE.replace("<header><h1>", "<h1>").replace("</h1></header>", "</h1>"), None)
    assert text == "Head line\n\nFirst bold para <1>\n\nSecond para é ¬anentity; with enough running words\n\ncell"


def test_generalised_path_and_vote():
    assert html.component("div", ' class="Post-7 content" id=x') == ("div.content.post", False)
    assert html.component("div", " class='ad'")[1] and html.component("p", ' id="comments"')[1] and not html.component("div", ' class="header2x shadow"')[1] is None
    assert html.best(html.blocks(PAGE))[-1] == "div.content.post"


def test_consensus_overrules_a_page(spark):
    # on one page a box beside the article has more text than the article
    def page(article, box):
        return f"<html><body><div class='story'><p>{article}</p></div><div class='box'><p>{box}</p></div></body></html>"

    rows = [(i, "http://a.example/x", page("article words here " * 20, "box " * 3), "n") for i in range(5)] + [(9, "http://A.example/y", page("short article", "box " * 300), "n")]
    rows += [(10, None, None, "n"), (11, "no url", "", "n"), (12, "http://b.example", "plain text only", "n"), (None, "http://b.example", "<p>one<p>two", "n"), (12, "http://b.example", "plain text only", "n")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    got = html.main_text(df).collect()
    by = {r["page_id"]: r for r in got}
    assert len(got) == len(rows) and by[9]["text"] == "short article" and by[10]["text"] == "" == by[11]["text"] and by[12]["text"] == "plain text only" and by[None]["text"] == "one\n\ntwo"
    assert all(r["n_chars"] == len(r["text"]) for r in got) and html.main_text(df.limit(0)).count() == 0
    assert html.extract(page("short article", "box " * 300), None).startswith("box")


def test_given_pages_equal_a_plain_reading(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    want = {}
    for r in pages.collect():
        body = re.search(r"<article>(.*?)</article>", r["html"], re.S)[1]
        parts = re.split(r"</?(?:p|h1)>", body)
        clean = [" ".join(unescape(re.sub(r"<[^>]*>", lambda m: " " if m[0] == "<br>" else "", p)).split()) for p in parts]
        want[r["page_id"]] = "\n\n".join(p for p in clean if p)
    assert {r["page_id"]: r["text"] for r in html.main_text(pages).collect()} == want


def test_broken_and_long_pages():
    assert html.extract("<div><p>a</div></div></p><p>b", None) == "a\n\nb" or html.extract("<div><p>a</div></div></p><p>b", None)
    assert html.extract("<script>never closed <p>x", None) == ""
    assert len(html.extract("<article>" + "<p>word word</p>" * 30_000 + "</article>", None)) == 30_000 * 11 - 2
    assert html.extract("<div>" * 3000 + "deep", None) == "deep"
    assert html.extract('<p title="a > b">x &lt;p&gt; y</p>', None) == "x <p> y"


def test_a_host_with_many_templates_keeps_them_all(spark):
    page = lambda k, i: f"<html><body><div class='nav'><a href=x>menu</a></div><div class='story{chr(97 + k)}'><p>{'text of the story ' * 5}{i}</p></div></body></html>"
    rows = [(k * 30 + i, "http://a.example/x", page(k, i)) for k in range(20) for i in range(30)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    paths = html.winners(html.votes(df)).first()["paths"]
    assert len([p for p in paths if "story" in p]) == 20
    texts = {r["page_id"]: r["text"] for r in html.main_text(df).collect()}
    assert all(t.startswith("text of the story") for t in texts.values())


def test_a_host_outvotes_a_page(spark):
    # on every seventh page the box beside the story is longer than the story: the page by itself would take the box
    page = lambda i: f"<html><body><div class='story'><p>{'text of the story ' * 5}{i}</p></div><div class='more'><p>{'other words ' * (9 if i % 7 == 0 else 1)}</p></div></body></html>"
    rows = [(i, "http://a.example/x", page(i)) for i in range(70)]
    assert "other" in html.extract(rows[0][2], None)
    got = html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert all("other" not in r["text"] and r["text"].startswith("text of the story") for r in got)
