import html
import re
import time

import pytest

from chronocluster.llm.html_text import extract, main_texts

BODY = "<h1>Title &amp; more</h1><p><b>First, with commas, and <a href='/x'>a link</a>.<br>Line<p>Second   paragraph, longer than the first one, with words.</p>"
WANT = "Title & more\n\nFirst, with commas, and a link. Line\n\nSecond paragraph, longer than the first one, with words."


@pytest.mark.parametrize(
    "page",
    [
        f"<html><head><title>t</title><style>p{{}}</style><script>var t='</p>';</script></head><body><nav><ul><li><a href='/a'>A</a></ul></nav><div class='ad'>Buy, buy, buy.</div><article>{BODY}</article><footer>&copy; us, them, all.</footer></body></html>",
        f"<body><header><p>Site, name, here</p></header><div id=content>{BODY}</div><aside><p>Related, stuff, and more stuff.</p></aside><div class='comments'><p>Nice, post, really, I think, so, too, much, yes.</p></div>",
        f"<body><div class='cookie-notice'><p>We use, cookies, a lot, of, them.</p></div><main>{BODY}</main><form><input><p>Sign, up, now.</p></form>",
        f"<article>{BODY}",
    ],
)
def test_article_alone(page):
    assert extract(page) == WANT


def test_odd_pages():
    assert extract(None) == extract("") == extract("<script>x</script>") == extract("<nav>only menus</nav>") == ""
    assert extract("plain text") == "plain text"
    assert extract("<p>a < b & c") == "a < b & c"
    assert extract("<p>one</p><!-- <p>no</p> --><p title='a>b'>two</p>") == "one\n\ntwo"
    assert "deep" in extract("<div>" * 3000 + "<p>deep, text</p>" + "</div>" * 3000)
    assert len(extract("<article><p>" + "word, " * 50_000 + "</article>")) > 250_000


PARAS = [f"Paragraph number {i}, which has some words, and ends here." for i in range(6)]


@pytest.mark.parametrize("outer", ["div id=main", "section", "article", "main"])
@pytest.mark.parametrize("depth", range(11))
def test_paragraphs_in_containers_of_their_own(outer, depth):
    inner = "".join("<div>" * depth + f"<p>{p}</p>" + "</div>" * depth for p in PARAS)
    tag, links = outer.split()[0], "<div><a href=x>one</a> <a href=y>two</a></div>"
    assert extract(f"<html><body><nav><a href=x>m</a></nav><{outer}>{inner}</{tag}><div class=footer><p>f, f, f</p></div>") == "\n\n".join(PARAS)
    assert extract(f"<body>{links}<{outer}><h1>Title</h1>{inner}</{tag}>{links}") == "\n\n".join(["Title", *PARAS])


def test_uneven_sections():
    """A long section does not drive out short ones, beside it or farther up."""
    long, short = "".join(f"<p>{p}</p>" for p in PARAS), "<h2>More</h2><p>One short line of it.</p>"
    want = "\n\n".join([*PARAS, "More", "One short line of it."])
    assert extract(f"<body><div><section>{long}</section><section>{short}</section></div>") == want
    assert extract(f"<body><div><div><section>{long}</section></div><div><section>{short}</section></div></div>") == want
    nested = "".join(f"<div><p>{p}</p>" for p in PARAS) + "</div>" * 6
    assert extract(f"<body><header><p>Name, of, site</p></header>{nested}") == "\n\n".join(PARAS)


@pytest.mark.parametrize("part", ["<div>", "<div></b>", "<pre><b>", "<li><b>x", "<p><i>", "<td>", "<a '", "<ul><li>x", "<b>", "</b>", "<!--"])
def test_deep_pages_take_linear_time(part):
    def seconds(n):
        began = time.process_time()
        extract(part * n + "<p>x, y")
        return time.process_time() - began

    assert seconds(100_000) < 4 + 20 * seconds(10_000)


@pytest.mark.parametrize("scale", ["0.001", "0.01"])
def test_pages_of_the_table(spark, scale):
    pages = spark.read.parquet(f"/root/testdata/sf{scale}/pages.parquet")
    got = {r.page_id: r for r in main_texts(pages, ["page_id", "url"]).collect()}
    for r in pages.collect():
        inner = r.html[r.html.index("<article>") + 9 : r.html.index("</article>")]
        parts = (" ".join(html.unescape(re.sub(r"<br>", "\n", re.sub(r"</?b>", "", s))).split()) for s in re.split(r"</?(?:p|h1)>", inner))
        want = "\n\n".join(p for p in parts if p)
        assert got[r.page_id].text == want and got[r.page_id].n_chars == len(want) and got[r.page_id].url == r.url


def test_rows(spark):
    df = spark.createDataFrame([(1, None, "x"), (1, "<p>a</p>", "y"), (None, "", None)], "page_id bigint, html string, text string")
    assert sorted((r.page_id or 0, r.text, r.n_chars) for r in main_texts(df, ["page_id"]).collect()) == [(0, "", 0), (1, "", 0), (1, "a", 1)]
    assert main_texts(df.limit(0), ["page_id"]).count() == 0
