import re

from turnwise.llm import html_text as h

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{margin:0}</style><script>var t="</p>";</script></head><body class="has-sidebar">
<header><div>Site name and slogan of the whole site, quite long as headers go</div></header><nav><ul><li><a href="/a">menu one</a></li><li><a href="/b">menu two</a></li></ul></nav>
<!-- c --><div class="ad top">Buy this now, it is a long advertisement text that goes on for long.</div><div id="cookie-notice">We use cookies to make this site better for all of you.</div>
<article><header><h1>A title &amp; more</h1></header><p><b>First paragraph with   enough words to look
like text.<br><p>Second &eacute; paragraph with a <a href="x">link</a> in it and more words.</p><p>Short.</p><ul><li>point one<li>point two</ul>
<form><label>Mail</label><input type=text></form><p>Last paragraph of the article with enough words again.</p></article>
<section class="comments"><p>A reader comment which is as long as any paragraph of the article, sadly.</p></section><aside>Side text</aside><footer>&copy; foot</footer></body></html>"""
WANT = "A title & more\nFirst paragraph with enough words to look like text.\nSecond é paragraph with a link in it and more words.\nShort.\npoint one\npoint two\nLast paragraph of the article with enough words again."


def test_article_without_furniture():
    assert h.main_text(PAGE) == WANT
    assert h.main_text(PAGE.split("</article>")[0]) == WANT  # cut off


def test_page_without_an_article_element():
    x = PAGE.replace("article>", "div>")
    assert h.main_text(x).split("\n")[-1].startswith("Last paragraph") and "menu" not in h.main_text(x)


def test_bad_pages():
    assert h.main_text("") == "" and h.main_text("<<<>>><p") is not None and h.main_text("plain  text") == "plain text"
    assert h.main_text("<div>" * 3000 + "deep text" + "</div>") == "deep text"
    assert h.main_text("<script>x</script><p>a</p></div></b>") == "a"
    assert h.main_text("<p>" + "w " * 200_000) == ("w " * 200_000).strip()


def test_smoothing_keeps_a_constant_and_threshold_splits_two_levels():
    import numpy as np

    assert np.allclose(h.smooth(np.full(9, 3.0)), 3.0)
    assert h.threshold(np.array([1.0, 1.2, 9.0, 9.5, 1.1])) == 9.0


def test_every_row_comes_back(spark):
    rows = [(1, "u", PAGE), (1, "u", PAGE), (2, None, None), (3, "v", "")]
    got = h.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert sorted((r.page_id, r.text, r.n_chars) for r in got) == [(1, WANT, len(WANT)), (1, WANT, len(WANT)), (2, "", 0), (3, "", 0)]


def test_given_pages_give_exactly_the_blocks_of_their_article(spark):
    import html

    for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect():
        body = re.sub(r"(?s)^.*?<article>|</article>.*$|<footer>.*$", "", r.html)
        blocks = [re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]*>", lambda m: " " if m.group().startswith("<br") else "", x))).strip() for x in re.split(r"</?(?:p|h1|article|li|ul|div)\b[^>]*>", body)]
        assert h.main_text(r.html) == "\n".join(x for x in blocks if x), r.page_id


LONG = "A sentence of the body that goes on with many plain words and no mark-up at all. " * 30


def test_blocks_around_an_inner_wrapper_stay():
    body = f"<h1>Title</h1><p>Lead of the text.</p><div class='body'><div><p>{LONG}</p><p>{LONG}</p></div></div><section><p>Closing words.</p></section>"
    nav = "<div><ul><li><a href='/a'>one page of many</a></li><li><a href='/b'>another page of many</a></li></ul></div>"
    want = ["Title", "Lead of the text.", LONG.strip(), LONG.strip(), "Closing words."]
    for page in (f"<article>{body}</article>", f"<main><div>{body}</div></main>", f"<div id='post'>{body}</div>"):
        assert h.main_text(f"<html><body>{nav}{page}{nav}<footer>foot</footer></body></html>").split("\n") == want, page
    split = f"<main><h1>Title</h1><article><p>Lead of the text.</p><section><p>{LONG}</p><p>{LONG}</p></section><section><p>Closing words.</p></section></article></main>"
    assert h.main_text(f"<body>{nav}{split}</body>").split("\n") == want


def test_names_of_several_words_are_furniture_only_as_a_whole():
    assert all(map(h.is_furniture, ("ad", "ad-300x250", "site-header", "comment-list", "cookie-notice", "sidebar_left", "share-buttons", "main-nav")))
    assert not any(map(h.is_furniture, ("related-work", "share-price", "has-sidebar-story", "reader", "article-body", "content")))
    page = f"<body><article><h1>T</h1><p>{LONG}</p><div class='related-work'><p>Work that is related.</p></div><p class='share-price'>The price of a share.</p></article></body>"
    assert h.main_text(page).split("\n")[2:] == ["Work that is related.", "The price of a share."]


def test_a_heading_before_the_region_stays():
    page = f"<body><nav><a href='/'>home</a></nav><h1>The <i>title</i></h1><article><p>{LONG}</p><p>{LONG}</p></article><footer>foot</footer></body>"
    assert h.main_text(page).split("\n") == ["The title", LONG.strip(), LONG.strip()]


def test_unclosed_elements_cost_linear_time():
    import time

    began = time.perf_counter()
    assert "end" in h.main_text("<div><p>start" + "<span>" * 16_000 + "".join(f"<p>word {i}" for i in range(2000)) + "<p>end")
    assert "end" in h.main_text("<p>" + "<td><span>" * 8_000 + "</b></i>" * 8_000 + "end")
    assert time.perf_counter() - began < 3
