import re
from html import unescape

import numpy as np

from hypernear.llm import html_text as H

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body>
<header><a href=/>Home</a></header><nav><ul><li>One<li>Two</ul></nav><div class="cookie-notice">We use cookies</div><aside>Side</aside>
<article><header><h1>A  &amp; B</h1></header><p>First <b>bo</b>ld&nbsp;text<br>next<p>Second &eacute;&#233;<div class="ad">Buy</div><form><input>Name</form>
<ul><li>x<li>y</ul><section id="comments"><article>I like it</article></section><footer>by me</footer></article>
<footer>&copy; us</footer></body></html>"""


def test_article_of_a_full_page():
    assert H.extract([PAGE]) == ["A & B First bold text next Second éé x y"]


def test_pages_without_marks_lose_what_repeats():
    menu, end = "home news sports weather about contact help", "all rights reserved by the example company forever"
    pages = [f"<div>{menu}</div><div>unique story number {w} with its own words {w * 2}</div><div>{end}</div>" for w in ("a", "b", "c")]
    assert H.extract(pages) == [f"unique story number {w} with its own words {w * 2}" for w in ("a", "b", "c")]
    assert H.extract(pages[:1])[0].startswith("home news")  # nothing repeats on one page


def test_repeats_inside_an_article_are_content():
    page = "<nav>a b c d e f g</nav><article><p>the very same passage in two articles of one host</p></article>"
    assert H.extract([page, page]) == ["the very same passage in two articles of one host"] * 2


def test_repeated_and_mirrored_pages_keep_their_text():
    page, other = "<div>one two three four five six seven</div><p>a b c d e f g h</p>", "<p>other text with eight words of its own</p>"
    text = "one two three four five six seven a b c d e f g h"
    assert H.extract([page, page, other, f"<section>{page}</section>"]) == [text, text, "other text with eight words of its own", text]


def test_main_content_without_an_article():
    page = '<div class="site-header">Brand</div><div class="sidebar">S</div><div id="content"><div class="post-header"><h1>T</h1></div><p>body text</p><div class="adbox">buy</div><div class="comments">c</div></div><div class="footer-links">f</div>'
    assert H.extract([page, page]) == ["T body text"] * 2
    assert H.extract(['<main><nav>n</nav><p>x</p><article class="post">y</article></main>']) == ["y"]


def test_covered_runs_equal_brute_force():
    random = np.random.default_rng(0)
    for _ in range(50):
        pages = [[str(t) for t in random.integers(0, 3, random.integers(0, 25))] for _ in range(4)]
        for run in (1, 3, 6):
            got = H.covered(pages, run)
            for p, page in enumerate(pages):
                want = [False] * len(page)
                others = {tuple(q[i : i + run]) for k, q in enumerate(pages) if k != p for i in range(len(q) - run + 1)}
                for i in range(len(page) - run + 1):
                    if tuple(page[i : i + run]) in others:
                        want[i : i + run] = [True] * run
                assert got[p].tolist() == want


def test_suffix_array():
    random = np.random.default_rng(1)
    for n in (0, 1, 2, 30, 200):
        flat = random.integers(0, 3, n)
        order, shared = H.suffix_array(flat)
        want = sorted(range(n), key=lambda i: flat[i:].tolist())
        assert order.tolist() == want
        for k in range(1, n):
            a, b = flat[want[k - 1] :].tolist(), flat[want[k] :].tolist()
            same = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
            assert shared[k] == same


def test_repetition_alone(spark, real):
    """With the markup's hints left out, the method itself removes most boilerplate of the given pages, and without repetition
    nothing of it would go; whole tables and one host's suffix array agree page by page."""
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    alone = {r.page_id: r.text for r in H.main_text(pages, hints=False).collect()}
    none = {r.page_id: r.text for r in H.main_text(pages, share=1.1, hints=False).collect()}
    right = {r.page_id: r.text for r in H.main_text(pages).collect()}
    by_host: dict = {}
    for r in pages.select("page_id", H.host_of(pages.url).alias("host"), "html").collect():
        by_host.setdefault(r.host, []).append((r.page_id, r.html))
    for rows in by_host.values():
        assert [alone[i] for i, _ in rows] == H.extract([html for _, html in rows], hints=False)
    excess = lambda texts: sum(max(0, len(texts[i]) - len(right[i])) for i in right)
    assert sum(alone[i] != none[i] for i in alone) > len(alone) / 4 and excess(alone) < 0.8 * excess(none), (excess(alone), excess(none))


def test_tolerates_broken_markup():
    for page in ("<", "<p", "</p></div>", "<b><p>x</b>y", "<article>open <b>end", "<!-- never closed", "<script>no end", "a < b & c &bogus; <3", "<p title='a>b'>q</p>"):
        H.extract([page])
    assert H.extract(["<article>open <b>end"]) == ["open end"]
    assert H.extract(["<article><p>a < b &amp; c</p></article>"]) == ["a < b & c"]


def test_table(spark, real):
    pages = real("pages")
    rows = {r.page_id: r for r in H.main_text(pages).collect()}
    for p in pages.collect():
        body = re.search(r"<article>(.*?)(</article>|$)", p.html, re.S).group(1)
        want = " ".join(unescape(re.sub(r"<[^>]*>", " ", re.sub(r"</?b>", "", body))).split())
        assert rows[p.page_id].text == want and rows[p.page_id].n_chars == len(want)


def test_a_large_host_is_judged_whole(spark):
    """Boilerplate on two of many pages of a host goes, as it would on a small host; other hosts don't count."""
    menu = "<div>home news sports weather about contact help</div>"
    htmls = [f"<p>page {i} tells {i * 3} stories about number {i * 7} only</p>" for i in range(60)]
    htmls[3], htmls[41] = menu + htmls[3], htmls[41] + menu
    rows = [(i, f"http://a.com/{i}", html) for i, html in enumerate(htmls)] + [(99, "http://b.com/", menu)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    found = {r.page_id: r.text for r in H.main_text(pages).collect()}
    assert [found[i] for i in range(60)] == H.extract(htmls) and "home" not in found[3] + found[41] and found[99].startswith("home news")


def test_edge_cases(spark):
    rows = [(1, "http://a.com/", None), (2, None, "<p>x</p>"), (3, "http://a.com/", ""), (None, "http://a.com/", "<article>y</article>"), (4, "u", "<article>z</article>"), (4, "u", "<article>z</article>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'t' AS text", "1 AS n_chars", "'h' AS host")
    found = sorted(((r.page_id or 0, r.text, r.n_chars) for r in H.main_text(pages).collect()))
    assert found == [(0, "y", 1), (1, "", 0), (2, "x", 1), (3, "", 0), (4, "z", 1), (4, "z", 1)]
    assert H.main_text(pages.limit(0)).count() == 0
