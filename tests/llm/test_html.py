import html
import random
import re

import numpy as np
import pytest

from particle_engine.llm import html_extract as H

SCHEMA = "page_id long, url string, html string, text string, n_chars int"


def article(text):
    """Brute force on the given pages, which have exactly one article."""
    body = re.search(r"<article>(.*?)</article>", text, re.S).group(1)
    parts = [" ".join(html.unescape(re.sub(r"<[^>]*>", "", b)).split()) for b in re.split(r"</?(?:p|h1|br)[^>]*>", body)]
    return " ".join(p for p in parts if p)


def test_given_pages_match_brute_force(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    want = {r["page_id"]: article(r["html"]) for r in pages.collect()}
    got = {r["page_id"]: (r["text"], r["n_chars"]) for r in H.extract(pages).collect()}
    assert got == {k: (v, len(v)) for k, v in want.items()}


@pytest.mark.parametrize(
    "page, want",
    [
        (None, ""),
        ("", ""),
        ("<article><p>a <b>b</b>c<br>d&amp;e</p><form><input>x</form><aside>y</aside></article>", "a bc d&e"),
        ("<main><header><h1>T</h1></header><p>x</p><div class='comments'><p>nice</p></div></main><footer>f</footer>", "T x"),
        ("<article><p>cut off <i>here", "cut off here"),
        ("<div id=sidebar>s</div><article>k&eacute;y&nbsp;z<script>if(a</b){}</script></article>", "kéy z"),
        ("<nav><ul><li>m</nav><article><p>one<p>two</article>", "one two"),
        ('<article><h1 class="article-header">T</h1><p class="advert">buy</p><p class="cookie-notice">c</p><p>x <span class="share">tell <span>all</span></span>y</p><div class="related-work">r</div><div class="share-prices">q</div></article>', "T x y r q"),
        ('<article><div class="comment-list"><p>c</p></div><p>a<p class="ad">b<p>c</article><p>d', "a c"),
        ('<article><p class="x>one</p><p>two</p></article>', "one two"),
        ("<article>" + "<b>" * 5000 + "deep" + "<div>" * 3000 + "er" + "</article> no", "deep er"),
        ("<article><!-- <p>no</p> --><p>yes <a title='a>b'>l</a></p></article>", "yes l"),
    ],
)
def test_markup(spark, page, want):
    assert " ".join(H.stream(page)[1]) == want


def test_pages_without_article_lose_repeated_runs(spark):
    notice = "this site uses biscuits to count all of its visitors every day"
    rows = [(i, f"http://h.example/{i}", f"<body><div>{notice}</div><div>unique words of page number {i} follow here {i * 7}</div></body>", "x", 1) for i in range(4)]
    rows += [(9, "http://other.example/", f"<div>{notice}</div>", "x", 1), (9, "http://other.example/", f"<div>{notice}</div>", "x", 1), (None, None, None, None, None)]
    got = H.extract(spark.createDataFrame(rows, SCHEMA)).collect()
    texts = {r["page_id"]: r["text"] for r in got}
    assert len(got) == 7
    assert all(texts[i] == f"unique words of page number {i} follow here {i * 7}" for i in range(4))
    assert texts[9] == notice  # one page of its host: nothing repeats across pages
    assert texts[None] == ""


def test_ordinary_phrases_of_a_large_host_stay(spark):
    notice = "this site uses biscuits to count all of its visitors every day"
    phrase = "as everyone in the old town knows very well"
    own = [f"story {i} opens and {phrase} the year {i * 7} was long" for i in range(100)]
    rows = [(i, f"http://h.example/{i}", f"<div>{notice}</div><p>{t}</p><p>To be continued {i // 2}</p>", "x", 1) for i, t in enumerate(own)]
    got = {r["page_id"]: r["text"] for r in H.extract(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == {i: f"{t} To be continued {i // 2}" for i, t in enumerate(own)}


def brute_runs(pages, least):
    """Pages of every run of ``least`` words, by listing all."""
    seen = {}
    for p, texts in enumerate(pages):
        for t in texts:
            words = t.lower().split(" ")
            for j in range(len(words) - least + 1):
                seen.setdefault(" ".join(words[j : j + least]), set()).add(p)
    return {H._hash(k): len(v) for k, v in seen.items() if len(v) > 1}


def test_suffix_array_matches_brute_force():
    rng = np.random.default_rng(3)
    for text in (rng.integers(0, 3, 200), np.zeros(50, int), np.arange(5), np.array([7])):
        order, lcp = H.suffix_array(text)
        suffixes = sorted(range(len(text)), key=lambda i: text[i:].tolist())
        assert order.tolist() == suffixes
        common = [next((k for k in range(len(text)) if i + k >= len(text) or j + k >= len(text) or text[i + k] != text[j + k]), len(text)) for i, j in zip(suffixes[1:], suffixes)]
        assert lcp.tolist() == [0, *common]


def test_repeated_runs_match_brute_force():
    rng = random.Random(4)
    passages = [" ".join(f"p{k}w{rng.randrange(9)}" for _ in range(60)) for k in range(4)]
    pages = [[" ".join(f"w{rng.randrange(50)}" for _ in range(30)) + " " + rng.choice(passages)[: rng.randrange(100, 240)].rsplit(" ", 1)[0], "Short block"] for _ in range(40)]
    got = dict(H.repeated_runs(pages))
    assert got.pop(H._hash("\x00short block")) == 40
    assert got == brute_runs(pages, H.MIN_RUN) and got


def test_array_acts_on_articles_of_a_host(spark):
    notice = " ".join(f"notice{i}" for i in range(30))
    passage = " ".join(f"quoted{i}" for i in range(60))
    body = lambda i: " ".join(f"own{i}x{j}" for j in range(40))
    pages = [(i, f"http://h.example/{i}", f"<article><p>{body(i)} {passage if i % 4 == 0 else ''}</p><p>{notice} {i}</p><p>Like this page</p></article>", "x", 1) for i in range(600)]
    got = {r["page_id"]: r["text"] for r in H.extract(spark.createDataFrame(pages, SCHEMA)).collect()}
    # what every page has goes, over several groups of pages; what a quarter quotes is content
    assert got == {i: " ".join(f"{body(i)} {passage if i % 4 == 0 else ''} {i}".split()) for i in range(600)}


def test_very_long_page(spark):
    long = "".join(f"<p>word{i} <b>and</b> more" for i in range(60_000))
    got = H.extract(spark.createDataFrame([(1, "http://h/1", f"<article>{long}", "x", 1), (2, "http://h/2", "<" * 20_000 + '"' * 20_000, "x", 1)], SCHEMA)).collect()
    assert {r["page_id"]: r["n_chars"] for r in got}[1] == len(" ".join(f"word{i} and more" for i in range(60_000)))


def test_empty_table(spark):
    assert H.extract(spark.createDataFrame([], SCHEMA)).collect() == []
