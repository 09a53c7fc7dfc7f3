import html as H
import itertools
import re

import numpy as np
import pytest

from predtopics.llm import html_text as ht


def brute_cut(terminal, edges):
    """Least cost over all labellings."""
    best = None
    for side in itertools.product((False, True), repeat=len(terminal)):
        cost = sum(-t for t, s in zip(terminal, side) if s and t < 0) + sum(t for t, s in zip(terminal, side) if not s and t > 0) + sum(c for a, b, c in edges if side[a] != side[b])
        best = cost if best is None else min(best, cost)
    return best


def test_cut_is_the_cheapest_labelling():
    rng = np.random.default_rng(4)
    for _ in range(150):
        n = int(rng.integers(1, 9))
        terminal = rng.normal(0, 2, n).round(2).tolist()
        edges = [(i, j, float(rng.random().__round__(2) * 2)) for i in range(n) for j in range(i) if rng.random() < 0.5]
        side = ht.minimum_cut(terminal, edges)
        cost = sum(-t for t, s in zip(terminal, side) if s and t < 0) + sum(t for t, s in zip(terminal, side) if not s and t > 0) + sum(c for a, b, c in edges if side[a] != side[b])
        assert cost == pytest.approx(brute_cut(terminal, edges))


def article(page):
    """The given tables' articles, read off their markup."""
    body = re.search(r"<article>(.*?)</article>", page, re.S)[1]
    parts = [H.unescape(re.sub(r"<b>", "", x)) for x in re.split(r"</?(?:h1|p|br)>", body)]
    return " ".join(" ".join(x.split()) for x in parts if x.split())


def test_whole_table(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    want = {r.page_id: article(r.html) for r in pages.collect()}
    assert {r.page_id: r.text for r in ht.extract(pages).collect()} == want


PAGE = """<html><head><title>T</title><script>if (a<b) document.write("<p>no</p>")</script></head><body>
<header class="site"><a href="/">Home</a> Site name</header><nav><ul><li><a href=x>One</a><li><a href=y>Two</a></ul></nav>
<div id="cookie-notice"><p>We use cookies to make this site better for all of our readers.</p></div>
<main><article><header><h1>The &quot;title&quot; &amp; more</h1></header><p>First   paragraph,\n with <b>bold</b> words and a <a href=z>link</a>.
<p>Second paragraph&nbsp;here.<aside><p>An aside that is not part of the text at all, really.</p></aside>
<div class="ad-slot"><p>Buy this now, it is the best thing you can buy today.</p></div><ul><li>item one<li>item two</ul><p>Short.</p>
<form><label>Mail</label><input name=a><button>Send</button></form><p>Last &lt;p&gt; words.</article></main>
<section id="comments"><p>A reader says something long about the article, and then some more.</p></section>
<div style="display:none"><p>Hidden words that nobody sees on the page.</p></div>
<footer><p>Copyright notice with a sentence that is quite long, as they are.</p></footer></body></html>"""


def test_furniture_is_left_out():
    assert ht.main_text(PAGE) == 'The "title" & more First paragraph, with bold words and a link. Second paragraph here. item one item two Short. Last <p> words.'


def test_page_without_article_marks():
    text = "A long paragraph of running text, with many words in it, that goes on. " * 5
    page = f'<body><div class="menu"><a href=a>A</a> <a href=b>B</a></div><div><p>{text}</p><p>{text}</p></div><div class="footer">Imprint</div></body>'
    assert ht.main_text(page) == f"{text.strip()} {text.strip()}"


def test_edges(spark):
    odd = [None, "", "   ", "<", "<p", "<p class='x>y</p>", "<!-- never closed <p>a</p>", "plain words only", "<script>never closed", "&", "<article>" + "<div>" * 3000 + "deep", "<article><p>" + "x " * 200_000]
    frame = spark.createDataFrame([(i, None, p, "clash") for i, p in enumerate(odd)] + [(None, "u", PAGE, ""), (None, "u", PAGE, "")], "page_id long, url string, html string, text string")
    got = ht.extract(frame).collect()
    assert len(got) == len(odd) + 2
    by = {r.page_id: r.text for r in got}
    assert [by[i] for i in (0, 1, 2, 6, 8)] == [""] * 5 and by[10] == "deep" and len(by[11]) == 399_999
    assert ht.extract(frame.limit(0)).count() == 0


def test_neighbours_decide_where_a_block_is_unclear():
    text = "A long paragraph of running text, with many words in it, that goes on. " * 5
    page = f"<body><div><a href=a>Top</a></div><div><p>{text}</p><h2>Part two</h2><p>{text}</p></div><div>Imprint</div></body>"
    blocks = {b.text: b for b in ht.label(ht.blocks_of(page))}
    assert blocks["Part two"].log_odds < 0 and blocks["Part two"].content  # by itself it is left out; between paragraphs it stays
    alone = {b.text: b for b in ht.label(ht.blocks_of("<body><div><a href=a>Top</a></div><h2>Part two</h2><div><a href=b>More</a></div></body>"))}
    assert not any(b.content for b in alone.values())
    links = "".join(f"<div><a href={i}>Link {i}</a></div>" for i in range(3))
    among = {b.text: b for b in ht.label(ht.blocks_of(f"<body>{links}<div>See you.</div>{links}</body>"), [-0.5 if k == "bias" else v for k, v in ht.PRIOR.items()])}
    assert among["See you."].log_odds > 0 and not among["See you."].content  # and the other way round


def test_elements_at_any_depth_are_seen():
    deep = "<article>" + "<div>" * 2000 + "<p>Some words of the article, as they are.</p><aside><p>An advert that says to buy this now.</p></aside>" + "</div>" * 2000 + "<p>The last words.</p></article>"
    assert ht.main_text(deep) == "Some words of the article, as they are. The last words."
    assert ht.main_text("<div>" * 60_000 + "<article><p>Words." + "</span>" * 60_000) == "Words."


def test_fitted_weights(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    weights = ht.fitted(pages)
    assert weights == ht.fitted(pages.repartition(5)) and weights != list(ht.PRIOR.values())
    x = np.array([e for r in pages.collect() for e, _ in ht.examples(ht.blocks_of(r.html))])
    y = np.array([v for r in pages.collect() for _, v in ht.examples(ht.blocks_of(r.html))])
    w, prior = np.array(weights), np.array(list(ht.PRIOR.values()))
    slope = x.T @ (1 / (1 + np.exp(-x @ w)) - y) / len(x) + ht.FIRMNESS * (w - prior)
    assert np.abs(slope).max() < 1e-6  # the least loss
    assert ht.fitted(pages.limit(0)) == list(ht.PRIOR.values())
    want = {r.page_id: article(r.html) for r in pages.collect()}
    assert {r.page_id: r.text for r in ht.op9_html_text(spark, sf_dir).collect()} == want
