import html
import itertools
import math
import random
import re

import pytest

from tiersort.llm import html_text as h
from tiersort.llm.queries import QUERIES
from helpers import DATA

LONG = "A sentence of the story that goes on for a while, with commas, and ends here."


def text(source):
    return h.main_text(source, h.standard_model())


def test_marginals_equal_brute_force():
    """Sum over all labellings of small random trees."""
    rng = random.Random(1)
    for _ in range(25):
        page = h.Page()
        for i in range(rng.randrange(2, 8)):
            page.add(rng.choice(["div", "p", "nav", "b", "form", "ul"]), rng.randrange(len(page.tag)), rng.choice(["", ' class="ad"', ' id="content"']))
        own, edge = h.standard_model().potentials(page)
        n = len(own)
        total, one = 0.0, [0.0] * n
        for z in itertools.product((0, 1), repeat=n):
            w = math.exp(sum(o * y for o, y in zip(own, z)))
            for i in range(1, n):
                p = edge[i][z[page.parent[i]]]
                w *= p if z[i] else 1 - p
            total += w
            for i in range(n):
                one[i] += w * z[i]
        for i, p in enumerate(h.standard_model().marginals(page)):
            assert abs(p - one[i] / total) < 1e-6


def test_given_pages(spark):
    pages = {r.page_id: r.html for r in spark.read.parquet(f"{DATA}/pages.parquet").collect()}
    for r in QUERIES["op5_html_text"](spark, DATA).collect():
        article = re.search(r"<article>(.*)</article>", pages[r.page_id], re.S)[1]
        blocks = [" ".join(html.unescape(re.sub("<[^>]*>", " ", x)).split()) for x in re.split("</?(?:p|h1)>", article)]
        assert r.text == "\n\n".join(x for x in blocks if x) and r.n_chars == len(r.text)


ARTICLE = f"<h1>Title &amp; more</h1><p>{LONG}</p><p>Second <b>part</b>&nbsp;of\n it &#233;</p>"
WANT = f"Title & more\n\n{LONG}\n\nSecond part of it é"


@pytest.mark.parametrize("page", [
    f"<html><body><nav><a href=x>Home</a></nav><article>{ARTICLE}</article><footer>(c) us</footer></body></html>",
    f"<body><div class='header'><h1>Site</h1><p>{LONG}</p></div><div id=content>{ARTICLE}</div><div class='sidebar'><p>{LONG}</p><p>{LONG}</p></div></body>",
    f"<main>{ARTICLE}</main><section class='comments'><h2>Comments</h2>" + f"<div class='comment'><p>{LONG}</p></div>" * 30 + "</section>",
    f"<article>{ARTICLE}<aside><p>{LONG}</p></aside><form><p>{LONG}</p><input></form></article>",
    f"<div class='cookie-notice'><p>{LONG}</p></div><div class=post>{ARTICLE}</div><div class='ad'>{LONG}</div>",
    f"<body>{ARTICLE}</body>", f"<header><ul><li><a>One</a></li></ul></header>{ARTICLE}<script>var a='<p>no</p>'</script><style>p</style>",
    f"<article>{ARTICLE}</article><ol class=commentlist><li><p>{LONG}</p><li><p>{LONG}</ol><div class='related-posts'><a>x</a></div>",
    f"<div class='wrapper'><div class='nav-bar'><a>x</a> <a>y</a></div><div class='article-body'>{ARTICLE}</div></div>",
    f"<article><!-- <p>no</p> -->{ARTICLE}<div class='share'>Share this</div><noscript>no</noscript></article><div id='disqus'><p>{LONG}</p></div>",
])
def test_layouts(page):
    assert text(page) == WANT


def test_markup_of_all_sorts():
    assert text("<article><p><b>One<br>two<p>three <i>four</i>five</b><ul><li>a<li>b &lt;p&gt;</ul></article>") == "One two\n\nthree fourfive\n\na\n\nb <p>"
    assert text("just words &amp; no tags < 3") == "just words & no tags < 3"
    assert text(None) == text("") == text("<nav>x</nav>") == ""
    assert text("<article>" + "<div>" * 40 + LONG) == LONG
    assert text("<article>" + "<div>" * 20000 + LONG) in ("", LONG)  # no limit of depth
    assert len(text("<article>" + f"<p>{LONG}</p>" * 30000)) == 30000 * (len(LONG) + 2) - 2
    assert text("<article><p>unclosed <") == "unclosed <"


def test_held_out_layouts():
    """Other pages of the grammar: share of elements whose side is right."""
    right = total = 0
    for source in h.training_pages(120, seed=99):
        page = h.parse(source)
        label = h.sides(page)
        for i, p in enumerate(h.standard_model().marginals(page)):
            if i and page.tag[i] not in ("html", "body", *h.MUTE):
                total += 1
                right += (p > 0.5) == label[i]
    assert right > 0.97 * total


def test_edge_rows(spark):
    df = spark.createDataFrame([(1, None, None, "t"), (2, "u", "", "t"), (2, "u", "<p>x</p>", None), (None, None, "<p>y</p>", "")], "page_id long, url string, html string, text string")
    assert sorted((r.page_id or 0, r.text, r.n_chars) for r in h.extract(df).collect()) == [(0, "y", 1), (1, "", 0), (2, "", 0), (2, "x", 1)]
    assert h.extract(df.limit(0)).count() == 0
