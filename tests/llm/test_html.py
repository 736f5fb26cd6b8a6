"""Main text: what the article keeps, what is cut, broken markup in linear time, odd rows."""

import time

import pytest

from serieslake.llm import html
from serieslake.llm.queries import QUERIES

LONG = "Some long text, with commas, and yet more of it. " * 20
SAID = " ".join(LONG.split())


@pytest.mark.parametrize(
    ("page", "want"),
    [
        (f"<article><h1>T</h1><div>{LONG}</div><div><p>Short closing sentence.</p></div></article>", f"T\n{SAID}\nShort closing sentence."),
        (f"<body><nav>menu</nav><div class=intro><p>Short intro.</p></div><div>{LONG}</div><footer>f</footer>", f"Short intro.\n{SAID}"),
        (f"<article><p>{LONG}</p><p class=related>In related work we see more.</p><p class=ad>Buy!</p></article>", f"{SAID}\nIn related work we see more."),
        (f"<main><div class=sidebar>x</div><section><p>{LONG}</section></main><aside>y</aside>", SAID),
        (f"<div><div><p>{LONG}</p></div></div><div><a href=x>one</a> <a href=y>two</a></div>", SAID),
        (f"<article><p title=it's>{LONG}</p><p data-x='a>b'>&lt;b&gt; \n &amp;</p><!-- <p>no</p> --></article>", f"{SAID}\n<b> &"),
        (f"<article><p>{LONG}</p><div class='user comments'><p>{LONG}</p></div><form><p>f</p></form></article>", SAID),
    ],
)
def test_what_stays(page, want):
    assert html.main_text(page) == want


@pytest.mark.parametrize("page", ["<a b" * 250_000, "<div>a" * 60_000, "<div>" * 60_000 + "x" + "</table>" * 60_000, '<a ="' * 100_000 + '>"', "<p>" * 100_000 + "</p>" * 100_000, "<b>" * 50_000 + "<hr>x" * 50_000, "<li>x" * 100_000, "<!--" * 100_000, "<script>" + "</scrip>" * 100_000], ids=range(9))
def test_broken_markup_takes_linear_time(page):
    html.main_text(page[: len(page) // 10])
    begun = time.process_time()
    html.main_text(page)
    assert time.process_time() - begun < 5


def test_registered_query(spark, tmp_path):
    rows = [(1, "u", f"<article><p>{LONG}</p></article>", 1), (1, "u", f"<article><p>{LONG}</p></article>", 1), (2, None, None, None), (None, "v", "", None)]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string, n_chars int")
    df.write.parquet(f"{tmp_path}/pages.parquet")
    got = sorted((r.page_id or 0, r.url or "", r.text, r.n_chars) for r in QUERIES["op1_html_main_text"](spark, str(tmp_path)).collect())
    assert got == [(0, "v", "", 0), (1, "u", SAID, len(SAID)), (1, "u", SAID, len(SAID)), (2, "", "", 0)]
    assert html.extract(df.limit(0)).count() == 0
