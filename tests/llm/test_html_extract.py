import html
import re
import time

import pytest

from filekind.llm import html_extract
from filekind.llm.html_extract import Page


def best(source):
    return Page(source).text(())


LONG = "Plain words of the article go on here, and on. " * 4


SIDE = "Side words that go on and on. " * 2


@pytest.mark.parametrize("source", [
    "<main class='no-sidebar'><p>{0}</p></main>", "<div class='content has-sidebar'><p>{0}</p></div><div class='sidebar'>x</div>", "<body class='menu-open'><div class='page with-ads'><article>{0}</article></div>",
    "<article title=it's><p class=x'y>{0}</p></article><p title='z'>", "<div class='nav'><article>{0}</article></div><div class='nav'>{1}</div>", "<form id=aspnet><div class=menu>{1}</div><article>{0}</article></form>",
    "<article>{0}<div class='ad'>{1}</div><section id='comments'><ol><li class='comment'>{1}</ol></section></article>", "<div class=site-header>{1}</div><div class=text>{0}{0}</div>".replace("{0}{0}", "{0}"),
    "<head><title>t</title><p>{0}", "<article>{0}<select><option>x</article>", "<noscript>{1}</noscript><template>{1}</template><div>{0}</div>", "<div class='post-12'>{0}</div><div class='newsletter-signup'>{1}</div>",
])
def test_parts_and_remarks(source):
    assert best(source.format(LONG, SIDE)) == LONG.strip()


@pytest.mark.parametrize("inside", [
    "<div class='notice'>kept</div>", "<div class=alert>kept</div>", "<section id='related-work'>kept</section>", "<math><mi>kept</mi></math>", "<svg><text>kept</text></svg>", "<object>kept</object>",
    "<canvas>kept", "<video>kept", "<div class='no-ads'>kept</div>", "<header>kept</header>", "<p data-x='a>b' title=don't>kept</p>",
])
def test_what_an_article_holds_stays(inside):
    assert best(f"<article><p>{LONG}</p>{inside}<p>{LONG}</p></article>") == f"{LONG}kept {LONG.strip()}"


def test_deep_and_odd_markup_takes_linear_time():
    began = time.process_time()
    assert best("<div>" * 100_000 + "deep") == "deep"
    assert best("<div>" * 50_000 + "</p></section>" * 50_000 + "deep") == "deep"
    assert best("<a title='x" * 20_001 + "'>deep") == "deep"
    assert best("<li>x" * 50_000) == " ".join("x" * 50_000)
    assert time.process_time() - began < 30


@pytest.mark.parametrize(("source", "want"), [
    ("", ""), ("just text &amp; more", "just text & more"), ("<p>a<b>b</b> c\n\t d<br>e", "ab c d e"),
    (f"<body><nav><a href=x>menu</a></nav><article><h1>T</h1><p>{LONG}</p></article><footer>f</footer>", f"T {LONG.strip()}"),
    (f"<header>site</header><main><header><h1>T</h1></header><p>{LONG}<script>var a='</p>';</script></main>", f"T {LONG.strip()}"),
    (f"<div class='post'><p>{LONG}</p><div class='comments'><p>{LONG}{LONG}</p></div><aside>x</aside><form>f<input></form></div>", LONG.strip()),
    (f"<div id=cookie-notice>{LONG}</div><div class=content>{LONG}&lt;ok&gt; 1 < 2</div>", f"{LONG}<ok> 1 < 2"),
    (f"<article><!-- c > --><p title='a>b'>{LONG}<style>p{{}}</style></article", LONG.strip()),
    (f"<article><p>{LONG}<ul><li>one<li>two</ul><table><tr><td>x<td>y</table>", f"{LONG}one two x y"),
    ("<article><p>cut &am", "cut &am"), ("<div hidden>a</div><div style='display: none'>b</div><p>c", "c"), ("<title>t</title><body><textarea>x</textarea>y", "y"),
])
def test_pages(source, want):
    assert best(source) == want


def test_whole_table(spark, sf):
    pages = {r.page_id: r for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    got = html_extract.op4_consensus_paths(spark, sf).collect()
    assert {r.page_id for r in got} == set(pages) and len(got) == len(pages)
    for r in got:
        inner = re.search(r"<article>(.*?)</article>", pages[r.page_id].html, re.S)[1]
        parts = re.sub(r"<[^>]*>", "", re.sub(r"</?(?:p|h1|br)\b[^>]*>", "\0", inner)).split("\0")
        want = " ".join(x for x in (" ".join(html.unescape(p).split()) for p in parts) if x)
        assert (r.text, r.n_chars, r.url) == (want, len(want), pages[r.page_id].url)


def test_host_consensus_overrules_a_page(spark):
    def page(body, extra):
        return f"<body><div class='story-12'><p>{body}</p></div><div class='box'><p>{extra}</p></div>"

    rows = [(i, f"http://h.com/{i}", page(LONG, "short")) for i in range(9)] + [(9, "http://h.com/9", page("little", LONG * 3)), (10, "http://o.com/", page("little", LONG * 3))]
    got = {r.page_id: r.text for r in html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[9] == "little" and got[10] == (LONG * 3).strip() and got[0] == LONG.strip()


def test_vote_decides_where_divs_have_no_class(spark):
    """Bare divs: a page whose side column is the longer one, and a host on which most pages quote one long text beside their own."""
    def page(body, extra):
        return f"<body><div><p>top</p></div><div><p>{body}</p></div><div><p>{extra}</p></div>"

    rows = [(i, "http://h.com/", page(f"{i} {LONG}", "short")) for i in range(9)] + [(9, "http://h.com/", page("little", LONG * 3))]
    rows += [(20 + i, "http://q.com/", page(f"own {i} " * (3 + 100 * (i > 5)), "terms of use " * 20)) for i in range(9)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    alone = {i: best(h) for i, _, h in rows}
    got = {r.page_id: r.text for r in html_extract.extract(df).collect()}
    assert got[9] == "little" != alone[9] and got[0] == f"0 {LONG.strip()}"
    assert got[20] == "own 0 own 0 own 0" != alone[20]


def test_edges(spark, monkeypatch):
    rows = [(1, None, None), (2, "x", ""), (None, "http://a/", "<p>t"), (3, "http://a/", "<p>t"), (3, "http://a/", "<p>t"), (4, "http://b/", "<div>" * 3000 + "deep"), (5, "http://b/", "<p>" + "long " * 50_000)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 text", "'p' paths", "'h' host", "2 steps")
    want = sorted([(1, None, ""), (2, "x", ""), (None, "http://a/", "t"), (3, "http://a/", "t"), (3, "http://a/", "t"), (4, "http://b/", "deep"), (5, "http://b/", ("long " * 50_000).strip())], key=str)
    for offered in (lambda won: won, html_extract.offered):
        monkeypatch.setattr(html_extract, "offered", offered)
        assert sorted(((r.page_id, r.url, r.text) for r in html_extract.extract(df).collect()), key=str) == want
    assert html_extract.extract(df.limit(0)).count() == 0
