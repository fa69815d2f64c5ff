import re

import pytest

from filekind.llm import url_filter
from filekind.llm.url_filter import RULES


def plain(url, rules=RULES):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host, tail = re.match(r"([^/?#]*)([^?#]*)", rest).groups()
    host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
    fits = [(len(h + p), len(h), v, h + p) for v, h, p in rules if (host == h or host.endswith("." + h)) and tail.startswith(p)]
    best = max(fits, default=None)
    return host, tail, best and best[3], best[2] if best else "allow"


URLS = [None, "", "no scheme", "http://NET/", "http://x.net", "https://Example.NET/en/1", "https://a.example.net/en", "https://anexample.net/en/1", "http://example.com/de/?q", "http://example.com/de", "http://m.example.com/fr/#x", "ftp://www.a.org/fr/", "://org/fr/x", "http://h?x=/net/", "http://h#://net/", "http://ÄNET.net/ä", "http://a..net/", "http://net./", "x://y://z.net/", "http://" + "a." * 300 + "net/" + "p/" * 5000]


def test_edges(spark):
    df = spark.createDataFrame([(i, u) for i, u in enumerate(URLS)] + [(3, URLS[3])], "page_id long, url string").selectExpr("*", "'c' host", "1 path", "'d' rule", "2 key")
    got = sorted(map(tuple, url_filter.judge(df, url_filter.rule_table(spark)).collect()))
    assert got == sorted([(i, *plain(u)) for i, u in enumerate(URLS)] + [(3, *plain(URLS[3]))])
    assert url_filter.judge(df.limit(0), url_filter.rule_table(spark)).count() == 0
    assert {r.verdict for r in url_filter.judge(df, url_filter.rule_table(spark).limit(0)).collect()} == {"allow"}


@pytest.mark.parametrize("limit", [0, 1 << 25])
def test_long_list(spark, limit):
    rules = [("block" if i % 3 else "allow", f"h{i % 50}.com", f"/{i % 7}/{i}/") for i in range(700)] + [("block", "com", ""), ("allow", "h1.com", "/1")]
    urls = [f"http://s.h{i % 60}.com/{i % 7}/{i}/z" for i in range(900)]
    got = url_filter.judge(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), url_filter.rule_table(spark, rules), limit=limit)
    assert sorted(map(tuple, got.collect())) == sorted((i, *plain(u, rules)) for i, u in enumerate(urls))


def test_many_path_lengths_and_long_urls(spark):
    rules = [("block" if n % 2 else "allow", "deep.org", "/" + "x" * n) for n in range(2500)] + [("block", "a" * 300 + ".org", "/")]
    urls = ["http://deep.org/" + "x" * n for n in (0, 7, 2499, 4000)] + ["http://" + "b." * 50_000 + "deep.org/xx", "http://" + "c" * 400 + ".deep.org/x", "http://" + "d" * 100_000 + "/", "http://" + "a" * 300 + ".org/" + "p" * 100_000, "http://x" + "a" * 300 + ".org/"]
    got = url_filter.judge(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), url_filter.rule_table(spark, rules))
    assert sorted(map(tuple, got.collect())) == sorted((i, *plain(u, rules)) for i, u in enumerate(urls))


@pytest.mark.parametrize(("url", "want"), [
    (None, None), ("no scheme", None), ("HTTP://User:pw@WWW.Example.com.:80", "http://www.example.com/"), ("https://a..b/./x/../%7Ey%2f?q=%41#f", "https://a.b/~y%2F?q=A"), ("http://a:8080/x/.", "http://a:8080/x/"),
    (" ftp://a:21/../z ", "ftp://a/z"), ("http://a?x", "http://a/?x"), ("http://a/100%", "http://a/100%"),
])
def test_canonical_form(url, want):
    assert url_filter.canonical(url) == want
    assert want is None or url_filter.canonical(want) == want


@pytest.mark.parametrize("limit", [0, 1 << 25])
def test_listed_urls(spark, limit):
    listed = spark.createDataFrame([("http://Bad.org:80/a/../b",), ("http://example.net/en/1",), ("x",), (None,), ("http://bad.org/b",)], "url string")
    urls = ["http://bad.org/b#x", "http://bad.org/b/", "http://example.net/en/%31", None, "http://bad.org/%62", "http://bad.org/b#x"]
    got = url_filter.judge(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), url_filter.rule_table(spark), listed, limit=limit)
    assert [r.verdict for r in got.orderBy("page_id").collect()] == ["block", "allow", "allow", "allow", "block", "block"]


def test_filter_lets_all_listed_and_few_others_through(spark):
    keys, others = spark.range(20_000).selectExpr("concat('k', id) key"), spark.range(20_000).selectExpr("concat('o', id) key")
    blocks = 20_000 * url_filter.BITS_PER_KEY // 256
    held = url_filter.bloom_blocks(keys, blocks)
    assert url_filter.may_be_listed(keys, held, blocks).count() == 20_000
    assert url_filter.may_be_listed(others, held, blocks).count() < 400
