"""URL rules and listed URLs behind a blocked Bloom filter.

Entries are canonical keys: a host and a path prefix for rules, the canonical form of the URL for listed URLs. A URL asks for every suffix of its host that is in the list of
hosts, with every prefix of its path that has a length listed for that host. The Bloom filter, one 256-bit block for each key's hash, lets through few keys
that are not listed; an exact hash join with the list removes those, and the longest entry left decides. Where no rule fits, a URL whose canonical form is
listed is blocked, and any other gets the default verdict. Everything is a DataFrame: the filter is a table of blocks; it, the lists and the hits are broadcast where their measured bytes
are few, and joined by key beyond that.

The canonical form lowers scheme and host, drops user, default port, needless dots and fragment, resolves dot segments, and writes percent codes in one way.

Defined cases: a null URL or one without `://` has empty host and path and is in no list; entries of one length go to the longer host,
then to block before allow; entries listed twice count once; repeated pages keep their rows; very long hosts and paths are cut to no more than the list's longest; empty tables give empty results; further columns are left alone.
"""

from __future__ import annotations

import re
from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from .common import BROADCAST_BYTES, measured, offered, stash, table

#: Rules of the contract: (verdict, host, path).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
DEFAULT = "allow"
#: Filter bits for each entry, and bits set by an entry.
BITS_PER_KEY, PROBES = 16, 6
#: Ports that a scheme implies.
PORTS = {"http": "80", "https": "443", "ftp": "21", "ws": "80", "wss": "443"}
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    return F.coalesce(F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    return F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


_CODE = re.compile(r"%([0-9A-Fa-f]{2})")


def _coded(text: str) -> str:
    """Percent codes of letters, digits and -._~ as these characters, others with capital digits."""
    def one(m: re.Match) -> str:
        c = chr(int(m[1], 16))
        return c if c.isascii() and (c.isalnum() or c in "-._~") else m[0].upper()

    return _CODE.sub(one, text) if "%" in text else text


def canonical(url: str | None) -> str | None:
    """The one form of a URL that lists hold; None without `://`."""
    scheme, found, rest = (url or "").strip().partition("://")
    if not found:
        return None
    scheme, rest = scheme.lower(), rest.partition("#")[0]
    authority, path, query = re.match(r"([^/?]*)([^?]*)(.*)", rest, re.S).groups()
    host, _, port = authority.rpartition("@")[2].lower().partition(":")
    host = ".".join(x for x in _coded(host).split(".") if x)
    kept: list[str] = []
    parts = _coded(path).split("/")[1:]
    for p in parts:
        if p == "..":
            del kept[-1:]
        elif p != ".":
            kept.append(p)
    if parts and parts[-1] in (".", ".."):
        kept.append("")
    return f"{scheme}://{host}{':' + port if port and port != PORTS.get(scheme) else ''}/{'/'.join(kept)}{_coded(query)}"


@F.pandas_udf(StringType())
def canonical_url(urls: pd.Series) -> pd.Series:
    return urls.map(lambda u: canonical(u if isinstance(u, str) else None))


def rule_table(spark: SparkSession, rules: Sequence[tuple[str, str, str]] = RULES) -> DataFrame:
    return spark.createDataFrame(list(rules), "verdict string, host string, path string")


def _bits(key: str) -> tuple[Column, list[Column]]:
    """The hash that picks a block, and the four 64-bit words an entry sets in it."""
    spread = F.xxhash64(F.lit(1), F.col(key))
    at = [F.shiftrightunsigned(spread, 8 * i).bitwiseAND(F.lit(255)) for i in range(PROBES)]
    words = []
    for w in range(4):
        word = F.lit(0).cast("long")
        for p in at:
            word = word.bitwiseOR(F.when(F.shiftright(p, 6) == w, F.call_function("shiftleft", F.lit(1).cast("long"), p.bitwiseAND(F.lit(63)).cast("int"))).otherwise(F.lit(0).cast("long")))
        words.append(word)
    return F.xxhash64(F.lit(0), F.col(key)), words


def bloom_blocks(keys: DataFrame, blocks: int, key: str = "key") -> DataFrame:
    """(block, w0..w3): the filter, one row for each block that has bits."""
    pick, words = _bits(key)
    return keys.select(F.pmod(pick, F.lit(blocks)).alias("block"), *(w.alias(f"w{i}") for i, w in enumerate(words))).groupBy("block").agg(*(F.bit_or(f"w{i}").alias(f"w{i}") for i in range(4)))


def may_be_listed(asked: DataFrame, filter_: DataFrame, blocks: int, limit: int = BROADCAST_BYTES, key: str = "key") -> DataFrame:
    """The rows of `asked` whose key may be in the (stashed) filter: all that are, and few others."""
    pick, words = _bits(key)
    probed = asked.withColumn("__block", F.pmod(pick, F.lit(blocks)))
    f = filter_.select(F.col("block").alias("__block"), *(F.col(f"w{i}").alias(f"__w{i}") for i in range(4)))
    for i, w in enumerate(words):
        probed = probed.withColumn(f"__q{i}", w)
    passed = probed.join(offered(f, limit), "__block")
    for i in range(4):
        passed = passed.where(F.col(f"__w{i}").bitwiseAND(F.col(f"__q{i}")) == F.col(f"__q{i}"))
    return passed.select(*asked.columns)


def listed_among(asked: DataFrame, entries: DataFrame, on: list[str], limit: int = BROADCAST_BYTES) -> DataFrame:
    """asked (with a column key) joined with the (stashed) entries by `on`, which has the key: first through the filter, then exactly."""
    count = entries.count()
    blocks = max(1, -(-count * BITS_PER_KEY // 256))
    possible = may_be_listed(asked, stash(bloom_blocks(entries, blocks)), blocks, limit)
    return possible.join(offered(entries, limit), on)


def rule_hits(seen: DataFrame, rules: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """(host, path, best) for the different (host, path) of seen that a rule fits; best: n, nh, verdict, key."""
    entries = stash(rules.groupBy("host", "path").agg(F.max("verdict").alias("verdict")).select(F.concat("host", "path").alias("key"), F.col("host").alias("h"), F.col("path").alias("p"), "verdict"))
    hosts = stash(entries.groupBy("h").agg(F.sort_array(F.collect_set(F.length("p"))).alias("lengths")))
    longest, deepest = entries.agg(F.coalesce(F.max(F.length("h")), F.lit(0)), F.coalesce(F.max(F.length("p")), F.lit(0))).first()
    # Of a host longer than any listed only its end counts; what stands before the first dot there is no whole label.
    cut = F.length("host") > longest
    labels = F.split(F.when(cut, F.right("host", F.lit(longest + 1))).otherwise(F.col("host")), r"\.")
    labels = F.when(cut, F.slice(labels, 2, F.greatest(F.size(labels), F.lit(1)))).otherwise(labels)
    few = seen.select("host", "path", labels.alias("labels"), F.left("path", F.lit(deepest)).alias("head")).dropDuplicates(["host", "path"]).where(F.size("labels") > 0)
    suffixes = F.transform(F.sequence(F.lit(1), F.size("labels")), lambda i: F.array_join(F.slice("labels", i, F.size("labels")), "."))
    asked = (
        few.select("host", "path", "head", F.explode(suffixes).alias("h")).join(offered(hosts, limit), "h")
        .select("host", "path", "h", "head", F.explode(F.filter("lengths", lambda n: n <= F.length("head"))).alias("n"))
        .select("host", "path", "h", F.expr("left(head, n)").alias("p")).withColumn("key", F.concat("h", "p"))
    )
    certain = listed_among(asked, entries, ["key", "h", "p"], limit)
    return certain.groupBy("host", "path").agg(F.max(F.struct(F.length("key").alias("n"), F.length("h").alias("nh"), "verdict", "key")).alias("best"))


def judge(pages: DataFrame, rules: DataFrame, listed: DataFrame | None = None, id_col: str = "page_id", url_col: str = "url", default: str = DEFAULT, limit: int = BROADCAST_BYTES) -> DataFrame:
    """One row for each page: page_id, host, path, rule, verdict. rules: verdict, host, path; listed: url, the blocked URLs. limit: bytes up to which tables are broadcast."""
    seen = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    # Written, so that both sides of the joins are plain exchanges and a URL that many pages share can be split.
    best = offered(stash(rule_hits(seen, rules, limit)), limit)
    told = seen.join(best, ["host", "path"], "left")
    verdict = F.lit(default)
    if listed is not None:
        entries = stash(listed.select(canonical_url("url").alias("key")).where("key is not null").distinct())
        asked = seen.select("url").distinct().select("url", canonical_url("url").alias("key")).where("key is not null")
        hits = stash(listed_among(asked, entries, ["key"], limit).select("url", F.lit(True).alias("hit")))
        told = told.join(offered(hits, limit), "url", "left")
        verdict = F.when(F.col("hit"), F.lit("block")).otherwise(verdict)
    return told.select("page_id", "host", "path", F.col("best.key").alias("rule"), F.coalesce("best.verdict", verdict).alias("verdict"))


def op6_blocked_bloom(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages"), rule_table(spark))


ORACLE_SQL = r"""
WITH cut AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
seen AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut),
rules(verdict, h, p) AS (VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')),
fit AS (SELECT s.page_id, r.h || r.p AS rule, r.verdict, row_number() OVER (PARTITION BY s.page_id ORDER BY length(r.h || r.p) DESC) AS k
        FROM seen s JOIN rules r ON (s.host = r.h OR ends_with(s.host, '.' || r.h)) AND starts_with(s.path, r.p))
SELECT s.page_id, s.host, s.path, f.rule, coalesce(f.verdict, 'allow') AS verdict FROM seen s LEFT JOIN fit f ON f.page_id = s.page_id AND f.k = 1
"""
