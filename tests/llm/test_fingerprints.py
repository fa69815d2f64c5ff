import hashlib
import math
import re
import struct
from collections import Counter

import regex
import xxhash
from pyspark.sql import functions as F

from filekind.llm import fingerprints as fp


def words(text):
    return {w for w in re.split(r"[\W_]+", text.lower()) if w}


def test_lexicon_is_the_band(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = docs.select("text").collect()
    df = Counter(w for r in rows for w in words(r.text))
    band = {w for w, n in df.items() if 3.0 <= math.log(len(rows) / n) <= 4.0}
    got = {r.term: r.mask for r in fp.lexicon(docs, low=3.0, high=4.0, rates=(1, 2)).collect()}
    assert set(got) == band
    assert all(m & 1 for m in got.values()) and 0.3 < sum(m >> 1 for m in got.values()) / len(got) < 0.7


def test_edited_text_and_likeness(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()]
    got = {r.doc_id: r for r in fp.op1_imatch(spark, sf).collect()}
    assert len(got) == len(rows)
    texts = {}
    for i, (d, t) in enumerate(rows):
        q = len(t) // 4
        edited = t[: len(t) - q] + rows[(i + 1) % len(rows)][1][:q]
        assert got[d].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest() and got[d].n_chars == len(t)
        assert texts.setdefault(t, got[d].fingerprint) == got[d].fingerprint
        assert 0 <= got[d].near_edited <= 1 and 0 <= got[d].near_next <= 1
    assert len(set(texts.values())) > 0.9 * len(texts)
    assert sum(r.near_edited for r in got.values()) > 3 * sum(r.near_next for r in got.values())


def test_hash_is_of_the_sorted_terms(spark):
    df = spark.createDataFrame([(1, "b a c"), (2, "c; B a a"), (3, "a b d"), (4, "e f g")], "doc_id long, text string")
    got = {r.doc_id: r.fingerprint for r in fp.imatch(df, low=0.0, high=9.0, rates=(1,)).collect()}
    want = spark.range(1).select(F.lower(F.hex(F.xxhash64(F.lit(0), F.array(*map(F.lit, "abc")))))).first()[0]
    assert got[1] == got[2] == want.zfill(16) and got[3] != got[1]


def test_shuffled_lexicon_gives_the_same(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert sorted(fp.imatch(docs).collect()) == sorted(fp.imatch(docs, broadcast_bytes=0).collect())


def test_edges(spark):
    rows = [(5, None), (7, ""), (-9, "abc"), (100, "ä" * 9), (100, "ä" * 9), (None, "lost words here"), (8, "long " * 20_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 bucket", "2 pos", "'x' term")
    got = fp.imatch(df).collect()
    assert len(got) == len(rows)
    by = {r.doc_id: r for r in got}
    assert by[5].n_chars == by[7].n_chars == 0 and by[5].fingerprint == by[7].fingerprint and by[5].near_edited == by[5].near_next == 1.0
    assert by[None].near_next == 0.0 and by[None].edited_sha256 == hashlib.sha256(b"lost words here"[:12]).hexdigest()
    assert by[8].edited_sha256 == hashlib.sha256(("long " * 15_000 + "ä" * 9).encode()).hexdigest()
    assert fp.imatch(df.limit(0)).count() == 0
    one = fp.imatch(spark.createDataFrame([(3, "abcdefgh")], "doc_id long, text string")).first()
    assert one.edited_sha256 == hashlib.sha256(b"abcdefab").hexdigest() and one.near_next == 1.0


def hash_of(*parts):
    """Spark's chained hash of whole numbers (4 or 8 bytes) and strings."""
    h = 42
    for p in parts:
        h = xxhash.xxh64_intdigest(p if isinstance(p, bytes) else p.encode(), h)
    return h


def signed(h):
    return h - (1 << 64) if h >= 1 << 63 else h


def test_whole_table_against_brute_force(spark):
    sf = "/root/testdata/sf0.01"
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()]
    split = regex.compile(r"[^\p{L}\p{N}]+")

    def terms_of(text):
        return {w for w in split.split(text.lower()) if w}

    df = Counter(w for _, t in rows for w in terms_of(t))
    lexicon = [
        {w for w, n in df.items() if fp.IDF_LOW <= math.log(len(rows) / n) <= fp.IDF_HIGH and signed(hash_of(struct.pack("<i", k), w)) % rate == 0}
        for k, rate in enumerate(fp.RATES)
    ]

    def fingerprint(text):
        found = terms_of(text)
        sets = [sorted((found & lex), key=str.encode) for lex in lexicon]
        if not any(sets):
            whole = struct.pack("<Q", hash_of(text))
            return [hash_of(struct.pack("<i", k), whole) for k in range(len(sets))]
        return [hash_of(struct.pack("<i", k), *s) for k, s in enumerate(sets)]

    def alike(a, b):
        bare = [hash_of(struct.pack("<i", k)) for k in range(len(a))]
        there = [x != z or y != z for x, y, z in zip(a, b, bare, strict=True)]
        same = [x == y != z for x, y, z in zip(a, b, bare, strict=True)]
        return sum(same) / sum(there) if any(there) else 0.0

    got = {r.doc_id: r for r in fp.op1_imatch(spark, sf).collect()}
    assert len(got) == len(rows)
    own = [fingerprint(t) for _, t in rows]
    for i, (d, t) in enumerate(rows):
        q = len(t) // 4
        following = (i + 1) % len(rows)
        edited = fingerprint(t[: len(t) - q] + rows[following][1][:q])
        assert got[d].fingerprint == "".join(f"{h:016x}" for h in own[i]), d
        assert got[d].edited_fingerprint == "".join(f"{h:016x}" for h in edited), d
        assert math.isclose(got[d].near_edited, alike(own[i], edited)) and math.isclose(got[d].near_next, alike(own[i], own[following])), d
    assert sum(r.near_edited for r in got.values()) / len(got) > 0.3


def test_far_ids_and_repeated_rows_fall_into_many_ranges(spark):
    rows = [(i, f"text {i}") for i in range(4000)] + [(1 << 60, "far")] + [(5000, f"same {i}") for i in range(2000)] + [(6000, "repeated")] * 2000
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    sizes = [r["count"] for r in fp.with_successor(df).where("tail = 0").groupBy("bucket").count().collect()]
    assert sum(sizes) == len(rows) and max(sizes) < len(rows) / 8
    got = [(r.doc_id, r.text, r.next_text) for r in fp.with_successor(df).where("tail = 0").collect()]
    by = dict((d, n) for d, _, n in got if d < 4000 or d > 7000)
    assert all(by[i] == f"text {i + 1}" for i in range(3999)) and by[1 << 60] == "text 0"
    assert Counter(n for d, _, n in got if d == 6000) == {"repeated": 1999, "far": 1}
    assert Counter(n for d, _, n in got if d == 5000 or d == 3999) == Counter([*(f"same {i}" for i in range(2000)), "repeated"])
