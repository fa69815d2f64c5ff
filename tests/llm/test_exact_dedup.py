import hashlib
import random
import re
from collections import Counter

import pytest

from filekind.llm import exact_dedup


def plain(rows):
    norm = [re.sub(r"[\x20\x09-\x0d]+", " ", t or "") for _, t in rows]
    size, least = Counter(norm), {}
    for (d, _), n in zip(rows, norm):
        if d is not None:
            least[n] = min(d, least.get(n, d))
    return Counter((d, least.get(n), size[n], hashlib.sha256(n.encode()).hexdigest()) for (d, _), n in zip(rows, norm))


def got(df, **how):
    rows = exact_dedup.dedup(df, **how).collect()
    kept = Counter(r.text_sha256 for r in rows if r.kept)
    assert set(kept.values()) <= {1} and set(kept) == {r.text_sha256 for r in rows}
    assert all(r.doc_id == r.keep_id for r in rows if r.kept)
    return Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in rows)


@pytest.mark.parametrize("how", [{}, {"least": 8, "most": 64}, {"hash_bits": 4}, {"least": 4, "most": 16, "hash_bits": 6}])
def test_whole_table(spark, sf, how):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert got(docs, **how) == plain([(r.doc_id, r.text) for r in docs.collect()])


@pytest.mark.parametrize("how", [{}, {"least": 2, "most": 5, "hash_bits": 1}])
def test_edges(spark, how):
    rows = [(1, None), (2, ""), (3, " "), (4, "\t\n"), (5, "a b"), (5, "a  b"), (5, "a b"), (6, "a\x0b\x0cb"), (7, "a\u00a0b"), (8, "x" * 20_000), (9, "x" * 20_000), (10, "x" * 20_001), (None, "lone"), (11, "a b ")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'c' recipe", "1 h", "2 copies")
    assert got(df, **how) == plain(rows)
    assert exact_dedup.dedup(df.limit(0), **how).count() == 0


def test_chunks_join_to_the_text_and_follow_content(spark):
    rng = random.Random(4)
    text = " ".join("".join(rng.choices("abcdefghijklmnopqrst", k=rng.randint(2, 8))) for _ in range(6000))
    df = spark.createDataFrame([(1, text), (2, "Some other start. " + text)], "id long, t string")
    a, b = (r.p for r in df.select(exact_dedup.chunks(df.t).alias("p")).collect())
    assert "".join(a) == text and "".join(b) == "Some other start. " + text
    assert len(set(a) & set(b)) > 0.7 * len(a) and all(len(x) <= exact_dedup.MOST for x in a)
