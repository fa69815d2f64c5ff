import random

import corpus_pipeline as cp
import pytest
from filekind.llm import similar
from pyspark.sql import functions as F


def plain_groups(rows):
    """{row number: group} by brute-force Jaccard of at least 0.8 over five-word shingles; the group is its smallest id."""
    sets = []
    for _, text in rows:
        w = (text or "").lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set()))
    by = {}
    for i, s in enumerate(sets):
        for x in s:
            by.setdefault(x, []).append(i)
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, s in enumerate(sets):
        near = {j for x in s for j in by[x] if j < i} if s else {j for j in range(i) if not sets[j]}
        for j in near:
            if 5 * len(s & sets[j]) >= 4 * len(s | sets[j]):
                root[find(i)] = find(j)
    return [find(i) for i in range(len(rows))]


def kept(rows):
    least = {}
    for (d, _), g in zip(rows, plain_groups(rows), strict=True):
        least[g] = min(d, least.get(g, d))
    return sorted(least.values())


def test_stage_against_brute_force(spark):
    sf = "/root/testdata/sf0.01"
    once = cp.drop_copies(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf).cache()
    rows = [(r.doc_id, r.text) for r in once.collect()]
    want = kept(rows)
    got = dict(cp.STAGES)["near_dedup"](spark, once, sf)
    assert sorted(r.doc_id for r in got.collect()) == want and len(want) < len(rows) and got.columns == once.columns


@pytest.mark.parametrize("sample", [1, 2, 50])
def test_groups_at_the_bound(spark, sample):
    rng = random.Random(sample)
    texts = ["x y", "X  y", "x", "", None, " ", "a b c d e", "A b c d e f", "a b c d e f g h i", "a b c d e f g h i j"]  # 4 of 5 and 5 of 6 shared
    line = [f"licence{i}" for i in range(20)]
    for size in (12, 40, 200):
        for _ in range(8):
            words = [rng.choice("abcdefghij") + str(rng.randrange(400)) for _ in range(size)] + line
            for _ in range(6):
                texts.append(" ".join(words))
                words = list(words)
                for _ in range(rng.randint(0, max(1, size // 25))):
                    words[rng.randrange(len(words))] = f"new{rng.randrange(10**6)}"
    rows = list(enumerate(texts))
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.root for r in similar.grouped(df, sample=sample).collect()}
    want = plain_groups(rows)
    pairs = lambda g: {frozenset(m) for m in g.values()}
    a, b = {}, {}
    for (d, _), g in zip(rows, want, strict=True):
        a.setdefault(g, set()).add(d)
        b.setdefault(got[d], set()).add(d)
    assert pairs(a) == pairs(b) and 5 < len(a) < len(rows)


def test_edges(spark):
    rows = [(1, None), (2, ""), (3, " \n"), (4, "a b c d"), (4, "a b c d"), (None, "A B C D"), (5, "other words are here now")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("entry", F.lit("clash"))
    assert sorted(r.doc_id for r in similar.keep_one(df).collect()) == [1, 4, 5]
    assert similar.keep_one(df.limit(0)).count() == 0


@pytest.mark.parametrize("crowded", [similar.CROWDED, 0])
def test_pairs_of_a_large_group_stay_few(spark, monkeypatch, crowded):
    """A group in which hardly two texts are alike but to one: not all its pairs are tried."""
    rng, n = random.Random(7), 240
    base = [f"w{i}" for i in range(150)]
    texts = []
    for i in range(n):
        words = list(base)
        for j in range(3 if i != 100 else 0):
            words[rng.randrange(len(words))] = f"own{i}x{j}"
        texts.append(" ".join(words))
    rows = list(enumerate([*texts, *(" ".join([*base[:60], *(f"far{i}x{j}" for j in range(30))]) for i in range(20))]))
    most, write = [], similar.stash

    def counted(df):
        out = write(df)
        if out.columns == ["a", "b"]:
            most.append(out.count())
        return out

    monkeypatch.setattr(similar, "stash", counted)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    found = {}
    for r in similar.grouped(df, crowded=crowded).collect():
        found.setdefault(r.root, set()).add(r.doc_id)
    want = {}
    for (d, _), g in zip(rows, plain_groups(rows), strict=True):
        want.setdefault(g, set()).add(d)
    assert sorted(map(sorted, found.values())) == sorted(map(sorted, want.values())) and max(map(len, found.values())) > n / 2
    assert max(most) <= 4 * len(rows)
