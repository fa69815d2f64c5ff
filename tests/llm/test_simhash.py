import random
import re

import pytest
import xxhash
from pyspark.sql import functions as F

from filekind.llm import simhash
from filekind.llm.components import components


def plain_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << i for i in range(64) if 2 * sum(h >> i & 1 for h in hashes) > len(hashes))


def plain_components(ids, fps, distance=2):
    root = list(range(len(fps)))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= distance:
                root[find(i)] = find(j)
    least = {}
    for i, d in enumerate(ids):
        least[find(i)] = min(d, least.get(find(i), d))
    return {d: least[find(i)] for i, d in enumerate(ids)}


@pytest.mark.parametrize("text", [None, "", " \t\n", "One", "one TWO", "A b C", "Ärger ÄÖ x ß y", "same same same same same", "x" * 5000 + " y z", "a\x0bb\x0cc\x1dd e f"])
def test_fingerprint(text):
    assert simhash.fingerprint(None if text is None else text.encode()) == plain_fingerprint(text)


def test_seed_equals_spark(spark):
    got = spark.sql("select xxhash64('ä b c') h").first()[0] % (1 << 64)
    assert got == xxhash.xxh64_intdigest("ä b c".encode(), 42)


def signed(x):
    return x - (1 << 64) if x >> 63 else x


@pytest.mark.parametrize("dense", [0, 3, 8, 1000])
def test_links_against_brute_force(spark, dense):
    rng = random.Random(dense)
    values = [rng.getrandbits(64) for _ in range(150)]
    for _ in range(150):
        v = rng.choice(values)
        for b in rng.sample(range(64), rng.choice([1, 2, 2, 3, 4])):
            v ^= 1 << b
        values.append(v)
    values = sorted(set(values) | {0, 1, 3, 1 << 63})
    fps = spark.createDataFrame([(signed(v),) for v in values], "fp long")
    roots = {r.node: r.root for r in components(simhash.links(fps, dense=dense), "a", "b").collect()}
    want = plain_components(list(map(signed, values)), values)
    assert {signed(v): roots.get(signed(v), signed(v)) for v in values} == want


def test_whole_tables(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in simhash.op7_simhash_bytes(spark, sf).collect()}
    rows = docs.select("doc_id", "text").collect()
    fps = [plain_fingerprint(r.text) for r in rows]
    want = plain_components([r.doc_id for r in rows], fps)
    assert len(got) == len(rows)
    for r, f in zip(rows, fps, strict=True):
        assert got[r.doc_id].fingerprint == f"{f:016x}" and got[r.doc_id].component_id == want[r.doc_id]


def test_very_long_texts(spark):
    rng = random.Random(9)
    words = [f"w{rng.randint(0, 400)}" for _ in range(200_000)]
    other = [*words[:100_000], "changed", *words[100_001:]]
    texts = [" ".join(words), " ".join(other), "  ".join(words), "x" * 1_000_000, " ".join(words[:50_000])]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in simhash.near_duplicates(df).collect()}
    fps = list(map(plain_fingerprint, texts[:2])) + [simhash.fingerprint(t.encode()) for t in texts[2:]]
    want = plain_components(list(range(5)), fps)
    assert all(got[i].fingerprint == f"{f:016x}" and got[i].component_id == want[i] for i, f in enumerate(fps))
    assert got[0].component_id == got[1].component_id == got[2].component_id == 0 and got[3].component_id == 3


def test_edges(spark):
    rows = [(1, None), (2, ""), (3, " \n"), (4, "a b c d"), (4, "a b c d"), (None, "A B C D"), (5, "other words are here now")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("fp", F.lit("clash"))
    got = sorted(((r.doc_id, r.component_id) for r in simhash.near_duplicates(df).collect()), key=str)
    assert got == sorted([(1, 1), (2, 1), (3, 1), (4, 4), (4, 4), (None, 4), (5, 5)], key=str)
    assert simhash.near_duplicates(df.limit(0)).count() == 0
