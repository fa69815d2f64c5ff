import itertools
import zlib
from collections import Counter

import pytest
from pyspark.sql import functions as F

from filekind.llm import sharding


@pytest.mark.parametrize(("dims", "bits"), [(1, 3), (2, 3), (3, 3), (4, 2)])
def test_curve_visits_neighbours(spark, dims, bits):
    cells = list(itertools.product(range(1 << bits), repeat=dims))
    names = [f"c{i}" for i in range(dims)]
    df = spark.createDataFrame(cells, ", ".join(f"{n} int" for n in names)).withColumn("i", sharding.curve_index([F.col(n) for n in names], bits))
    path = [r[:dims] for r in df.orderBy("i").collect()]
    assert sorted(r.i for r in df.collect()) == list(range(len(cells)))
    assert all(sum(abs(a - b) for a, b in zip(x, y)) == 1 for x, y in itertools.pairwise(path))


def check(got, texts, shards, law):
    assert Counter(r.doc_id for r in got) == Counter(d for d, _ in texts)
    want = Counter((d, len((t or "").encode()) + 8, zlib.crc32((t or "").encode())) for d, t in texts)
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == want
    by = {s: sorted((r.slot, r.curve) for r in got if r.shard == s) for s in range(shards)}
    assert all([x for x, _ in v] == list(range(len(v))) for v in by.values())
    run = [c for s in range(shards) for _, c in by[s]]
    assert run == sorted(run)
    counts = [len(v) for v in by.values()]
    if law == "rows":
        assert max(counts) - min(counts) <= 1
    else:
        sizes = [sum(r.size for r in got if r.shard == s) for s in range(shards)]
        assert max(sizes) - min(sizes) <= 2 * max((r.size for r in got), default=0)


@pytest.mark.parametrize("law", ["rows", "bytes"])
def test_laws_on_the_table(spark, sf, law):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = [(r.doc_id, r.text) for r in docs.collect()]
    check(sharding.hilbert_shards(docs, law=law).collect(), texts, 24, law)


@pytest.mark.parametrize("law", ["rows", "bytes"])
def test_edges(spark, law):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (2, "", "en", "a", 0), (None, "é", "x", None, -5), (5, "z" * 50_000, "de", "b", 50_000)] + [(i, "hot", "en", "a", 3) for i in range(10, 60)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").selectExpr("*", "'c' shard", "'d' rank", "3 slice")
    check(sharding.hilbert_shards(df, shards=5, law=law).collect(), [(r[0], r[1]) for r in rows], 5, law)
    assert sharding.hilbert_shards(df.limit(0), law=law).count() == 0


def test_files_and_manifest(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    docs = docs.union(docs.limit(3).withColumn("doc_id", F.lit(None).cast("long"))).union(docs.limit(2))
    got = sharding.write_shards(docs, str(tmp_path / "out"), rows_per_file=3)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert Counter(map(tuple, back.drop("__shard").collect())) == Counter(map(tuple, docs.collect()))
    held = {r.shard: r for r in got.collect()}
    for r in back.collect():
        m = held[r["__shard"]]
        assert m.min_source <= r.source <= m.max_source and m.min_n_chars <= r.n_chars <= m.max_n_chars and m.min_lang <= r.lang <= m.max_lang
    assert sum(m.n for m in held.values()) == docs.count()
    spans = got.agg(F.avg(F.col("max_n_chars") - F.col("min_n_chars"))).first()[0]
    assert spans < docs.agg(F.max("n_chars") - F.min("n_chars")).first()[0]


def test_categories_keep_their_order(spark):
    few = spark.createDataFrame([(f"s{i:02}",) for i in range(20)] + [(None,)], "source string")
    got = {r.source: r.c for r in few.withColumn("c", sharding.coordinate(few, "source", "category", 5)).collect()}
    assert got == {None: 0, **{f"s{i:02}": i + 1 for i in range(20)}}
    many = spark.range(5000).selectExpr("concat('s', lpad(id, 5, '0')) source")
    rows = many.withColumn("c", sharding.coordinate(many, "source", "category", 3)).orderBy("source").collect()
    assert [r.c for r in rows] == sorted(r.c for r in rows) and len({r.c for r in rows}) == 7


def test_cuts_of_many_categories_are_exact(spark):
    """The values that hold the ranks at which cells begin, among all rows; a sample finds others."""
    rows = [f"v{i % 997:03}" for i in range(30_000)] + ["v500"] * 9_000 + [f"w{i}" for i in range(6_000)] + ["é", "\U0001f600", ""]
    df = spark.createDataFrame([(v,) for v in rows] + [(None,)] * 50, "source string")
    want = {b"", *(sorted(v.encode() for v in rows)[len(rows) * i // 31] for i in range(1, 31))}
    for parts in (1, 13):
        assert {v.encode() for v in sharding.category_starts(df.repartition(parts), "source", 5)} == want


@pytest.mark.parametrize("rows", [100_000_000, 10**12])
def test_places_of_very_many_rows(spark, rows):
    """The whole-number laws of shard and slot at the edges of shards, far beyond 32 bits."""
    at = spark.createDataFrame([(r,) for r in (0, rows // 24 - 1, rows // 24, rows // 24 + 1, rows // 2, rows - 1)], "rank long")
    got = at.selectExpr("rank", f"cast(rank * 24L div {rows}L as int) shard").selectExpr("rank", "shard", f"rank - (shard * {rows}L + 23L) div 24L slot").collect()
    for r in got:
        assert r.shard == r.rank * 24 // rows and r.slot == r.rank - -(-r.shard * rows // 24) >= 0
