import pytest
from pyspark.sql import functions as F

from filekind.operators import balance, prep, splits, vocab
from filekind.plans.heavy_hitters import frequent_terms, summarize
from filekind.sources import corpus


@pytest.fixture(scope="module")
def small(spark):
    rows = [("f1", "aa", "x"), ("f2", "aa", "x"), ("f3", "aa", "y"), ("f4", "b\x00\x00", "x"), ("f5", "cc", "x"), ("f6", "dd", "y"), ("f7", "", "x"), ("f8", "ee", "rare")]
    return spark.createDataFrame(rows, "file_id string, content string, label string").withColumn("sha", F.sha1("content")).withColumn("filename", F.concat_ws(".", "file_id", "label"))


def ids(df):
    return sorted(r.file_id for r in df.collect())


def test_steps(small):
    assert ids(prep.dedup_content(small)) == ["f1", "f4", "f5", "f6", "f7", "f8"]
    assert ids(prep.keep_textual(small)) == ["f1", "f2", "f3", "f5", "f6", "f7", "f8"]
    assert ids(prep.drop_ambiguous(small)) == ["f4", "f5", "f6", "f7", "f8"]
    assert ids(prep.drop_rare(small, (2, 10))) == ["f1", "f2", "f3", "f4", "f5", "f6", "f7"]
    assert ids(prep.drop_rare(small, (1, 8), inclusive=False)) == ["f1", "f2", "f3", "f4", "f5", "f6", "f7"]
    assert ids(prep.prepare(small, prep.Config(min_freq=(2, 10)))) == ["f5", "f6", "f7"]
    assert [(r.files, r.classes) for r in prep.funnel(small, prep.Config(min_freq=(2, 10))).orderBy("step").collect()] == [(8, 3), (7, 3), (6, 2), (5, 2), (3, 2)]
    assert {r.sha[:3]: r.labels for r in prep.label_sets(small).collect() if len(r.labels) > 1}.popitem()[1] == ["x", "y"]
    assert {(r.filename, r.label) for r in prep.name_map(small).collect()} == {(f"f{i}.{c}", c) for i, c in enumerate("x x y x x y x rare".split(), 1)}


def test_preparation_does_not_depend_on_what_is_broadcast(spark, small):
    cfg = prep.Config(min_freq=(2, 10))
    assert ids(prep.prepare(small, cfg, limit=0)) == ids(prep.prepare(small, cfg)) == ["f5", "f6", "f7"]
    assert [r.files for r in prep.funnel(small.limit(0)).orderBy("step").collect()] == [0] * 5


def test_guessed_text(spark):
    df = spark.createDataFrame([(bytearray("é".encode()),), (bytearray(b"\xe9"),)], "b binary")
    assert [r[0] for r in df.select(prep.guessed_text(F.col("b"))).collect()] == ["é", "é"]


def test_class_sample_filter(spark, sf):
    kept = prep.keep_textual(corpus.injected(spark, sf), scope="class_sample", content="content_bytes", binary=True)
    assert "blob" not in {r.label for r in kept.select("label").distinct().collect()}


def test_undersampling_is_exact_and_does_not_depend_on_partitions(spark, sf, monkeypatch):
    t1 = corpus.prose(spark, sf)
    got = balance.undersample(t1)
    sizes = {r.label: r["count"] for r in got.groupBy("label").count().collect()}
    assert set(sizes.values()) == {17}
    assert ids(got) == ids(balance.undersample(t1.repartition(13)))
    assert {r["count"] for r in balance.undersample(t1, per_class=5).groupBy("label").count().collect()} == {5}
    for slices in (1, 7, 1_000_000):
        monkeypatch.setattr(balance, "SLICES", slices)
        assert ids(balance.undersample(t1)) == ids(got)


def test_oversampling(spark, sf):
    up = balance.oversample(corpus.prose(spark, sf))
    assert {r["count"] for r in up.groupBy("label").count().collect()} == {127}


def test_synthetic_vectors_keep_mass(spark):
    v = spark.createDataFrame([("a", "x", 0, 1.0), ("b", "x", 1, 1.0), ("c", "y", 2, 1.0)], "file_id string, label string, idx int, freq double")
    made = balance.synthesize(v, k=2).groupBy("file_id", "label").agg(F.sum("freq").alias("m")).collect()
    assert len(made) == 6 and all(abs(r.m - 1) < 1e-9 for r in made)


def test_splits_hold_copies_together(spark, sf):
    s = splits.assign(corpus.prose(spark, sf))
    assert s.groupBy("sha").agg(F.count_distinct("split").alias("n")).where("n > 1").count() == 0
    old, new = s.where("split = 'train'"), s
    later = splits.later_snapshot(old, new)
    assert later.join(old, "sha", "left_semi").count() == 0 and later.count() > 0
    assert splits.missing_classes(old, new.where("label = 'en'")).count() == 3


def test_vocabulary_properties(spark, sf):
    toks = vocab.tokens(corpus.prose(spark, sf)).cache()
    v = vocab.as_list(vocab.build(toks))
    assert len(v) == 30 and len(vocab.as_list(vocab.build(toks, combine="global"))) == 9
    assert len(vocab.as_list(vocab.build(toks, 2, v))) == 125 and len(vocab.as_list(vocab.build(toks, 3, v))) == 240
    assert set(vocab.as_list(vocab.build(toks, combine="global"))) | set(vocab.as_list(vocab.build(toks, combine="all"))) <= set(v)
    assert set(vocab.as_list(vocab.build(toks, tau=(2, 100)))) <= set(v) and len(v) <= 4 * 100
    assert vocab.as_list(vocab.build(toks.repartition(11))) == v
    with pytest.raises(ValueError, match="combine"):
        vocab.build(toks, combine="some")


def test_heavy_hitters_equal_full_counts(spark, sf):
    toks = vocab.tokens(corpus.prose(spark, sf))
    full = vocab.class_term_freq(toks).where("n * 100 > total")
    assert sorted(frequent_terms(vocab.terms(toks).repartition(7), (1, 100)).collect()) == sorted(full.collect())


def test_summaries_merge_in_rounds(spark, sf, monkeypatch):
    from filekind.plans import heavy_hitters

    monkeypatch.setattr(heavy_hitters, "FAN", 2)
    toks = vocab.tokens(corpus.prose(spark, sf))
    full = vocab.class_term_freq(toks).where("n * 100 > total")
    assert sorted(frequent_terms(vocab.terms(toks.repartition(9)), (1, 100)).collect()) == sorted(full.collect())


def test_summary_never_loses_a_frequent_term():
    import random

    rng = random.Random(3)
    for room in (1, 3, 9):
        stream = [rng.choice("aabbcdefghijk") for _ in range(500)]
        held: dict = {}
        for t in stream:
            summarize(held, t, 1, room)
        assert {t for t in set(stream) if stream.count(t) * (room + 1) > len(stream)} <= set(held)
