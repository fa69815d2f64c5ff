import re
from collections import defaultdict

import corpus_pipeline as cp
import pyarrow as pa
import pytest
from filekind.llm import common, packing, simhash, toxicity
from pyspark.sql import functions as F

from tests.llm.test_simhash import plain_components, plain_fingerprint


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def test_stages_against_plain_versions(spark, docs):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    clean = cp.drop_toxic(spark, docs, sf).cache()
    scores = {r.doc_id: r.predicted for r in toxicity.op5_nearest_examples(spark, sf).collect()}
    assert {r.doc_id for r in clean.collect()} == {d for d, p in scores.items() if not p} and sum(scores.values()) > 20
    assert clean.columns == docs.columns

    once = cp.drop_copies(spark, clean, sf).cache()
    least = {}
    for r in clean.collect():
        t = re.sub(r"[\x20\x09-\x0d]+", " ", r.text)
        least[t] = min(r.doc_id, least.get(t, r.doc_id))
    assert sorted(r.doc_id for r in once.collect()) == sorted(least.values()) and once.columns == docs.columns

    apart = cp.drop_near_copies(spark, once, sf).cache()
    rows = once.collect()
    group = plain_components([r.doc_id for r in rows], [plain_fingerprint(r.text) for r in rows])
    assert sorted(r.doc_id for r in apart.collect()) == sorted(set(group.values())) and apart.columns == docs.columns

    mixed = cp.mix_sources(spark, apart, sf).cache()
    tokens = {r.doc_id: len(r.text.split()) for r in apart.collect()}
    kept = [r.doc_id for r in mixed.collect()]
    assert len(kept) == len(set(kept)) and set(kept) <= set(tokens) and mixed.columns == docs.columns
    assert 0.59 < sum(tokens[d] for d in kept) / sum(tokens.values()) < 0.75

    packed = cp.pack_sequences(spark, mixed, sf).collect()
    held = defaultdict(int)
    for r in packed:
        held[r.doc_id] += r.length
    assert dict(held) == {d: tokens[d] for d in kept}
    assert sum(held.values()) / sum({r.bin: r.bin_length for r in packed}.values()) > 0.9


def test_edges(spark, sf):
    rows = [(1, None, None, None, None), (2, "", "en", "src1", 0), (3, "a  b c d", "en", "src1", 8), (4, "a b c d", "en", "src1", 7), (4, "a b c d", "en", "src1", 7), (None, "other words entirely here", "de", "x", 1), (None, "other words entirely here", "de", "x", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").selectExpr("*", "1 score", "'f' fp")
    once = cp.drop_copies(spark, df, sf)
    assert sorted((r.doc_id or 0 for r in once.collect())) == [0, 1, 3] and once.columns == df.columns
    assert sorted((r.doc_id or 0 for r in cp.drop_near_copies(spark, df, sf).collect())) == [0, 1, 3]
    for _, stage in cp.STAGES:
        assert stage(spark, df.limit(0), sf).count() == 0
    assert cp.drop_toxic(spark, df, sf).count() == len(rows)


def test_very_long_texts(spark, sf):
    words = [f"w{i % 7919}" for i in range(150_000)]
    texts = [" ".join(words), "  ".join(words), " ".join([*words[:75_000], "other", *words[75_001:]]), "y" * 1_000_000, "short text of a few words"]
    df = spark.createDataFrame([(i, t, "en", "src1", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    clean = cp.drop_toxic(spark, df, sf)
    assert sorted(r.doc_id for r in clean.select("doc_id").collect()) == [0, 1, 2, 3, 4]
    once = cp.drop_copies(spark, clean, sf)
    assert sorted(r.doc_id for r in once.select("doc_id").collect()) == [0, 2, 3, 4]
    apart = dict(cp.STAGES)["near_dedup"](spark, once, sf)
    assert sorted((r.doc_id, r.text) for r in apart.collect()) == [(0, texts[0]), (3, texts[3]), (4, texts[4])]
    packed = cp.pack_sequences(spark, apart, sf).collect()
    assert sum(r.length for r in packed if r.doc_id == 0) == 150_000 and [r.length for r in packed if r.doc_id == 3] == [1]
    assert cp.mix_sources(spark, apart, sf).count() >= 1


def test_run(spark, sf):
    got = cp.run(spark, sf)
    assert set(packing.COLUMNS) == set(got.columns) and got.count() > 50 and simhash.DISTANCE == 2


@pytest.mark.parametrize("stage", [cp.drop_toxic, cp.drop_similar])
def test_texts_reach_python_in_small_batches(spark, docs, sf, stage):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], ["rows", "bytes"])

    def largest(length):
        text = spark.range(3000, numPartitions=1).select(F.repeat(F.lit("x"), length).alias("text"))
        return text.mapInArrow(sizes, "rows long, bytes long").agg(F.max("rows"), F.max("bytes"), F.sum("rows")).first()

    try:
        for name in common.BATCH:
            spark.conf.unset(name)
        assert stage(spark, docs, sf).count()
        assert largest(9)[0] <= 1024 and largest(9)[2] == 3000
        assert largest(9000)[1] <= (4 << 20) + 10_000
        # A session's smaller bounds stay.
        for name, few in zip(common.BATCH, ("100", "1m"), strict=True):
            spark.conf.set(name, few)
        common.small_batches(spark)
        assert largest(9)[0] == 100 and largest(90_000)[1] <= (1 << 20) + 100_000
    finally:
        for name in common.BATCH:
            spark.conf.unset(name)
