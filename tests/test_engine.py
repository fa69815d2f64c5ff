"""Whole queries: against SQL, on streams, in plans, and without the training-data operators."""

import subprocess
import sys

import duckdb
import pytest
from pyspark.sql import functions as F

from filekind import sqlapi
from filekind.ml import FileKindEstimator, FileKindModel
from filekind.operators import prep, score, vocab
from filekind.queries import operators, trained, workloads
from filekind.sources import corpus, tables

CHECKED = {**workloads.ORACLES, **operators.ORACLES}
ALL = {**workloads.QUERIES, **operators.QUERIES, **trained.QUERIES}
TABLES = list(tables.SCHEMAS)


def plain(v):
    if isinstance(v, float):
        return round(v, 6) + 0.0
    return tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    c.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(CHECKED))
def test_query_equals_sql(spark, sf, con, name):
    df = ALL[name](spark, sf)
    got = sorted((tuple(plain(r[c]) for c in sorted(df.columns)) for r in df.collect()), key=repr)
    out = con.execute(CHECKED[name])
    names = [d[0] for d in out.description]
    assert sorted(names) == sorted(df.columns)
    want = sorted((tuple(plain(r[names.index(c)]) for c in sorted(names)) for r in out.fetchall()), key=repr)
    assert got == want


def test_forward_check_reads_every_event(spark, sf):
    got = workloads.forward_check(spark, sf)
    events = tables.load(spark, sf, "events").count()
    assert got.count() == events and got.select("event_id").distinct().count() == events
    assert any(f.endswith("events.parquet") for f in got.inputFiles()) and got.where("abs(c0 + c1 + c2 - 1) > 2e-6").isEmpty()


def test_cost_profile_prepares_each_size_once(spark, sf, monkeypatch):
    asked, levels = [], prep.levels
    monkeypatch.setattr(prep, "levels", lambda df, *a: asked.append(1) or levels(df, *a))
    rows = {(r.step, r.times): r for r in trained.cost_profile(spark, sf, sizes=(1, 2)).collect()}
    assert len(asked) == 2 and len(rows) == 12
    assert rows["prepare", 2].rows == 2 * rows["prepare", 1].rows == 2 * corpus.prose(spark, sf).count()
    assert all(r.rows > 0 and r.seconds > 0 for r in rows.values()) and rows["retrain", 1].epochs > 0


def test_streams_equal_batches(spark, sf):
    space, model = workloads.model(spark, sf)
    batch = {(r.file_id, r.pred) for r in score.predict(corpus.prose(spark, sf), model, space).collect()}
    assert {(r.file_id, r.pred) for r in trained.stream_scored(spark, sf).collect()} == batch
    assert trained.stream_dedup(spark, sf).count() == corpus.prose(spark, sf).select("sha").distinct().count()
    late = trained.stream_late(spark, sf).first()
    assert late.late == 20 and late.kept == corpus.prose(spark, sf).select("sha").distinct().count()
    assert trained.stream_alarm(spark, sf).agg(F.sum("n")).first()[0] == corpus.prose(spark, sf).count()


def test_trained_models_beat_the_prior(spark, sf):
    rows = {r.variant: r for r in trained.baseline_models(spark, sf).collect()}
    assert rows["logistic"].macro_recall > 0.5 and rows["naive_bayes"].macro_recall > 0.5


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf):
    docs = tables.load(spark, sf, "documents").select(F.col("doc_id").cast("string").alias("file_id"), F.sha1("source").alias("sha"), F.col("lang").alias("label"))
    freq = plan(prep.class_frequency(docs))
    assert "ReadSchema: struct<lang:string>" in freq
    toks = vocab.tokens(corpus.prose(spark, sf))
    assert "Python" not in plan(vocab.class_term_freq(toks, 2, ["the"])) and "Arrow" not in plan(prep.prepare(corpus.prose(spark, sf)))
    space, model = workloads.model(spark, sf)
    scored = plan(score.predict(corpus.prose(spark, sf), model, space))
    assert "MapInArrow" in scored and "Exchange" not in scored


def test_sql_surface(spark, sf):
    space, model = workloads.model(spark, sf)
    sqlapi.register(spark, model, space)
    assert spark.sql("select fk_tokens('a=b é')").first()[0] == ["a", "=", "b", "\x1a"]
    assert spark.sql("select fk_ngrams(array('a', 'b', 'c'), 2), fk_ngrams(array('a'), 2)").first()[:] == (["a b", "b c"], [])
    corpus.prose(spark, sf).createOrReplaceTempView("fk_t1")
    got = {r.file_id: r.p for r in spark.sql("select file_id, fk_predict(fk_tokens(content)) p from fk_t1").collect()}
    assert got == {r.file_id: r.pred for r in score.predict(corpus.prose(spark, sf), model, space).collect()}


@pytest.mark.parametrize("network", [(), (12,)])
def test_pipeline_stage(spark, sf, tmp_path, network):
    df = corpus.prose(spark, sf).select("content", "label")
    model = FileKindEstimator(network=network, epochs=6, predictionCol="kind").fit(df)
    out = model.transform(df)
    assert {"content", "label", "kind", "p", "top"} == set(out.columns) and out.count() == df.count()
    model.save(str(tmp_path / "m"))
    back = FileKindModel.load(str(tmp_path / "m"))
    assert sorted(r.kind for r in back.transform(df).collect()) == sorted(r.kind for r in out.collect())


def test_sources_and_sinks(spark, tmp_path):
    (tmp_path / "in").mkdir()
    for name, data in {"a.py": b"x = 1", "b.txt": "é".encode(), "c.bin": b"\xff\xfe", "noext": b"q"}.items():
        (tmp_path / "in" / name).write_bytes(data)
    rows = {r.filename: r for r in tables.files(spark, str(tmp_path / "in")).collect()}
    assert rows["a.py"].label == "py" and rows["b.txt"].content == "é" and rows["c.bin"].content == "\xff\xfe" and rows["noext"].label is None
    assert tables.texts(spark, str(tmp_path / "in" / "a.py")).first().content == "x = 1"
    df = tables.files(spark, str(tmp_path / "in")).withColumn("split", F.lit("train"))
    tables.save_corpus(df, str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).where("split = 'train'").count() == 4
    tables.save_report(df.select("filename"), str(tmp_path / "rep"), "csv")
    assert tables.read(spark, str(tmp_path / "rep"), "csv", "filename string", header=True).count() == 4
    with pytest.raises(ValueError, match="one of"):
        tables.read(spark, "x", "avro", "a int")


def test_imports_without_the_training_data_operators():
    """As when the folders of the training-data operators are gone."""
    code = """
import importlib.util, sys
real = importlib.util.find_spec
importlib.util.find_spec = lambda name, *a: None if name.startswith("filekind.llm") else real(name, *a)
import __spark_entry__ as e
assert e.queries() and not [n for n in e.queries() if n.startswith("op") and n[2].isdigit()] and "pipeline" not in e.queries()
assert not [m for m in sys.modules if m.startswith("filekind.llm")]
"""
    subprocess.run([sys.executable, "-c", code], check=True, timeout=120, cwd=str(__import__("pathlib").Path(__file__).parent.parent))
