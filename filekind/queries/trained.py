"""Queries over trained networks and streams: no SQL says what they return, tests do."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import baselines, confusion, metrics, mlp, prep, score, sequence, splits, tiering, tune, vocab
from ..operators.features import vectorize
from ..store import keep, once, shared_folder
from ..streaming import scoring as streams
from . import sql
from .workloads import _measured, learned, model, predictions, raw, rounded, task, training

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
#: A net in proportion to the small corpora; larger rates than large corpora want.
SMALL = mlp.Spec(hidden=(64, 48, 32), dropout=0.2, lr=3e-3, epochs=24, batch=64)
#: What a retraining run is timed with: few epochs of the small net.
RETRAINED = mlp.Spec(hidden=SMALL.hidden, dropout=SMALL.dropout, lr=SMALL.lr, epochs=8, batch=64)
_NETS: dict = {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


def net(spark, sf: str, name: str = "T1", spec: mlp.Spec = SMALL) -> mlp.Net:
    key = (spark.sparkContext.applicationId, sf, name, spec)
    if key not in _NETS:
        space, _ = model(spark, sf, name)
        df = task(spark, sf, name)
        train = keep(vectorize(training(df).where("split = 'train'"), space, trimmed=True))
        _NETS[key] = mlp.fit(train, vectorize(df.where("split = 'val'"), space), space.size, spec)
    return _NETS[key]


def net_predictions(spark, sf: str, name: str = "T1", split: str = "test", spec: mlp.Spec = SMALL) -> DataFrame:
    space, _ = model(spark, sf, name)
    return once(spark, ("net", sf, name, split, spec), lambda: score.predict(task(spark, sf, name).where(F.col("split") == split), net(spark, sf, name, spec), space))


@query()
def train_curve(spark, sf):
    """Loss and validation accuracy by epoch (T1, T2)."""
    rows = [(t, h["epoch"], h["train_loss"], h["val_loss"], h["val_acc"]) for t in ("T1", "T2c") for h in net(spark, sf, t).history]
    return spark.createDataFrame(rows, "task string, epoch int, train_loss double, val_loss double, val_acc double")


#: The published setting: the network, its rate and its epochs.
PUBLISHED = mlp.Spec()


@query()
def train_published(spark, sf):
    """The published network on the balanced train set of T2: 1000-800-700, dropout 0.5, Adam at 1e-4, 8 epochs, with its test measures."""
    n = net(spark, sf, "T2c", PUBLISHED)
    pred = net_predictions(spark, sf, "T2c", spec=PUBLISHED)
    m = _measured(pred, "published").select("accuracy", "macro_recall", "macro_f1")
    rows = [(h["epoch"], mlp.parameters(n.weights[0].shape[0], PUBLISHED.hidden, len(n.classes)), h["train_loss"], h["val_loss"], h["val_acc"]) for h in n.history]
    return rounded(spark.createDataFrame(rows, "epoch int, parameters long, train_loss double, val_loss double, val_acc double").crossJoin(F.broadcast(m)), "accuracy", "macro_recall", "macro_f1")


@query()
def search_network(spark, sf):
    """An iterative, not exhaustive search over topology, dropout and rate on T1: every setting tried, by validation accuracy."""
    def run(hidden, dropout, lr):
        h = net(spark, sf, "T1", mlp.Spec(hidden=hidden, dropout=dropout, lr=lr, epochs=6, batch=64)).history
        return {"val_acc": max(x["val_acc"] for x in h)}

    start = {"hidden": (64, 48, 32), "dropout": 0.2, "lr": 3e-3}
    best, tried = tune.climb(run, start, {"hidden": [(64, 48, 32), (32,)], "dropout": [0.0, 0.5], "lr": [1e-3, 1e-2]}, "val_acc", rounds=1)
    rows = [("-".join(map(str, t["hidden"])), t["dropout"], t["lr"], t["val_acc"], all(t[k] == v for k, v in best.items())) for t in tried]
    return spark.createDataFrame(rows, "hidden string, dropout double, lr double, val_acc double, best boolean")


def scaled(df: DataFrame, times: int) -> DataFrame:
    """So many copies of a corpus under salted names and hashes, for runs at several sizes."""
    salt = F.explode(F.sequence(F.lit(0), F.lit(times - 1)))
    return df.withColumn("salt", salt).withColumns({"file_id": F.concat_ws("#", "file_id", "salt"), "sha": F.sha1(F.concat_ws("#", "sha", "salt"))}).drop("salt")


@query()
def cost_profile(spark, sf, sizes=(1, 10)):
    """What each step takes over T1 and over ten times T1, from preparation to scoring, and what training anew takes: wall time, rows, exchanges, bytes moved, epochs, parameters."""
    out = []
    for times in sizes:
        corpus_ = keep(scaled(raw(spark, sf, "T1"), times))
        told, prepared = tune.timed(spark, lambda: prep.levels(corpus_))
        rows = keep(splits.assign(prep.prepare(corpus_, told=told)))
        space, nb_model = learned(training(rows))

        def retrained(rows=rows, space=space):
            train = keep(vectorize(training(rows).where("split = 'train'"), space, trimmed=True))
            return train, mlp.fit(train, vectorize(rows.where("split = 'val'"), space), space.size, RETRAINED)

        (train, fitted), cost = tune.timed(spark, retrained)
        weights = mlp.parameters(space.size, RETRAINED.hidden, len(fitted.classes))
        out.append(("retrain", times, train.count(), cost["seconds"], None, cost["shuffled_bytes"], len(fitted.history), weights))
        out.append(("prepare", times, told.count(), prepared["seconds"], None, prepared["shuffled_bytes"], None, None))
        for step, df in {
            "vocabulary": vocab.build(vocab.tokens(rows.where("split = 'vocab'"), 10, 10)), "vectorize": vectorize(rows, space),
            "score_naive_bayes": score.predict(rows, nb_model, space), "score_network": score.predict(rows, fitted, space),
        }.items():
            got = tune.profile(df)
            out.append((step, times, got["rows"], got["seconds"], got["exchanges"], got["shuffled_bytes"], None, None))
    return spark.createDataFrame(out, "step string, times int, rows long, seconds double, exchanges int, shuffled_bytes long, epochs int, parameters long")


@query()
def mlp_predictions(spark, sf):
    """The network on the T1 test files."""
    return net_predictions(spark, sf).select("file_id", "label", "pred", "p")


@query()
def mlp_per_class(spark, sf):
    """Precision, recall and F of each kind by the network (T2 test files)."""
    return rounded(metrics.per_class(metrics.confusion(net_predictions(spark, sf, "T2c"))), "precision", "recall", "f1")


@query()
def mlp_averages(spark, sf):
    return rounded(metrics.averages(metrics.per_class(metrics.confusion(net_predictions(spark, sf, "T2c")))), "precision", "recall", "f1")


@query()
def mlp_groups(spark, sf):
    """Confusion groups of the network's validation predictions (T2)."""
    pred = net_predictions(spark, sf, "T2c", "val")
    return confusion.groups(confusion.t_matrix(pred), confusion.s_matrix(pred))


@query()
def logreg_predictions(spark, sf):
    """Multinomial logistic regression on the T1 test files."""
    space, _ = model(spark, sf)
    df = task(spark, sf, "T1")
    m = baselines.logreg(vectorize(training(df).where("split = 'train'"), space, trimmed=True), space.size)
    return score.predict(df.where("split = 'test'"), m, space).select("file_id", "label", "pred", "p")


@query()
def perceptron_predictions(spark, sf):
    """The library's perceptron on the T1 test files."""
    from ..operators.features import to_sparse

    space, _ = model(spark, sf)
    df = task(spark, sf, "T1")
    m, classes = baselines.perceptron(vectorize(training(df).where("split = 'train'"), space, trimmed=True), space.size)
    test = to_sparse(vectorize(df.where("split = 'test'"), space), space.size)
    return m.transform(test).select("file_id", "label", F.get(F.array(*map(F.lit, classes)), F.col("prediction").cast("int")).alias("pred"))


@query()
def hashed_linear_predictions(spark, sf):
    """Linear model over hashed tokens and their places, the stand-in for models of order."""
    df = task(spark, sf, "T1")
    return baselines.hashed_linear(training(df).where("split = 'train'"), df.where("split = 'test'"))


@query()
def convolution_predictions(spark, sf):
    """A small convolution over tokens on the T1 test files: a model of order."""
    space, _ = model(spark, sf)
    df = task(spark, sf, "T1")
    net_ = sequence.fit(training(df).where("split = 'train'"), space)
    return sequence.predict(df.where("split = 'test'"), net_, space).select("file_id", "label", "pred", "p")


@query()
def two_tier(spark, sf):
    """T2: the network alone, and with specialists for its confusion groups, routed and multiplied."""
    space, _ = model(spark, sf, "T2c")
    df = task(spark, sf, "T2c")
    val = net_predictions(spark, sf, "T2c", "val")
    groups = [r.members for r in confusion.groups(confusion.t_matrix(val), confusion.s_matrix(val), "cliques").collect()]
    vectors = vectorize(training(df).where("split = 'train'"), space, trimmed=True)
    base = net(spark, sf, "T2c")
    out = _measured(net_predictions(spark, sf, "T2c"), "one tier")
    tiers = tiering.fit(vectors, groups, base, space.size, SMALL)
    for mode in ("route", "product"):
        tiers = tiering.Tiers(base, tiers.nets, mode)
        out = out.unionByName(_measured(score.predict(df.where("split = 'test'"), tiers, space), mode))
    return rounded(out, "accuracy", "macro_recall", "macro_f1")


@query()
def baseline_models(spark, sf):
    """T1 test accuracy of every trained model and baseline."""
    from .workloads import QUERIES as W

    named = {
        "network": net_predictions(spark, sf), "naive_bayes": predictions(spark, sf), "logistic": logreg_predictions(spark, sf), "perceptron": perceptron_predictions(spark, sf),
        "hashed_linear": hashed_linear_predictions(spark, sf), "convolution": convolution_predictions(spark, sf), "centroid": W["centroid_nearest"](spark, sf),
    }
    out = None
    for n, p in named.items():
        one = rounded(_measured(p.select("file_id", "label", "pred"), n), "accuracy", "macro_recall", "macro_f1")
        out = one if out is None else out.unionByName(one)
    return out


#: Rows that one file of a feed holds at most, about.
FEED_ROWS = 1_000_000


def _feed(spark, sf: str, late: bool = False) -> tuple[str, str]:
    """Arrivals of T6 as it comes, in files of successive times (four at least); with `late`, a last file of rows far behind.

    Times are cut at approximate quantiles, so each file is filtered where the corpus is read and no task sorts it.
    """
    base = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    t6 = raw(spark, sf, "T6").select("file_id", "sha", "content", "label", F.col("arrival").cast("timestamp").alias("arrival"))
    files = max(4, -(-t6.count() // FEED_ROWS))
    at = F.unix_micros("arrival")
    cuts = sorted(set(t6.agg(F.percentile_approx(at, [k / files for k in range(1, files)], 10_000)).first()[0] or []))
    for lo, hi in zip([None, *cuts], [*cuts, None], strict=True):
        part = t6.where((at >= lo if lo is not None else F.lit(True)) & (at < hi if hi is not None else F.lit(True)))
        part.coalesce(1).write.mode("append").parquet(f"{base}/in")  # bounded by FEED_ROWS, about
    if late:
        old = t6.orderBy("file_id").limit(20).withColumn("arrival", F.expr("arrival - INTERVAL 90 DAYS")).withColumn("sha", F.concat("sha", F.lit("-late")))
        old.coalesce(1).write.mode("append").parquet(f"{base}/in")
    return base, f"{base}/in"


_ALL6 = sql.chain(f"SELECT *, file_id IN (SELECT file_id FROM ({sql.P1})) AS known FROM ({sql.T6})", learn="known", scored="true")


@query(sql.query(_ALL6, "SELECT file_id, label, pred, round(p, 6) AS p FROM p"))
def stream_scored(spark, sf):
    """The scoring stage on a stream; its result is that of the batch."""
    base, feed = _feed(spark, sf)
    space, m = model(spark, sf)
    streams.run_once(streams.score_stream(streams.arrivals(spark, feed), m, space), f"{base}/out", f"{base}/ck")
    return spark.read.parquet(f"{base}/out").select("file_id", "label", "pred", F.round("p", 6).alias("p"))


@query(f"SELECT DISTINCT sha FROM ({sql.T6})")
def stream_dedup(spark, sf):
    """Contents once each within the watermark, which is wider here than the time of all arrivals."""
    base, feed = _feed(spark, sf)
    streams.run_once(streams.without_copies(streams.arrivals(spark, feed), "60 days"), f"{base}/out", f"{base}/ck")
    return spark.read.parquet(f"{base}/out").select("sha")


@query(f"SELECT count(DISTINCT sha) AS kept, least(count(*), 20) AS late FROM ({sql.T6})")
def stream_late(spark, sf):
    """Rows kept, and rows (planted) that came too late to be kept."""
    base, feed = _feed(spark, sf, late=True)
    q = streams.run_once(streams.without_copies(streams.arrivals(spark, feed), "60 days"), f"{base}/out", f"{base}/ck")
    return spark.read.parquet(f"{base}/out").agg(F.count("*").alias("kept")).withColumn("late", F.lit(streams.late_rows(q)).cast("long"))




@query(sql.query([*_ALL6, "w AS (SELECT time_bucket(INTERVAL 6 HOUR, arrival, TIMESTAMP '1970-01-01') AS start, count(*) AS n, avg((p.label = pred)::INT) AS accuracy FROM p JOIN c USING (file_id) GROUP BY 1)"],
                 "SELECT start, n, round(accuracy, 6) AS accuracy FROM w WHERE start + INTERVAL 6 HOUR <= (SELECT max(arrival) - INTERVAL 1 HOUR FROM c)"))
def stream_accuracy(spark, sf):
    """Accuracy by six hours of arrival, as windows close."""
    base, feed = _feed(spark, sf)
    space, m = model(spark, sf)
    streams.run_once(streams.rolling_accuracy(streams.score_stream(streams.arrivals(spark, feed), m, space), delay="1 hour"), f"{base}/out", f"{base}/ck")
    return spark.read.parquet(f"{base}/out").select(F.col("start").cast("timestamp_ntz").alias("start"), "n", F.round("accuracy", 6).alias("accuracy"))


@query()
def stream_alarm(spark, sf):
    """The state of the drift detector of each class after all arrivals."""
    base, feed = _feed(spark, sf)
    space, m = model(spark, sf)
    scored = streams.score_stream(streams.arrivals(spark, feed), m, space)

    def put(df, number):
        df.withColumn("batch", F.lit(number)).write.mode("append").parquet(f"{base}/out")

    q = streams.drift_alarm(scored).writeStream.foreachBatch(put).outputMode("update").option("checkpointLocation", f"{base}/ck").trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.read.parquet(f"{base}/out").groupBy("label").agg(F.max(F.struct("n", "accuracy", "best", "alarm")).alias("s"))
    return last.select("label", "s.*")
