"""Streams of arriving files: scoring, copies, rolling accuracy and a drift alarm."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.features import Space
from ..operators.score import predict

ARRIVALS = "file_id string, sha string, content string, label string, arrival timestamp"


def arrivals(spark: SparkSession, folder: str, files_per_trigger: int = 1, schema: str = ARRIVALS) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def without_copies(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """Contents seen within the watermark go; state is bounded by the delay."""
    return stream.withWatermark("arrival", delay).dropDuplicatesWithinWatermark(["sha"])


def score_stream(stream: DataFrame, model, space: Space) -> DataFrame:
    """The batch stage on a stream: no state, no exchange."""
    return predict(stream, model, space, keep=("file_id", "sha", "label", "arrival"))


def rolling_accuracy(scored: DataFrame, span: str = "6 hours", delay: str = "1 day", slide: str | None = None) -> DataFrame:
    w = F.window("arrival", span, slide) if slide else F.window("arrival", span)
    hits = (F.col("label") == F.col("pred")).cast("double")
    return scored.withWatermark("arrival", delay).groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.avg(hits).alias("accuracy")).select(F.col("w.start").alias("start"), "n", "accuracy")


def with_late_labels(scored: DataFrame, labels: DataFrame, delay: str = "1 day", within: str = "2 days") -> DataFrame:
    """Predictions met by labels (file_id, truth, told) that come up to `within` later; both sides forget what is older."""
    p = scored.withWatermark("arrival", delay).alias("p")
    t = labels.withWatermark("told", delay).withColumnRenamed("file_id", "told_id").alias("t")
    return p.join(t, F.expr(f"file_id = told_id AND told BETWEEN arrival AND arrival + INTERVAL {within}")).drop("told_id")


def drift_alarm(scored: DataFrame, tolerance: float = 0.05, least: int = 50, decay: float = 0.98) -> DataFrame:
    """(label, n, accuracy, best, alarm) per class and batch: a decayed hit rate against the best it has been, kept as state for each class."""
    state = "n long, rate double, best double"

    def step(key, frames: Iterator[pd.DataFrame], held):
        n, rate, best = held.get if held.exists else (0, 0.0, 0.0)
        for x in frames:
            for hit in (x["label"] == x["pred"]).tolist():
                n += 1
                a = max(1 - decay, 1 / n)
                rate += a * (hit - rate)
                best = max(best, rate) if n >= least else best
        held.update((n, rate, best))
        yield pd.DataFrame({"label": [key[0]], "n": [n], "accuracy": [rate], "best": [best], "alarm": [n >= least and best - rate > tolerance]})

    return scored.select("label", "pred").groupBy("label").applyInPandasWithState(step, "label string, n long, accuracy double, best double, alarm boolean", state, "update", "NoTimeout")


def run_once(stream: DataFrame, out: str, checkpoint: str, mode: str = "append"):
    """Run a stream over what is there into Parquet; the query's progress tells rows that came too late."""
    q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def late_rows(q) -> int:
    return sum(op.numRowsDroppedByWatermark for p in q.recentProgress for op in p.stateOperators)


def swap_models(stream: DataFrame, versions, checkpoint: str, sink) -> object:
    """foreachBatch: each batch is scored by the latest model and space that `versions()` returns, then handed to sink(df, batch)."""
    def batch(df: DataFrame, number: int) -> None:
        model, space = versions()
        sink(score_stream(df, model, space), number)

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
