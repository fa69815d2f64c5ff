"""Ageing: the same measures on an old and a newer test set, and over time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def compare(old: DataFrame, new: DataFrame) -> DataFrame:
    """Class measures side by side: status (both, vanished, new) and deltas."""
    names = ("support", "precision", "recall", "f1")
    a = old.select("label", *(F.col(c).alias(f"{c}_old") for c in names))
    b = new.select("label", *(F.col(c).alias(f"{c}_new") for c in names))
    status = F.when(F.coalesce("support_new", F.lit(0)) == 0, "vanished").when(F.coalesce("support_old", F.lit(0)) == 0, "new").otherwise("both")
    deltas = [(F.col(f"{c}_new") - F.col(f"{c}_old")).alias(f"{c}_delta") for c in names[1:]]
    return a.join(b, "label", "full_outer").select("label", status.alias("status"), *(f"{c}_{x}" for c in names for x in ("old", "new")), *deltas)


def windows(pred: DataFrame, span: str = "6 hours") -> DataFrame:
    """(start, n, accuracy) by arrival."""
    return pred.groupBy(F.window("arrival", span).alias("w")).agg(F.count("*").alias("n"), F.avg((F.col("label") == F.col("pred")).cast("double")).alias("accuracy")).select(F.col("w.start").alias("start"), "n", "accuracy")


def schedule(pred: DataFrame, span: str = "6 hours", tolerance: float = 0.05) -> DataFrame:
    """(start, n, accuracy, delta, alarm): time buckets, and where accuracy fell by more than the tolerance below the best so far."""
    by = Window.orderBy("start")  # as many rows as time buckets
    w = windows(pred, span)
    best = F.max("accuracy").over(by.rowsBetween(Window.unboundedPreceding, -1))
    return w.select("*", (F.col("accuracy") - F.lag("accuracy").over(by)).alias("delta"), F.coalesce(F.round(best - F.col("accuracy"), 12) > tolerance, F.lit(False)).alias("alarm"))
