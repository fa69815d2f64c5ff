"""Accuracy measures out of predictions (label, pred)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def confusion(pred: DataFrame, classes: DataFrame | None = None) -> DataFrame:
    """(i, j, n). With a table of classes (label), cells without files are there with 0."""
    n = pred.groupBy(F.col("label").alias("i"), F.col("pred").alias("j")).agg(F.count("*").alias("n"))
    if classes is None:
        return n
    c = classes.select("label").distinct()
    grid = c.select(F.col("label").alias("i")).crossJoin(F.broadcast(c.select(F.col("label").alias("j"))))  # the square of the classes
    return grid.join(n, ["i", "j"], "left").select("i", "j", F.coalesce("n", F.lit(0)).alias("n"))


def per_class(cells: DataFrame, universe: str = "model") -> DataFrame:
    """(label, support, tp, fp, fn, precision, recall, f1). A measure with nothing to divide by is null; F is then 0 if the class occurs.

    universe `model`: all classes that occur or are predicted; `observed`: only cells between classes that occur count.
    """
    if universe == "observed":
        there = cells.where("n > 0").select("i").distinct()
        cells = cells.join(F.broadcast(there.withColumnRenamed("i", "j")), "j", "left_semi")
    elif universe != "model":
        raise ValueError(f"universe {universe!r}: model or observed")
    hit = F.when(F.col("i") == F.col("j"), F.col("n")).otherwise(F.lit(0))
    zero = F.lit(0).cast("long")
    by_truth = cells.select(F.col("i").alias("label"), F.col("n").alias("support"), hit.alias("tp"), zero.alias("predicted"))
    by_guess = cells.select(F.col("j").alias("label"), zero.alias("support"), zero.alias("tp"), F.col("n").alias("predicted"))
    s = by_truth.unionByName(by_guess).groupBy("label").agg(*(F.sum(c).cast("long").alias(c) for c in ("support", "tp", "predicted"))).where("support > 0 or predicted > 0")
    both = F.col("support") + F.col("predicted")
    return s.select(
        "label", "support", "tp", (F.col("predicted") - F.col("tp")).alias("fp"), (F.col("support") - F.col("tp")).alias("fn"),
        F.try_divide("tp", "predicted").alias("precision"), F.try_divide("tp", "support").alias("recall"), F.try_divide(2 * F.col("tp"), both).alias("f1"),
    )


def micro(m: DataFrame) -> DataFrame:
    tp, fp, fn = F.sum("tp"), F.sum("fp"), F.sum("fn")
    return m.agg(F.try_divide(tp, tp + fp).alias("precision"), F.try_divide(tp, tp + fn).alias("recall"), F.try_divide(2 * tp, 2 * tp + fp + fn).alias("f1")).select(F.lit("micro").alias("kind"), "*")


def macro(m: DataFrame, null_is_zero: bool = True) -> DataFrame:
    """Unweighted means over the classes that occur; F is the mean of the classes' F."""
    def mean(c: str):
        return F.avg(F.coalesce(F.col(c), F.lit(0.0)) if null_is_zero else F.col(c)).alias(c)

    m = m.where("support > 0") if "support" in m.columns else m
    return m.agg(*map(mean, ("precision", "recall", "f1"))).select(F.lit("macro").alias("kind"), "*")


def weighted(m: DataFrame) -> DataFrame:
    """Means over classes weighted by their files."""
    return m.agg(*(F.try_divide(F.sum(F.coalesce(F.col(c), F.lit(0.0)) * F.col("support")), F.sum("support")).alias(c) for c in ("precision", "recall", "f1"))).select(F.lit("weighted").alias("kind"), "*")


def averages(m: DataFrame) -> DataFrame:
    return micro(m).unionByName(macro(m)).unionByName(weighted(m))


def accuracy(pred: DataFrame) -> DataFrame:
    """(files, accuracy, class_accuracy): over files, and as the mean over classes."""
    by = pred.groupBy("label").agg(F.count("*").alias("n"), F.sum((F.col("label") == F.col("pred")).cast("long")).alias("hits"))
    return by.agg(F.sum("n").alias("files"), F.try_divide(F.sum("hits"), F.sum("n")).alias("accuracy"), F.avg(F.col("hits") / F.col("n")).alias("class_accuracy"))


def calibration(pred: DataFrame, bins: int = 10) -> DataFrame:
    """(bin, n, mean_p, accuracy) over equal steps of the top probability."""
    b = F.least(F.floor(F.col("p") * bins), F.lit(bins - 1)).cast("int")
    return pred.groupBy(b.alias("bin")).agg(F.count("*").alias("n"), F.avg("p").alias("mean_p"), F.avg((F.col("label") == F.col("pred")).cast("double")).alias("accuracy"))
