"""Preparation of a labelled corpus: copies, rare classes, binary content and ambiguous labels."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import bucket, extension, nonprintable_ratio
from ..store import BROADCAST_BYTES, keep, measured, offered


def dedup_content(df: DataFrame, key: str = "sha") -> DataFrame:
    """One row for each content, that of the smallest file id. Only hashes and ids move: the files that go are found in them, and contents are filtered where they are read."""
    held = df.select(key, "file_id")
    first = held.groupBy(key).agg(F.min("file_id").alias("first"))
    surplus = keep(held.join(first, key).where("file_id <> first").select("file_id"))
    return df.join(offered(surplus), "file_id", "left_anti")


def name_map(df: DataFrame) -> DataFrame:
    """(sha, filename, label): every name under which a content is known, and the suffix it ends in."""
    return df.select("sha", "filename").distinct().withColumn("label", extension(F.col("filename")))


def class_frequency(df: DataFrame, by: str = "files") -> DataFrame:
    """(label, n, share). by: `files` counts rows, `pairs` counts different (content, label) pairs."""
    rows = df.select("sha", "label").distinct() if by == "pairs" else df
    counted = rows.groupBy("label").agg(F.count("*").alias("n"))
    return counted.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy()))  # as many rows as classes


def frequent_classes(df: DataFrame, min_freq: tuple[int, int] = (1, 10_000), inclusive: bool = True) -> DataFrame:
    """Classes whose share is not below the fraction; compared in whole numbers."""
    num, den = min_freq
    n = class_frequency(df).withColumn("all", F.sum("n").over(Window.partitionBy()))
    test = F.col("n") * den >= F.col("all") * num if inclusive else F.col("n") * den > F.col("all") * num
    return n.where(test).select("label")


def drop_rare(df: DataFrame, min_freq: tuple[int, int] = (1, 10_000), inclusive: bool = True) -> DataFrame:
    return df.join(frequent_classes(df, min_freq, inclusive), "label", "left_semi")


def keep_textual(df: DataFrame, max_ratio: float = 0.2, scope: str = "file", content: str = "content", unit: str = "codepoint", binary: bool = False, sample: int = 100, seed: int = 42) -> DataFrame:
    """Without binary content. scope `file` tests each file; `class_sample` tests a seeded sample of each class, one file in `100 / sample`
    of every hundred, and drops classes whose mean is over the limit."""
    ratio = F.coalesce(nonprintable_ratio(F.col(content), unit, binary), F.lit(0.0))
    if scope == "file":
        return df.where(ratio <= max_ratio)
    if scope != "class_sample":
        raise ValueError(f"scope {scope!r}: file or class_sample")
    drawn = df.where(bucket(F.col("file_id"), f"binary{seed}", 100) < sample)
    binary_classes = drawn.groupBy("label").agg(F.avg(ratio).alias("ratio")).where(F.col("ratio") > max_ratio).select("label")
    return df.join(binary_classes, "label", "left_anti")


def guessed_text(content: Column) -> Column:
    """Bytes as text by a guessed encoding: UTF-8 where valid, else one character for each byte."""
    return F.when(F.is_valid_utf8(content.cast("string")), content.cast("string")).otherwise(F.decode(content, "ISO-8859-1"))


def label_sets(df: DataFrame) -> DataFrame:
    """(sha, labels): every label under which a content occurs."""
    return df.groupBy("sha").agg(F.sort_array(F.collect_set("label")).alias("labels"))


def ambiguous(df: DataFrame) -> DataFrame:
    return df.groupBy("sha").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("sha")


def drop_ambiguous(df: DataFrame) -> DataFrame:
    """Without contents that occur under several labels."""
    return df.join(ambiguous(df), "sha", "left_anti")


@dataclass(frozen=True)
class Config:
    """min_freq as a fraction; the defaults are those of a corpus of millions of files."""

    min_freq: tuple[int, int] = (1, 10_000)
    max_ratio: float = 0.2
    unit: str = "codepoint"


#: Names of the steps, in the order in which shares are defined.
STEPS = ("raw", "distinct", "frequent", "textual", "unambiguous")


def levels(df: DataFrame, cfg: Config = Config()) -> DataFrame:
    """(file_id, sha, label, level), written: how many steps each file passes. Copies of one label go, then rare classes, binary content, contents of several labels.

    Contents are read once, for their share of non-printables; all steps work on what is left of a file without its content.
    """
    odd = F.coalesce(nonprintable_ratio(F.col("content"), cfg.unit), F.lit(0.0)) > cfg.max_ratio
    facts = keep(df.select("file_id", "sha", "label", odd.alias("odd")))
    pairs = keep(facts.groupBy("sha", "label").agg(F.min("file_id").alias("first"), F.bool_or("odd").alias("odd")))
    frequent = frequent_classes(pairs, cfg.min_freq).withColumn("frequent", F.lit(True))  # as many rows as classes
    flagged = pairs.join(offered(keep(frequent)), "label", "left").withColumns({"frequent": F.coalesce("frequent", F.lit(False)), "fine": ~F.col("odd")})
    clear = F.count_if(F.col("frequent") & F.col("fine")).over(Window.partitionBy("sha")) == 1  # as many rows as labels of a content
    level = 1 + F.when(~F.col("frequent"), 0).when(~F.col("fine"), 1).when(~clear, 2).otherwise(3)
    known = flagged.select("sha", "label", "first", level.alias("level"))
    return keep(facts.select("file_id", "sha", "label").join(known, ["sha", "label"]).select("file_id", "sha", "label", F.when(F.col("file_id") == F.col("first"), F.col("level")).otherwise(0).alias("level")))


def prepare(df: DataFrame, cfg: Config = Config(), limit: int = BROADCAST_BYTES, told: DataFrame | None = None) -> DataFrame:
    """The files that pass every step. What goes, or else what stays, is broadcast if it is small, so that contents are filtered where they are read.

    told: levels(df, cfg), where a caller has them already.
    """
    told = levels(df, cfg) if told is None else told
    last = len(STEPS) - 1
    gone, stays = (told.where(test).select("file_id") for test in (F.col("level") < last, F.col("level") == last))
    if measured(gone) <= limit:
        return df.join(F.broadcast(gone), "file_id", "left_anti")
    return df.join(offered(stays, limit), "file_id", "left_semi")


def funnel(df: DataFrame, cfg: Config = Config()) -> DataFrame:
    """(step, name, files, classes): what is left after each step, out of one pass."""
    counted = levels(df, cfg).groupBy("level", "label").agg(F.count("*").alias("n"))  # as many rows as classes and levels
    reached = counted.select("label", "n", F.explode(F.sequence(F.lit(0), "level")).alias("step"))
    sums = reached.groupBy("step").agg(F.sum("n").alias("files"), F.count_distinct("label").alias("classes"))
    names = df.sparkSession.createDataFrame(list(enumerate(STEPS)), "step int, name string")
    zero = F.lit(0).cast("long")
    return names.join(sums, "step", "left").select("step", "name", F.coalesce("files", zero).alias("files"), F.coalesce("classes", zero).alias("classes"))


def class_distribution(df: DataFrame) -> DataFrame:
    """(label, n, share, rank, cum_share), most frequent first; equal counts by name."""
    by = Window.orderBy(F.desc("n"), "label")  # as many rows as classes
    return class_frequency(df).withColumn("rank", F.row_number().over(by)).withColumn("cum_share", F.sum("n").over(by.rowsBetween(Window.unboundedPreceding, 0)) / F.sum("n").over(Window.partitionBy()))
