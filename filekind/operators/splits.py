"""Splits by content hash, and later snapshots."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import bucket

#: Shares of the splits, in percent.
SHARES = {"vocab": 20, "train": 40, "val": 20, "test": 20}


def assign(df: DataFrame, shares: dict[str, int] = SHARES, seed: int = 42) -> DataFrame:
    """Adds `split`. Copies of a content fall into one split; nothing is shuffled; proportions are natural."""
    b, upto, out = bucket(F.col("sha"), seed, 100), 0, None
    for name, share in shares.items():
        upto += share
        out = F.when(b < upto, name) if out is None else out.when(b < upto, name)
    return df.withColumn("split", out)


def later_snapshot(old: DataFrame, new: DataFrame) -> DataFrame:
    """Files of the new snapshot with unseen content and a known class."""
    known = F.broadcast(old.select("label").distinct())
    return new.join(old.select("sha").distinct(), "sha", "left_anti").join(known, "label", "left_semi")


def missing_classes(old: DataFrame, new: DataFrame) -> DataFrame:
    """Classes of the old snapshot that the later one lacks."""
    return old.select("label").distinct().join(later_snapshot(old, new).select("label").distinct(), "label", "left_anti")
