"""Balanced training sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import bucket


#: Grains that a seeded draw has, and slices of them that are counted.
GRAINS, SLICES = 1_000_000, 1000


def first_of(df: DataFrame, keys: list[str], wants: DataFrame, seed: int) -> DataFrame:
    """df with `chosen`: whether a row is among the first `want` (a column of wants, one row for each of the keys) of its keys in the seeded order by content hash.

    Rows are counted by slices of the order. All rows of the slices before the one where the want is reached are chosen, none of those after it, and only the rows of that slice
    are ranked, so no class is sorted as a whole.
    """
    drawn = bucket(F.col("sha"), f"draw{seed}", GRAINS)
    place = F.floor(drawn * SLICES / GRAINS).cast("int")
    counted = df.groupBy(*keys, place.alias("__slice")).agg(F.count("*").alias("n"))  # at most SLICES rows for each of the keys
    upto = Window.partitionBy(*keys).orderBy("__slice")
    cuts = counted.withColumn("upto", F.sum("n").over(upto)).join(F.broadcast(wants.select(*keys, "want")), keys).where((F.col("upto") >= F.col("want")) & (F.col("upto") - F.col("n") < F.col("want")))
    edge = cuts.select(*keys, F.col("__slice").alias("__edge"), (F.col("want") - F.col("upto") + F.col("n")).alias("__left"))  # one row for each of the keys
    placed = df.withColumn("__slice", place).join(F.broadcast(edge), keys, "left")
    inside = F.col("__slice") == F.col("__edge")
    order = Window.partitionBy(*keys, "__slice").orderBy(drawn, F.md5(F.concat_ws(":", "sha", F.lit(f"balance{seed}"))), "file_id")
    at_edge = placed.where(inside).withColumn("chosen", F.row_number().over(order) <= F.col("__left"))
    clear = placed.where(~F.coalesce(inside, F.lit(False))).withColumn("chosen", F.coalesce(F.col("__slice") < F.col("__edge"), F.lit(False)))
    return at_edge.unionByName(clear).drop("__slice", "__edge", "__left")


def undersample(df: DataFrame, seed: int = 42, per_class: int | None = None, within: tuple[str, ...] = ()) -> DataFrame:
    """Every class at the size of the smallest (or per_class), drawn by seeded hash. `within` names columns whose values are balanced apart."""
    keys = [*within, "label"]
    counts = df.groupBy(*keys).agg(F.count("*").alias("n"))  # as many rows as classes
    wanted = F.min("n").over(Window.partitionBy(*within)) if per_class is None else F.least(F.lit(per_class), "n")
    return first_of(df, keys, counts.withColumn("want", wanted), seed).where("chosen").select(*df.columns)


def oversample(df: DataFrame, seed: int = 42) -> DataFrame:
    """Every class at the size of the largest: each file as often as goes into it, the first by seeded order once more. Adds `copy`."""
    aims = df.groupBy("label").agg(F.count("*").alias("n")).withColumn("most", F.max("n").over(Window.partitionBy()))  # as many rows as classes
    told = first_of(df, ["label"], aims.withColumn("want", F.col("most") % F.col("n")), seed).join(F.broadcast(aims), "label")
    times = F.floor(F.col("most") / F.col("n")) + F.col("chosen").cast("long")
    return told.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), times))).select(*df.columns, "copy")


def synthesize(vectors: DataFrame, seed: int = 42, k: int | None = None) -> DataFrame:
    """Made-up files: convex mixes of a file's vector with that of a neighbour in the seeded order of its class.

    vectors: file_id, label, idx, freq (long form), of a training set. Each of the k mixes of a file pairs it with the one as many places on; without k, every class
    gets as many as bring it to the size of the largest.
    """
    files = vectors.select("file_id", "label").distinct()
    by = Window.partitionBy("label").orderBy(F.md5(F.concat_ws(":", "file_id", F.lit(f"mix{seed}"))), "file_id")
    ranked = files.withColumn("rank", F.row_number().over(by) - 1).withColumn("n", F.count("*").over(Window.partitionBy("label")))
    if k is None:
        largest = files.groupBy("label").agg(F.count("*").alias("c")).agg(F.max("c").alias("most"))  # one row
        met = ranked.join(F.broadcast(largest))
        times = (F.floor(F.col("most") / F.col("n")) - 1 + (F.col("rank") < F.col("most") % F.col("n")).cast("long")).cast("int")
    else:
        met, times = ranked, F.lit(k)
    shift = F.explode(F.when(times > 0, F.sequence(F.lit(1), times)).otherwise(F.array().cast("array<int>")))
    pairs = met.select("file_id", "label", "rank", "n", shift.alias("shift")).withColumn("other", (F.col("rank") + F.col("shift")) % F.col("n"))
    partner = ranked.select("label", F.col("rank").alias("other"), F.col("file_id").alias("mate"))
    lam = bucket(F.concat_ws(":", "file_id", "shift"), f"lambda{seed}", 1000) / 1000.0
    mixes = pairs.join(partner, ["label", "other"]).select(F.concat_ws("+", "file_id", "mate", "shift").alias("new_id"), "label", "file_id", "mate", lam.alias("lam"))
    own = mixes.join(vectors.select("file_id", "idx", "freq"), "file_id").select("new_id", "label", "idx", (F.col("freq") * (1 - F.col("lam"))).alias("freq"))
    mate = mixes.join(vectors.select(F.col("file_id").alias("mate"), "idx", "freq"), "mate").select("new_id", "label", "idx", (F.col("freq") * F.col("lam")).alias("freq"))
    return own.unionByName(mate).groupBy(F.col("new_id").alias("file_id"), "label", "idx").agg(F.sum("freq").alias("freq"))
