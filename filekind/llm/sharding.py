"""Shards cut as runs of a Hilbert curve over quantised metadata.

Every row gets a cell of a small grid (one axis for each metadata column; categories in the order of their names, so that minima and maxima
tell them apart), cells are ordered along a Hilbert curve,
and the ordered rows are cut into runs of equal counts (law `rows`) or nearly equal bytes (law `bytes`). Rows that are
near in several dimensions at once then share a shard, so the minimum and maximum of each dimension prune whole files.

Defined cases: a null metadata value gets grid coordinate 0; a null text has no bytes and CRC 0; rows with equal
metadata lie in one cell and are ordered by salt, id, CRC and size; repeated rows get slots of their own; an empty table gives an
empty result; further columns of the input, whatever their names, are left alone.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import clean_text, discard, running_before, shuffle_width, sized, stash, table

SHARDS = 24
BITS = 5
#: (column, how it is quantised)
DIMENSIONS = (("lang", "category"), ("source", "category"), ("n_chars", "magnitude"))


def curve_steps(dims: int) -> tuple[list[int], list[int]]:
    """Digit and next state of a Hilbert curve in `dims` dimensions, for each state and each corner of a cell.

    A state is (entry corner, direction) as one number; the rule is the published Gray-code construction.
    """
    corners = 1 << dims
    mask = corners - 1

    def turn_left(x: int, k: int) -> int:
        k %= dims
        return ((x << k) | (x >> (dims - k))) & mask

    def gray(x: int) -> int:
        return x ^ (x >> 1)

    rank = {gray(x): x for x in range(corners)}

    def low_ones(x: int) -> int:
        return ((~x & (x + 1)).bit_length() - 1) % dims

    digits, states = [], []
    for entry in range(corners):
        for direction in range(dims):
            for corner in range(corners):
                w = rank[turn_left(corner ^ entry, dims - (direction + 1) % dims)]
                door = 0 if w == 0 else gray(2 * ((w - 1) // 2))
                along = 0 if w == 0 else low_ones(w - 1 if w % 2 == 0 else w)
                digits.append(w)
                states.append((entry ^ turn_left(door, direction + 1)) * dims + (direction + along + 1) % dims)
    return digits, states


def curve_index(coordinates: Sequence[Column], bits: int) -> Column:
    """Index along the curve of integer coordinates in [0, 2**bits), by table look-ups inside generated code."""
    dims = len(coordinates)
    digits, states = (F.split(F.lit(",".join(map(str, t))), ",").cast("array<int>") for t in curve_steps(dims))
    state, index = F.lit(0), F.lit(0).cast("long")
    for bit in reversed(range(bits)):
        corner = F.lit(0)
        for axis, c in enumerate(coordinates):
            corner = corner + F.shiftleft(F.shiftright(c, bit).bitwiseAND(F.lit(1)), axis)
        at = state * (1 << dims) + corner
        index = index * (1 << dims) + F.get(digits, at)
        state = F.get(states, at)
    return index


def category_starts(df: DataFrame, name: str, bits: int) -> list[str]:
    """The first value of each cell of a category's axis, in ascending order: every value if the cells suffice, else cuts of nearly equal rows, from the counts of all values."""
    cells = (1 << bits) - 1
    known = df.select(F.col(name).cast("string").alias("v")).where("v is not null")
    few = sorted(r.v for r in known.distinct().limit(cells + 1).collect())
    if len(few) <= cells:
        return few
    # Tasks hold successive ranges of the sorted values, so their numbers are slices of one order.
    counted = known.groupBy("v").agg(F.count("*").alias("n")).orderBy("v")
    filed = stash(counted.select("v", "n", F.spark_partition_id().alias("slice"), F.lit(0).alias("all")))
    total = filed.agg(F.sum("n")).first()[0]
    places = F.array(*(F.lit(total * i // cells).cast("long") for i in range(1, cells)))
    ranked = running_before(filed, ["all"], "slice", [F.col("v")], {"before": "n"}, shuffle_width(df.sparkSession))
    cuts = ranked.where(F.exists(places, lambda p: (p >= F.col("before")) & (p < F.col("before") + F.col("n")))).select("v").collect()  # no more than cells
    discard(filed)
    return sorted({"", *(r.v for r in cuts)})


def coordinate(df: DataFrame, name: str, how: str, bits: int) -> Column:
    """Quantise a column of df: categories by rank, magnitudes by binary logarithm. Null is 0."""
    top = (1 << bits) - 1
    if how == "category":
        starts = F.array(*map(F.lit, category_starts(df, name, bits))).cast("array<string>")
        c = F.greatest(F.size(F.filter(starts, lambda x: x <= F.col(name).cast("string"))), F.lit(1))
    else:
        c = F.least(F.floor(F.log2(F.greatest(F.col(name), F.lit(0)) + 1)).cast("int"), F.lit(top))
    return F.when(F.col(name).isNull(), 0).otherwise(c)


def hilbert_shards(df: DataFrame, shards: int = SHARDS, law: str = "rows", dims: Sequence[tuple[str, str]] = DIMENSIONS, bits: int = BITS, id_col: str = "doc_id", text_col: str = "text", keep: Sequence[str] = ()) -> DataFrame:
    """One row for each input row: id, size, text_crc32, law, shard, slot, grown_shard, curve, and the columns to keep as one struct `kept`."""
    if law not in ("rows", "bytes"):
        raise ValueError(f"law {law!r}: rows or bytes")
    text = clean_text(text_col)
    meta = stash(
        df.select(
            F.col(id_col).alias("doc_id"),
            (F.octet_length(text) + 8).cast("long").alias("size"),
            F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
            curve_index([coordinate(df, c, how, bits) for c, how in dims], bits).alias("curve"),
            *([F.struct(*keep).alias("kept")] if keep else []),
        )
    )
    rows, total = meta.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    # A crowded cell is split by salt into slices of about this many rows; slices number at most cells + 4 x partitions.
    most = max(1, rows // (4 * shuffle_width(df.sparkSession)))
    cells = meta.groupBy("curve").agg(F.ceil(F.count("*") / most).alias("salts"))
    salted = meta.join(sized(cells, 1 << bits * len(dims)), "curve").select(
        *meta.columns, F.lit(1).cast("long").alias("one"), F.lit(0).alias("all"),
        F.struct("curve", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.col("salts")).alias("salt")).alias("slice"),
    )
    ranked = running_before(salted, ["all"], "slice", [F.col("doc_id"), F.col("text_crc32"), F.col("size")], {"rank": "one", "before": "size"}, (1 << bits * len(dims)) + 4 * shuffle_width(df.sparkSession))
    if law == "rows":
        cut = F.expr(f"rank * {shards}L div {max(rows, 1)}L")
    else:
        cut = F.floor((F.col("before") + F.col("size") / 2) * shards / F.lit(max(total, 1)))
    placed = ranked.withColumn("shard", F.least(cut, F.lit(shards - 1)).cast("int"))
    first = F.expr(f"(shard * {rows}L + {shards - 1}L) div {shards}L")  # of all rows, so in 64 bits
    if law == "bytes":
        starts = placed.groupBy("shard").agg(F.min("rank").alias("first"))
        placed, first = placed.join(F.broadcast(starts), "shard"), F.col("first")
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit(law).alias("law"), "shard",
        (F.col("rank") - first).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "curve", *(["kept"] if keep else []),
    )


def write_shards(df: DataFrame, path: str, rows_per_file: int = 1_000_000, dims: Sequence[tuple[str, str]] = DIMENSIONS, **how) -> DataFrame:
    """Write the rows of df into one folder per shard, files and rows in slot order, and return the pruning manifest. Rows travel with their places, so ids may be null or repeat."""
    placed = stash(hilbert_shards(df, dims=dims, keep=df.columns, **how))
    run = F.expr(f"slot div {rows_per_file}L")
    (
        placed.select("kept.*", F.col("shard").alias("__shard"), F.col("slot").alias("__slot"), run.alias("__run"))
        .repartition("__shard", "__run").sortWithinPartitions("__shard", "__slot").drop("__slot", "__run").write.partitionBy("__shard").parquet(path)
    )
    return manifest(placed, [c for c, _ in dims])


def manifest(placed: DataFrame, columns: Sequence[str]) -> DataFrame:
    """Rows, minimum and maximum of each column in each shard: what a reader prunes files by. placed: hilbert_shards with these columns kept."""
    return placed.groupBy("shard").agg(F.count("*").alias("n"), *(f(F.col("kept")[c]).alias(f"{n}_{c}") for c in columns for n, f in (("min", F.min), ("max", F.max))))


def op3_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hilbert_shards(table(spark, sf_dir, "documents"))
