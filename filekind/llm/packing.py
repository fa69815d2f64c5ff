"""Best-fit packing into sequences of several permitted lengths.

Documents longer than the longest sequence are cut into pieces of that length and a rest. Pieces are dealt to packing groups of
bounded size by a hash of their document and, among equal pieces, of their number. Within a group pieces go, longest first, into the fullest open bin that takes
them. When none does, a new bin opens; its length is the permitted one with the least cost for the tokens it can
hold, among those that the plan under trial allows. Every group tries each plan (a least length for new bins), shrinks each bin to the smallest permitted
length that holds its contents, and keeps the plan of least total cost. A bin costs a fixed overhead, its length, and the square of
its length for attention.

Defined cases: a null or empty text has no tokens and gets one row without a bin (piece 0, length 0); null ids and
rows that repeat an id are packed separately and dealt to many groups, and ties go by id and piece; an empty table gives an empty result; further columns are left alone.
"""

from __future__ import annotations

import bisect

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WORD, clean_text, stash, table

LENGTHS = (512, 1024, 2048, 4096)
#: Cost of a bin: OVERHEAD + length + length squared / SQUARE.
OVERHEAD, SQUARE = 16.0, 65_536.0
#: Pieces in a packing group, about.
GROUP = 20_000


def cost(length: int) -> float:
    return OVERHEAD + length + length * length / SQUARE


def fit_length(used: int, lengths: tuple[int, ...]) -> int:
    """The smallest permitted length that holds `used` tokens."""
    return lengths[bisect.bisect_left(lengths, used)]


def best_fit(sizes: np.ndarray, lengths: tuple[int, ...], least: int) -> tuple[list[int], list[int], list[int]]:
    """(bin of each piece, tokens in each bin, opening length of each bin); sizes in the order of packing.

    Open bins are kept by free space: a bit set of the free spaces that occur, and a stack of bins for each.
    """
    price = {n: cost(n) / n for n in lengths}
    opens: list[list[int]] = [[] for _ in range(lengths[-1] + 1)]
    there, place, used, opened = 0, [], [], []
    for size in sizes.tolist():
        above = there >> size
        if above:
            free = size + ((above & -above).bit_length() - 1)
            b = opens[free].pop()
            if not opens[free]:
                there &= ~(1 << free)
        else:
            length = min((n for n in lengths if n >= max(size, least)), key=lambda n: (price[n], n))
            b, free = len(used), length
            used.append(0)
            opened.append(length)
        place.append(b)
        used[b] += size
        free -= size
        if free:
            opens[free].append(b)
            there |= 1 << free
    return place, used, opened


def plans(lengths: tuple[int, ...]) -> list[tuple[tuple[int, ...], int]]:
    """(lengths for new bins, least length): new bins of any permitted length, or of one length upwards, or up to one."""
    out = [(lengths, n) for n in lengths]
    # A longest length below the last still has to take the largest pieces.
    return out + [(tuple(x for x in lengths if x <= n), lengths[0]) for n in lengths[:-1]]


def pack_group(sizes: np.ndarray, lengths: tuple[int, ...] = LENGTHS) -> tuple[list[int], list[int], list[int]]:
    """(bin of each piece, its offset in the bin, the final length of each bin) under the plan of least cost."""
    order = np.argsort(-sizes, kind="stable")
    best, least_cost = None, None
    for allowed, least in plans(lengths):
        if len(sizes) and sizes.max() > allowed[-1]:
            allowed = (*allowed, *(n for n in lengths if n > allowed[-1] and n >= fit_length(int(sizes.max()), lengths)))
        place, used, _ = best_fit(sizes[order], allowed, least)
        final = [fit_length(u, lengths) for u in used]
        total = sum(map(cost, final))
        if least_cost is None or total < least_cost - 1e-9:
            best, least_cost = (place, final), total
    place, final = best
    bins, offsets, filled = [0] * len(sizes), [0] * len(sizes), [0] * len(final)
    for i, b in zip(order.tolist(), place, strict=True):
        bins[i], offsets[i] = b, filled[b]
        filled[b] += int(sizes[i])
    return bins, offsets, final


def pieces(df: DataFrame, tokens: Column, longest: int, id_col: str = "doc_id") -> DataFrame:
    """(doc_id, piece, start, length): documents cut at the longest sequence."""
    held = df.select(F.col(id_col).cast("long").alias("doc_id"), tokens.cast("long").alias("tokens"))
    parts = F.sequence(F.lit(0), F.greatest(F.ceil(F.col("tokens") / longest).cast("int"), F.lit(1)) - 1)
    cut = held.select("doc_id", "tokens", F.explode(parts).alias("piece")).withColumn("start", F.col("piece").cast("long") * longest)
    return cut.select("doc_id", "piece", "start", F.least(F.lit(longest).cast("long"), F.col("tokens") - F.col("start")).alias("length"))


def pack(df: DataFrame, lengths: tuple[int, ...] = LENGTHS, group: int = GROUP, id_col: str = "doc_id", text_col: str = "text", tokens: Column | None = None) -> DataFrame:
    """One row for each piece: doc_id, piece, start, length, bin (group:number), bin_length, offset."""
    lengths = tuple(sorted(lengths))
    tokens = F.regexp_count(clean_text(text_col), F.lit(WORD)) if tokens is None else tokens
    # Equal pieces (of rows that repeat an id) are counted first and get numbers, so that their hashes differ.
    cut = stash(pieces(df, tokens, lengths[-1], id_col).groupBy("doc_id", "piece", "start", "length").agg(F.count("*").alias("copies")))
    groups = max(1, -(-cut.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0] // group))
    each = cut.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "copies")))
    dealt = each.withColumn("grp", F.pmod(F.xxhash64("doc_id", "piece", "length", "copy"), F.lit(groups)).cast("long"))

    def run(x: pd.DataFrame) -> pd.DataFrame:
        x = x.sort_values(["doc_id", "piece", "length"], kind="stable").reset_index(drop=True)
        bins, offsets, final = pack_group(x["length"].to_numpy(np.int64), lengths)
        return x.assign(bin=[f"{g}:{b}" for g, b in zip(x["grp"], bins, strict=True)], bin_length=[final[b] for b in bins], offset=offsets)[list(COLUMNS)]

    binned = dealt.where("length > 0").select(F.col("doc_id").cast("string"), "piece", "start", "length", "grp").groupBy("grp").applyInPandas(run, ", ".join(f"{n} {t}" for n, t in COLUMNS.items()))
    empty = dealt.where("length <= 0").select(F.col("doc_id").cast("string"), "piece", "start", "length", F.lit(None).cast("string").alias("bin"), F.lit(None).cast("int").alias("bin_length"), F.lit(0).cast("long").alias("offset"))
    return binned.union(empty).withColumn("doc_id", F.col("doc_id").cast("long"))


COLUMNS = {"doc_id": "string", "piece": "int", "start": "long", "length": "long", "bin": "string", "bin_length": "int", "offset": "long"}


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
