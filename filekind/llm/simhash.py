"""SimHash near-duplicates through an inverted index of byte positions.

A fingerprint of 64 bits is a record of eight tokens, one for each byte with its position. Two fingerprints that differ
in at most d bits share at least 8 - d of these tokens. Of the first d + w positions such a pair shares at least w,
so lists are kept for each choice of w among them: the pair meets in the list of its first shared choice and is taken up there alone.
For each candidate the shared positional bytes are tallied, pairs under the guaranteed minimum go, the rest are
verified by their differing bits. Equal fingerprints are one entry of the index.

A list with more than DENSE entries is not paired up. Its entries go to an exact star join instead: each is filed under itself and its
64 one-bit neighbours, so any two within two bits meet at a common neighbour, where at most 65 entries can meet. Work
stays linear in the entries, whatever the size of a group of near copies, and no link is lost.

Defined cases: a null or empty text, or one of white space only, has fingerprint zero; null ids are smallest to no group
unless all its ids are null (component null); equal ids, repeated rows and ties keep their rows; an empty table gives an empty result.
"""

from __future__ import annotations

from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import one_row_each, stash, table
from .components import components

SHINGLE, SEED = 3, 42
DISTANCE = 2
#: Positional bytes in a list key, and entries up to which a list is paired up.
WIDTH, DENSE = 4, 8


def majority(hashes: np.ndarray) -> int:
    """The bits that over half of the (unsigned 64-bit) hashes set."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at : at + (1 << 16)].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprint(text: bytes | None, size: int = SHINGLE) -> int:
    """SimHash of the word shingles of a UTF-8 text, repeats included; a bit is set if over half of the hashes set it."""
    words = text.lower().split() if text else []
    if not words:
        return 0
    if len(words) < size:
        hashes = np.array([xxhash.xxh64_intdigest(b" ".join(words), SEED)], np.uint64)
    else:
        runs = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False))
        hashes = np.fromiter(map(xxhash.xxh64_intdigest, runs, repeat(SEED)), np.uint64, len(words) - size + 1)
    return majority(hashes)


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, tag, fp): a hash of the text, and the fingerprint as a signed 64-bit integer."""

    def run(batches):
        for batch in batches:
            texts = batch.column(2)
            fps = np.fromiter((fingerprint(t.as_buffer().to_pybytes() if t.is_valid else None) for t in texts), np.uint64, len(texts))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fps.view(np.int64))], ["doc_id", "tag", "fp"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("tag"), F.col(text_col).cast("string").cast("binary").alias("text")).mapInArrow(run, f"doc_id {kind}, tag long, fp long")


def _byte(fp: str, i: int) -> Column:
    return F.shiftrightunsigned(F.col(fp), 8 * i).bitwiseAND(F.lit(255))


def links(fps: DataFrame, distance: int = DISTANCE, width: int = WIDTH, dense: int = DENSE) -> DataFrame:
    """(a, b): links between different values of column fp. All are there, or a chain of links within the distance that joins them."""
    if distance != 2:
        raise ValueError("the star join for dense lists is exact for a distance of 2")
    choices = list(combinations(range(distance + width), width))

    def key(k: int, at: tuple) -> Column:
        packed = F.lit(k).cast("long")
        for i in at:
            packed = F.shiftleft(packed, 8).bitwiseOR(_byte("fp", i))
        return packed

    filed = fps.select("fp", F.explode(F.array(*(key(k, at) for k, at in enumerate(choices)))).alias("key"))
    lengths = filed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    lists = stash(filed.join(lengths, "key"))

    met = lists.where(F.col("n") <= dense).groupBy("key").agg(F.sort_array(F.collect_list("fp")).alias("m"))
    pairs = met.select("key", F.explode(F.flatten(F.transform("m", lambda a: F.transform(F.filter("m", lambda b: b > a), lambda b: F.struct(a.alias("a"), b.alias("b")))))).alias("p")).select("key", "p.a", "p.b")
    same = [(_byte("a", i) == _byte("b", i)).cast("int") for i in range(8)]
    first = F.coalesce(*(F.when(sum((same[i] for i in at), F.lit(0)) == width, F.lit(k)) for k, at in enumerate(choices)))
    found = (
        pairs.where(first == F.shiftright("key", 8 * width))
        .where(sum(same, F.lit(0)) >= 8 - distance)
        .where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= distance)
        .select("a", "b")
    )

    crowded = lists.where(F.col("n") > dense).select("fp").distinct()
    near = F.array(F.col("fp"), *(F.col("fp").bitwiseXOR(F.lit((1 << i) - (1 << 64 if i == 63 else 0))) for i in range(64)))
    stars = crowded.select("fp", F.explode(near).alias("centre")).groupBy("centre").agg(F.min("fp").alias("a"), F.collect_list("fp").alias("m")).where(F.size("m") > 1)
    return found.union(stars.select("a", F.explode("m").alias("b")).where("a != b"))


def grouped(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each input row: doc_id, tag, fp, root (the smallest fingerprint that links reach), component_id."""
    held = stash(fingerprints(df, id_col, text_col))
    entries = stash(held.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = components(links(entries.select("fp")), "a", "b")
    placed = entries.join(roots, entries["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    smallest = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    return held.join(stash(placed.join(smallest, "root").select("fp", "root", "component_id")), "fp")


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each input row: doc_id, fingerprint (16 hex digits), component_id (smallest id that links reach)."""
    return grouped(df, id_col, text_col).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """df with one row of each group of near copies: the one with the smallest id."""
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tag")).alias("first")
    chosen = grouped(df, id_col, text_col).groupBy("root").agg(first).select("first.doc_id", "first.tag")
    return one_row_each(df, {"doc_id": F.col(id_col), "tag": F.xxhash64(text_col)}, chosen)


def op7_simhash_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
