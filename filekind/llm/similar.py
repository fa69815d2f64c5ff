"""Near copies by SimHash, verified by the exact Jaccard similarity of word shingles, and completed where fingerprints say too little.

A text is the set of its runs of SHINGLE words. Two sets are alike if they share at least ALIKE of their union. The SimHash of each set goes through the
byte-position lists of the SimHash operator; what they link is verified exactly, and groups of near copies become components in as many pairs as they have texts.
Sets that share no more than ALIKE can differ in a dozen bits and more, further than byte positions can tell, so pairs of texts that are still in different
components are looked for by prefix lists, which miss none. In any one order of
all shingles, sets that are alike share a shingle among the first s - ceil(ALIKE x s) + 1 of each (s its size), so lists are
kept for these alone and no pair is missed. Shingles that half of the texts repeat come last in the order, which keeps lists
short; the order decides the work, never the result.

Each list has one leader: the entry that meets most others over all its lists, for its size. In a group of near copies this is a text with few edits of its own, alike
to far more of the group than two of its other texts are to one another. Every entry is paired first with the best leader of its lists, so that a group, whatever its size, becomes
one component with about as many pairs as it has entries; then with the leaders that are still in other components. Where the lists then leave more than
CROWDED pairs for each row, they get next leaders, as long as each round takes a quarter of what was left; then the pairs of a list that are
still apart are taken up. A pair whose sizes, whose places in the order, or whose first shingles leave too few to share is not verified.

Shingles are compared, and equal sets are one entry, by 64-bit hashes. Words are lower-cased in ASCII and cut at ASCII white space, as in simhash.

Defined cases: a text of fewer words is one shingle; null, empty and blank texts are one another's copies and nobody else's; a group
keeps its smallest id, a null one only if it has no other; repeated rows are copies; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import simhash
from .common import discard, one_row_each, sized, stash
from .components import components

SHINGLE, SEED = 5, 42
#: Least similarity, as a fraction of whole numbers.
ALIKE = (4, 5)
#: The order of shingles is learnt from one text in so many, whatever their number, and names so many shingles (16 bytes each, broadcast).
SAMPLE, NAMED = 2, 1 << 18
#: Pairs of different components for each row of the lists, up to which they are taken up at once.
CROWDED = 16


def shingles(text: bytes | None, size: int = SHINGLE) -> np.ndarray:
    """Hashes of the different word shingles of a UTF-8 text, in ascending order."""
    words = text.lower().split() if text else []
    if not words:
        return np.zeros(0, np.int64)
    if len(words) < size:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), SEED)], np.uint64).view(np.int64)
    runs = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False))
    return np.unique(np.fromiter(map(xxhash.xxh64_intdigest, runs, repeat(SEED)), np.uint64, len(words) - size + 1).view(np.int64))


def entry_of(found: np.ndarray) -> int:
    return int(np.array(xxhash.xxh64_intdigest(found.astype("<i8").tobytes(), SEED), np.uint64).view(np.int64))


def print_of(found: np.ndarray) -> int:
    """SimHash of a set of shingles, as a signed 64-bit integer."""
    return int(np.array(simhash.majority(found.view(np.uint64)), np.uint64).view(np.int64))


def _bytes(batch: pa.RecordBatch, i: int) -> Iterator[bytes | None]:
    return (t.as_buffer().to_pybytes() if t.is_valid else None for t in batch.column(i))


def _lists(parts: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, parts)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*parts, np.zeros(0, np.int64)])))


def repeated(texts: DataFrame, size: int = SHINGLE, sample: int = SAMPLE, named: int = NAMED) -> tuple[np.ndarray, np.ndarray]:
    """(shingles in ascending order, texts that hold them): the most repeated shingles of a sample by hash of the texts (column text, binary)."""

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([*(shingles(t, size) for t in _bytes(batch, 0)), np.zeros(0, np.int64)]))], ["shingle"])

    some = texts.where(F.pmod(F.xxhash64(F.lit("sample"), "text"), F.lit(sample)) == 0)
    counted = some.mapInArrow(run, "shingle long").groupBy("shingle").agg(F.count("*").alias("n")).where("n > 2").orderBy(F.desc("n"), "shingle").limit(named)
    got = counted.toArrow().sort_by("shingle")
    return got["shingle"].to_numpy(), got["n"].to_numpy()


def _size_fits(a: Column, b: Column, alike: tuple[int, int]) -> Column:
    return F.least(a, b) * alike[1] >= F.greatest(a, b) * alike[0]


def _shares(shared: Column, sizes: Column, alike: tuple[int, int]) -> Column:
    """Whether so many shared shingles make sets of these sizes (their sum) alike."""
    return shared * (alike[0] + alike[1]) >= sizes * alike[0]


def grouped(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, alike: tuple[int, int] = ALIKE, sample: int = SAMPLE, crowded: int = CROWDED) -> DataFrame:
    """One row for each input row: doc_id, tag (a hash of the text), root (one value for each group of near copies)."""
    spark, kind = df.sparkSession, df.schema[id_col].dataType.simpleString()
    texts = df.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("tag"), F.col(text_col).cast("string").cast("binary").alias("text"))
    order = spark.sparkContext.broadcast(repeated(texts.select("text"), size, sample))
    share, whole = alike

    def heads(batches):
        known, counts = order.value
        for batch in batches:
            entries, sizes, firsts, prints = [], [], [], []
            for t in _bytes(batch, 2):
                found = shingles(t, size)
                entries.append(entry_of(found))
                prints.append(print_of(found))
                sizes.append(len(found))
                n = len(found) + share * len(found) // -whole + 1 if len(found) else 0
                if len(known):
                    at = np.minimum(np.searchsorted(known, found), len(known) - 1)
                    found = found[np.argsort(np.where(known[at] == found, counts[at], 0), kind="stable")]
                firsts.append(found[:n])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(entries, pa.int64()), pa.array(sizes, pa.int64()), pa.array(prints, pa.int64()), _lists(firsts)], ["doc_id", "tag", "entry", "size", "fp", "heads"])

    def sets(batches):
        for batch in batches:
            found = [shingles(t, size) for t in _bytes(batch, 0)]
            yield pa.RecordBatch.from_arrays([pa.array(list(map(entry_of, found)), pa.int64()), _lists(found)], ["entry", "found"])

    held = stash(texts.mapInArrow(heads, f"doc_id {kind}, tag long, entry long, size long, fp long, heads array<long>"))
    filed = held.select("entry", F.col("size").cast("int").alias("size"), F.posexplode("heads").alias("place", "head"))
    # Rows of one head meet once, in one exchange; most heads have one entry and go.
    each = Window.partitionBy("head")
    met = filed.withColumns({"n": F.count("*").over(each), "least": F.min("entry").over(each), "last": F.max("entry").over(each)}).where("least != last").drop("least", "last")
    ranked = met.dropDuplicates(["head", "entry"]).withColumn("weight", F.sum("n").over(Window.partitionBy("entry")) / F.col("size")).drop("n")
    lists = stash(ranked.withColumn("leader", F.max(F.struct("weight", "entry", "size")).over(each)))

    def hopeful(pairs: DataFrame) -> DataFrame:
        """The pairs whose first shingles leave it open. All that two sets share up to where the first of both lists ends is in both lists; beyond, no more than the rest of that set."""
        pairs = stash(pairs.distinct())
        wanted = pairs.select(F.col("a").alias("entry")).union(pairs.select(F.col("b").alias("entry"))).distinct()
        firsts = stash(held.join(wanted, "entry", "left_semi").select("entry", "size", "heads").dropDuplicates(["entry"]))
        met = pairs.join(firsts.select(F.col("entry").alias("a"), F.col("size").alias("s"), F.col("heads").alias("x")), "a").join(firsts.select(F.col("entry").alias("b"), F.col("size").alias("t"), F.col("heads").alias("y")), "b")
        most = F.size(F.array_intersect("x", "y")) + F.greatest(F.col("s") - F.size("x"), F.col("t") - F.size("y"))
        out = stash(met.where(_size_fits(F.col("s"), F.col("t"), alike) & _shares(most, F.col("s") + F.col("t"), alike)).select("a", "b"))
        discard(pairs)
        discard(firsts)
        return out

    def verified(pairs: DataFrame) -> DataFrame:
        """The pairs (a, b: entries) that are alike."""
        pairs = stash(pairs.distinct())
        wanted = pairs.select(F.col("a").alias("entry")).union(pairs.select(F.col("b").alias("entry"))).distinct()
        tags = stash(held.join(wanted, "entry", "left_semi").groupBy("entry").agg(F.min("tag").alias("tag")).select("tag").distinct())
        read = texts.join(sized(tags, tags.count()), "tag", "left_semi").select("text").mapInArrow(sets, "entry long, found array<long>")
        known = stash(read.dropDuplicates(["entry"]))
        met = pairs.join(known.select(F.col("entry").alias("a"), F.col("found").alias("x")), "a").join(known.select(F.col("entry").alias("b"), F.col("found").alias("y")), "b")
        out = stash(met.where(_shares(F.size(F.array_intersect("x", "y")), F.size("x") + F.size("y"), alike)).select("a", "b"))
        for used in (pairs, tags, known):
            discard(used)
        return out

    prints = stash(held.select("entry", "fp").distinct())
    first = stash(prints.groupBy("fp").agg(F.min("entry").alias("lead")))
    same = prints.join(first, "fp").where("entry != lead").select(F.col("lead").alias("a"), F.col("entry").alias("b"))
    near = simhash.links(first.select("fp")).join(first.select(F.col("fp").alias("a"), F.col("lead").alias("x")), "a").join(first.select(F.col("fp").alias("b"), F.col("lead").alias("y")), "b").select("x", "y")
    links = verified(same.union(near))

    def following(lists: DataFrame) -> DataFrame:
        """(entry, lead, weight): each entry of the lists with their leaders, where sizes leave it open."""
        led = lists.withColumn("lead", F.col("leader.entry")).where((F.col("entry") != F.col("lead")) & _size_fits(F.col("size"), F.col("leader.size"), alike))
        return led.groupBy("entry", "lead").agg(F.max("leader.weight").alias("weight"))

    led = stash(following(lists))
    nearest = led.groupBy("entry").agg(F.max(F.struct("weight", "lead")).alias("best")).select("entry", "best.lead")
    for step in (nearest, led):
        roots = stash(components(links, "a", "b"))
        own, others = (roots.select(F.col("node").alias(n), F.col("root").alias(r)) for n, r in (("entry", "own"), ("lead", "its")))
        apart = step.join(own, "entry", "left").join(others, "lead", "left").where(F.coalesce("own", "entry") != F.coalesce("its", "lead"))
        links = stash(links.union(verified(hopeful(apart.select(F.col("lead").alias("a"), F.col("entry").alias("b"))))))
        discard(roots)
    discard(led)

    def remaining(lists: DataFrame, roots: DataFrame) -> DataFrame:
        """The rows of the lists but for their leaders, which have met all others, where several components are left; with their roots."""
        placed = lists.where("entry != leader.entry").join(roots, F.col("entry") == F.col("node"), "left").select("head", "entry", "size", "place", "weight", F.coalesce("root", "entry").alias("root"))
        mixed = placed.groupBy("head").agg(F.min("root").alias("r"), F.max("root").alias("s")).where("r != s").select("head")
        return stash(placed.join(mixed, "head"))

    def pairs_left(apart: DataFrame) -> tuple[int, float]:
        """(rows, pairs of different components) of the lists."""
        own = apart.groupBy("head", "root").agg(F.count("*").cast("double").alias("n")).groupBy("head").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("own"))
        got = own.agg(F.sum("n"), F.sum((F.col("n") * F.col("n") - F.col("own")) / 2)).first()
        return int(got[0] or 0), got[1] or 0.0

    roots = components(links, "a", "b")
    apart = remaining(lists, roots)
    rows, left = pairs_left(apart)
    before = float("inf")
    while left > crowded * rows and 4 * left <= 3 * before:
        again = stash(apart.withColumn("leader", F.max(F.struct("weight", "entry", "size", "root")).over(each)))
        links = stash(links.union(verified(hopeful(following(again.where("root != leader.root")).select(F.col("lead").alias("a"), F.col("entry").alias("b"))))))
        discard(roots)
        discard(apart)
        roots = components(links, "a", "b")
        apart = remaining(again.drop("root"), roots)
        discard(again)
        before, (rows, left) = left, pairs_left(apart)
    x, y = apart.alias("x"), apart.alias("y")
    left = F.least(F.col("x.size") - F.col("x.place"), F.col("y.size") - F.col("y.place"))  # all they can share from their first common shingle on
    rest = x.join(y, (F.col("x.head") == F.col("y.head")) & (F.col("x.entry") < F.col("y.entry")) & (F.col("x.root") != F.col("y.root"))).where(_size_fits(F.col("x.size"), F.col("y.size"), alike) & _shares(left, F.col("x.size") + F.col("y.size"), alike))
    more = verified(hopeful(rest.select(F.col("x.entry").alias("a"), F.col("y.entry").alias("b"))))
    discard(lists)
    discard(apart)
    if not more.isEmpty():
        roots = components(links.union(more), "a", "b")
    return held.select("doc_id", "tag", "entry").join(roots, F.col("entry") == F.col("node"), "left").select("doc_id", "tag", F.coalesce("root", "entry").alias("root"))


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """df with one row of each group of near copies: the one with the smallest id."""
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tag")).alias("first")
    chosen = grouped(df, id_col, text_col).groupBy("root").agg(first).select("first.doc_id", "first.tag")
    return one_row_each(df, {"doc_id": F.col(id_col), "tag": F.xxhash64(text_col)}, chosen)
