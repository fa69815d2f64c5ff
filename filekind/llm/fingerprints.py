"""I-Match fingerprints over several randomised lexicon subsets.

The lexicon holds the terms whose inverse document frequency, counted over all documents, lies in a band: common terms
say too little, rare ones change with every edit. Each subset takes a term of the lexicon by a seeded hash at its own rate. For each
subset the distinct terms of a document that belong to it are sorted and hashed together; the fingerprint is
the list of these hashes. An edit changes a subset's hash only if it adds or removes one of the subset's terms, so thin subsets
survive edits that thick ones notice, and the share of equal hashes tells how alike two documents are. Most subsets are thin, a few tell documents apart.

Documents move once, to meet their successor, in ranges of ids cut by a sample, and all later steps keep that partitioning. The terms of both versions
of a document travel as one list that says which version has each, and only terms of the lexicon are gathered again.

Defined cases: a null text is empty; a document with no term in any subset is represented by the hash of its whole text; a null id
sorts nowhere, so its row has no successor (nothing is put in, near_next is 0); rows that repeat an id follow one another by the hash of their
text; a table of one row is its own successor; an empty table gives an empty result; further columns are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, clean_text, measured, shuffle_width, stash, table

#: Natural logarithms of documents per document with the term: between 1 in 20 and 1 in 2000.
IDF_LOW, IDF_HIGH = 3.0, 7.6
#: A subset takes one lexicon term in so many.
RATES = (8,) * 2 + (32,) * 2 + (128,) * 8 + (512,) * 20
#: Ranges of ids at most, and sampled rows for each range.
MOST_RANGES, SAMPLED = 16_384, 32


def terms(text: Column) -> Column:
    """Distinct lower-case runs of letters and digits, and always the empty term."""
    return F.array_distinct(F.concat(F.array(F.lit("")), F.split(F.lower(text), r"[^\p{L}\p{N}]+")))


def lexicon(df: DataFrame, text_col: str = "text", low: float = IDF_LOW, high: float = IDF_HIGH, rates: tuple = RATES) -> DataFrame:
    """(term, mask): terms of the band that at least one subset takes, with a bit for each subset."""
    n = df.count()
    counted = df.select(F.explode(terms(clean_text(text_col))).alias("term")).groupBy("term").agg(F.count("*").alias("df"))
    idf = F.ln(F.lit(max(n, 1)) / F.col("df"))
    mask = F.lit(0).cast("long")
    for k, rate in enumerate(rates):
        mask = mask.bitwiseOR(F.when(F.pmod(F.xxhash64(F.lit(k), "term"), F.lit(rate)) == 0, F.lit(1 << k)).otherwise(F.lit(0)))
    return counted.where((F.col("term") != "") & idf.between(low, high)).select("term", mask.alias("mask")).where("mask != 0")


def range_cuts(docs: DataFrame, ranges: int) -> list[tuple[int, int, int]]:
    """Cuts between ranges of nearly equal counts of rows, in the order of (doc_id, hash, salt): at most ranges - 1 of them, from a sample of ranges x SAMPLED rows."""
    known = docs.where("doc_id is not null")
    rows = known.count()
    share = min(1.0, ranges * SAMPLED / max(rows, 1))
    some = sorted(tuple(r) for r in (known.sample(False, share, seed=42) if share < 1 else known).select("doc_id", "hash", "salt").limit(2 * ranges * SAMPLED).collect())
    return sorted({some[len(some) * i // ranges] for i in range(1, ranges)}) if some else []


def _range_of(cuts: list[tuple[int, int, int]]) -> Column:
    """The number of cuts that are not above a row, by binary search in folded lists."""
    if not cuts:
        return F.lit(0)
    ids, hashes, salts = (F.split(F.lit(",".join(str(c[i]) for c in cuts)), ",").cast("array<bigint>") for i in range(3))

    def reached(at: Column) -> Column:
        i, h, s = F.get(ids, at), F.get(hashes, at), F.get(salts, at)
        return (F.col("doc_id") > i) | (F.col("doc_id") == i) & ((F.col("hash") > h) | (F.col("hash") == h) & (F.col("salt") >= s))

    strides = F.array(*(F.lit(1 << b) for b in reversed(range(len(cuts).bit_length()))))
    return F.aggregate(strides, F.lit(0), lambda at, step: F.when((at + step <= len(cuts)) & reached(at + step - 1), at + step).otherwise(at))


def with_successor(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(bucket, pos, tail, doc_id, text, next_text): each document with the text that follows it in ascending id, the first after the last.

    Buckets are ranges of (id, hash of the text, salt), so one of far ids or of repeated rows is cut like any other. The first document of each
    bucket is also sent, as a tail, to the bucket before, so the successor of every document stands in its own bucket. Only bucket minima meet in one task.
    """
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), clean_text(text_col).alias("text"))
    docs = docs.withColumns({"hash": F.xxhash64("text"), "salt": F.floor(F.rand(7) * (1 << 30))})
    count = min(MOST_RANGES, 4 * shuffle_width(df.sparkSession))
    apart = (-1 - F.pmod("hash", F.lit(count))).cast("int")
    docs = docs.withColumn("bucket", F.when(F.col("doc_id").isNull(), apart).otherwise(_range_of(range_cuts(docs, count))))
    least = docs.where("doc_id is not null").groupBy("bucket").agg(F.min(F.struct("doc_id", "hash")).alias("first"))
    before = F.coalesce(F.lag("bucket").over(Window.orderBy("bucket")), F.max("bucket").over(Window.partitionBy()))
    firsts = F.broadcast(stash(least.select("bucket", before.alias("to"), F.col("first.doc_id").alias("doc_id"), F.col("first.hash").alias("hash"))))  # one row for each bucket
    tails = docs.join(firsts, ["bucket", "doc_id", "hash"]).dropDuplicates(["bucket"])
    cut = ["tail", "doc_id", "hash", "text"]
    every = docs.select("bucket", F.lit(0).alias("tail"), *cut[1:]).union(tails.select("to", F.lit(1), *cut[1:]))
    order = Window.partitionBy("bucket").orderBy("tail", "doc_id", "hash")
    return every.select("bucket", *cut, F.row_number().over(order).alias("pos"), F.when(F.col("doc_id").isNotNull(), F.lead("text").over(order)).alias("next_text"))


def _hashes(ordered: str, whole: str, size: int) -> Column:
    """The hash of each subset's terms, out of the sorted entries in column `ordered`. One small expression serves all subsets."""
    subsets = F.sequence(F.lit(0), F.lit(size - 1))

    def one(k: Column) -> Column:
        return F.xxhash64(k, F.filter(ordered, lambda x: F.call_function("shiftright", x["mask"], k).bitwiseAND(F.lit(1)) != 0)["term"])

    return F.when(F.size(ordered) == 0, F.transform(subsets, lambda k: F.xxhash64(k, whole))).otherwise(F.transform(subsets, one))


def likeness(a: str, b: str, size: int) -> Column:
    """Share of equal hashes among the subsets that have terms in either document."""
    bare = F.array(*(F.xxhash64(F.lit(k), F.array().cast("array<string>")) for k in range(size)))  # the hashes of subsets without terms
    met = F.arrays_zip(F.col(a).alias("x"), F.coalesce(F.col(b), F.array().cast("array<long>")).alias("y"), bare.alias("none"))
    alike = F.size(F.filter(met, lambda m: (m["x"] == m["y"]) & (m["x"] != m["none"])))
    there = F.size(F.filter(met, lambda m: (m["x"] != m["none"]) | (m["y"] != m["none"])))
    return F.when(F.col(b).isNull(), 0.0).otherwise(F.coalesce(alike / F.nullif(there, F.lit(0)), F.lit(0.0)).cast("double"))


def imatch(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", low: float = IDF_LOW, high: float = IDF_HIGH, rates: tuple = RATES, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Fingerprint every document and its edited text: doc_id, n_chars, edited_sha256, both fingerprints, near_edited, near_next."""
    spark = df.sparkSession
    words = stash(lexicon(df, text_col, low, high, rates).union(spark.sql("select '' term, 0L mask")))
    n = F.length("text")
    edited = F.concat(F.left("text", n - F.floor(n / 4).cast("int")), F.coalesce(F.left("next_text", F.floor(n / 4).cast("int")), F.lit("")))
    both = with_successor(df, id_col, text_col).withColumn("edited", edited)
    row = ["bucket", "pos", "tail", "doc_id", "n_chars", "edited_sha256", "whole", "edited_whole"]
    split = both.select(
        "bucket", "pos", "tail", "doc_id", n.cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"), F.xxhash64("text").alias("whole"), F.xxhash64("edited").alias("edited_whole"),
        terms(F.col("text")).alias("own"), terms(F.col("edited")).alias("other"),
    )

    def marked(found: Column, of: int) -> Column:
        return F.transform(found, lambda t: F.struct(t.alias("term"), F.lit(of).alias("of")))

    # 1: in the text alone, 2: in the edited text alone, 3: in both, as the empty term always is.
    listed = F.concat(marked(F.array_intersect("own", "other"), 3), marked(F.array_except("own", "other"), 1), marked(F.array_except("other", "own"), 2))
    told = split.select(*row, F.explode(listed).alias("x")).select(*row, "x.term", "x.of")
    met = told.join(F.broadcast(words) if measured(words) <= broadcast_bytes else words, "term")
    entry = F.when(F.col("mask") != 0, F.struct("term", "mask", "of"))
    held = met.groupBy(*row).agg(F.sort_array(F.collect_list(entry)).alias("entries"))

    def of(version: int) -> Column:
        return F.filter("entries", lambda x: x["of"].bitwiseAND(F.lit(version)) != 0)

    hashed = held.select(*row, of(1).alias("own"), of(2).alias("other")).select(
        "bucket", "pos", "tail", "doc_id", "n_chars", "edited_sha256", _hashes("own", "whole", len(rates)).alias("a"), _hashes("other", "edited_whole", len(rates)).alias("b"),
    )
    following = hashed.withColumn("c", F.when(F.col("doc_id").isNotNull(), F.lead("a").over(Window.partitionBy("bucket").orderBy("pos"))))

    def shown(name: str) -> Column:
        return F.array_join(F.transform(name, lambda h: F.lower(F.lpad(F.hex(h), 16, "0"))), "")

    return following.where("tail = 0").select(
        "doc_id", "n_chars", "edited_sha256", shown("a").alias("fingerprint"), shown("b").alias("edited_fingerprint"),
        likeness("a", "b", len(rates)).alias("near_edited"), likeness("a", "c", len(rates)).alias("near_next"),
    )


def op1_imatch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return imatch(table(spark, sf_dir, "documents"))
