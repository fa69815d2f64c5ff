"""Exact deduplication by content-defined chunk recipes.

A text is normalised (each run of ASCII white space becomes one space) and cut into chunks at places that its own
content decides, so equal passages give equal chunks wherever they stand. Distinct chunks get verified identifiers:
the hash of the chunk, and a rank among the different chunks that share this hash, found by comparing the chunks
themselves. A document is then its recipe, the ordered list of identifiers, and equal recipes mean equal texts.
Whole documents never move: each task sends a chunk it holds once, and afterwards only recipes move.

Defined cases: a null text counts as empty, and empty texts equal one another; null ids sort after all others; rows that repeat
an id are kept as rows, each with the group's result, and only one of the rows with the smallest id is marked as kept;
an empty table gives an empty result; further columns are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import clean_text, one_row_each, stash, table

#: Chunk lengths in characters. A cut falls after a letter pair and a space that the pattern names, between both bounds.
LEAST, MOST = 64, 4096
#: About one space in 40 of European prose cuts, far apart against LEAST, so that chunks fall into step soon after an
#: edit; text without such places is cut at MOST. The space leads, so that other characters are passed over at once.
CUT_AFTER = r" (?<=[a-h][n-t] )(?=[a-h][l-t])"


def normalised(text: Column) -> Column:
    """Each run of ASCII white space as one space. Lone spaces, the usual case, are not touched."""
    return F.regexp_replace(text, r"[\x20\x09-\x0D](?:[\x20\x09-\x0D]+|(?<!\x20))", " ")


def chunks(text: Column, least: int = LEAST, most: int = MOST) -> Column:
    """Content-defined chunks, in order; joined they give the text again. An empty text has none."""
    return F.regexp_extract_all(text, F.lit(rf"(?s).{{{least},{most}}}?(?:{CUT_AFTER})|.{{1,{most}}}"), F.lit(0))


def recipes(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: int = LEAST, most: int = MOST, hash_bits: int = 64) -> DataFrame:
    """(doc_id, text_sha256, recipe, copies): the recipe and the number of rows it stands for; recipe lists each chunk as (hash, rank among the chunks of that hash).

    hash_bits below 64 make different chunks share hashes, which tests use to exercise the verification.
    """
    def hashed(c: Column) -> Column:
        return F.shiftrightunsigned(F.xxhash64(c), 64 - hash_bits) if hash_bits < 64 else F.xxhash64(c)

    text = normalised(clean_text(text_col))
    cut = df.select(F.col(id_col).alias("doc_id"), text.alias("body")).select("doc_id", F.sha2("body", 256).alias("text_sha256"), chunks(F.col("body"), least, most).alias("parts"))
    distinct = cut.select(F.explode("parts").alias("part")).select(hashed(F.col("part")).alias("h"), "part").distinct()
    # Hashes that stand for several chunks: only for these the chunk itself must be looked up again.
    shared = stash(distinct.groupBy("h").agg(F.count("*").alias("n")).where("n > 1").select("h"))
    if shared.isEmpty():
        plain = F.transform("parts", lambda p: F.struct(hashed(p).alias("h"), F.lit(0).alias("rank")))
        return cut.select("doc_id", "text_sha256", plain.alias("recipe"), F.lit(1).cast("long").alias("copies"))
    ranks = distinct.join(shared, "h").select("h", "part", F.row_number().over(Window.partitionBy("h").orderBy("part")).alias("rank"))
    placed = cut.select("doc_id", "text_sha256", F.posexplode_outer("parts").alias("pos", "part")).withColumn("h", hashed(F.col("part")))
    listed = placed.join(ranks, ["h", "part"], "left").groupBy("doc_id", "text_sha256").agg(
        F.sort_array(F.collect_set(F.when(F.col("part").isNotNull(), F.struct("pos", "h", F.coalesce("rank", F.lit(0)).alias("rank"))))).alias("found"),
        F.count_if(F.coalesce("pos", F.lit(0)) == 0).alias("copies"),
    )
    return listed.select("doc_id", "text_sha256", F.transform("found", lambda x: F.struct(x["h"].alias("h"), x["rank"].alias("rank"))).alias("recipe"), "copies")


def dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """One row for each input row: doc_id, keep_id, group_size, kept, text_sha256."""
    held = recipes(df, id_col, text_col, **how)
    # One row for each id and recipe; the hash only rides along.
    each = stash(held.groupBy("recipe", "doc_id", "text_sha256").agg(F.sum("copies").alias("copies")))
    # Written, so that both sides of the join are plain exchanges and a recipe that many documents share can be split.
    groups = stash(each.groupBy("recipe").agg(F.min("doc_id").alias("keep_id"), F.sum("copies").alias("group_size")))
    return each.join(groups, "recipe").select(
        "doc_id", "keep_id", "group_size", (F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias("first"), "text_sha256", F.explode(F.sequence(F.lit(1).cast("long"), "copies")).alias("copy"),
    ).select("doc_id", "keep_id", "group_size", (F.col("first") & (F.col("copy") == 1)).alias("kept"), "text_sha256")


def keep_first(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """df without the rows that repeat a text: of equal texts, one row with the smallest id stays."""
    sha = F.sha2(normalised(clean_text(text_col)), 256)
    return one_row_each(df, {"doc_id": F.col(id_col), "text_sha256": sha}, dedup(df, id_col, text_col, **how).where("kept"))


def op9_chunk_recipe_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "documents"))


ORACLE_SQL = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents)
SELECT doc_id, min(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size,
       doc_id = min(doc_id) OVER same AS kept, sha256(body) AS text_sha256
FROM n WINDOW same AS (PARTITION BY body)
"""
