"""Sources and sinks: the given tables with their schemas, folders of files, and the stores of the engine."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Explicit schemas, so that no reader infers anything.
SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "benchmark": "item_id long, text string",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.schema(SCHEMAS[name]).parquet(f"{folder}/{name}.parquet")


def files(spark: SparkSession, path: str, glob: str = "*") -> DataFrame:
    """CORPUS rows of a folder of files: content hash, name, decoded text (invalid UTF-8 read as single bytes), and bytes."""
    from ..functions.text import extension

    raw = spark.read.format("binaryFile").option("pathGlobFilter", glob).option("recursiveFileLookup", "true").load(path)
    name = F.element_at(F.split("path", "/"), -1)
    return raw.select(
        F.col("path").alias("file_id"), F.sha1("content").alias("sha"),
        F.coalesce(F.try_validate_utf8(F.col("content").cast("string")), F.decode("content", "ISO-8859-1")).alias("content"),
        F.col("content").alias("content_bytes"), name.alias("filename"), extension(name).alias("label"),
        F.lit("files").alias("origin"), F.col("modificationTime").cast("timestamp_ntz").alias("arrival"),
    )


def texts(spark: SparkSession, path: str) -> DataFrame:
    """One row per text file, as whole texts."""
    return spark.read.text(path, wholetext=True).select(F.col("_metadata.file_path").alias("file_id"), F.col("value").alias("content"))


READERS = ("parquet", "json", "csv", "orc", "xml")


def read(spark: SparkSession, path: str, kind: str, schema: str, **options) -> DataFrame:
    if kind not in READERS:
        raise ValueError(f"{kind!r}: one of {READERS}")
    return spark.read.format(kind).schema(schema).options(**options).load(path)


def save_corpus(df: DataFrame, path: str, parts: int = 64) -> None:
    """Parquet by split and hash bucket, so that training never reads test files and joins by content prune."""
    df.withColumn("bucket", F.conv(F.substring("sha", 1, 4), 16, 10).cast("int") % parts).repartition("split", "bucket").write.partitionBy("split", "bucket").parquet(path)


def save_bucketed(df: DataFrame, name: str, buckets: int = 64, key: str = "sha") -> None:
    """A table bucketed by content hash: later joins and groupings by it need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def save_report(df: DataFrame, path: str, kind: str = "json") -> None:
    """A small report in one file."""
    df.coalesce(1).write.format(kind).option("header", "true").save(path)
