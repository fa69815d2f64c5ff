"""The labelled corpora T1 to T8 over the given tables: (file_id, sha, content, filename, label, origin[, arrival])."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import bucket
from .tables import load

#: Rows that one rendered file holds.
ROWS_PER_FILE = 20


def _corpus(df: DataFrame, file_id: Column, content: Column, label: Column, origin: str) -> DataFrame:
    return df.select(file_id.alias("file_id"), content.alias("content"), label.alias("label"), F.lit(origin).alias("origin")).withColumn("sha", F.sha1("content"))


def prose(spark: SparkSession, sf: str, label: str = "lang") -> DataFrame:
    """T1 (label `lang`) and T3 (label `source`)."""
    d = load(spark, sf, "documents")
    return _corpus(d, F.concat(F.lit("d"), F.col("doc_id").cast("string")), F.col("text"), F.col(label), "documents")


def judged(spark: SparkSession, sf: str, label: str) -> DataFrame:
    """T4 (label `quality`) and T5 (label `toxic`)."""
    d = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id")
    return _corpus(d, F.concat(F.lit("d"), F.col("doc_id").cast("string")), F.col("text"), F.concat(F.lit(label), F.col(label).cast("string")), "documents")


def pages(spark: SparkSession, sf: str) -> DataFrame:
    """Pages by the language of their markup; the attribute that gives the label away is taken out."""
    p = load(spark, sf, "pages")
    lang = F.regexp_extract("html", r'<html lang="([a-z]+)"', 1)
    return _corpus(p, F.concat(F.lit("p"), F.col("page_id").cast("string")), F.regexp_replace("html", r'<html lang="[a-z]+"', "<html"), F.concat(F.lit("html_"), lang), "pages")


def turns(spark: SparkSession, sf: str) -> DataFrame:
    c = load(spark, sf, "conversations")
    return _corpus(c, F.concat_ws("_", F.lit("c"), F.col("conv_id"), F.col("turn")), F.col("text"), F.concat(F.lit("chat_"), F.col("role")), "conversations")


def items(spark: SparkSession, sf: str) -> DataFrame:
    b = load(spark, sf, "benchmark")
    return _corpus(b, F.concat(F.lit("b"), F.col("item_id").cast("string")), F.col("text"), F.lit("bench"), "benchmark")


def _joined(separator: str, *columns: Column) -> Column:
    return F.concat_ws(separator, *columns)


def _number(c: str) -> Column:
    """Doubles as whole hundredths, which all engines print alike."""
    return F.round(F.col(c) * 100).cast("long").cast("string")


def _day(c: str) -> Column:
    return F.date_format(c, "yyyy-MM-dd")


def _text(c: str) -> Column:
    return F.col(c).cast("string")


def _file(key: str, base: int = 0) -> Column:
    return ((F.col(key) - base) / ROWS_PER_FILE).cast("long")


def renderings(spark: SparkSession, sf: str) -> dict[str, tuple[DataFrame, Column, Column, list[str], str]]:
    """Tables as text rows: (table, file number, line, order in the file, separator of lines)."""
    t = {n: load(spark, sf, n) for n in ("events", "orders", "lineitem", "part", "customer", "supplier", "embeddings")}
    quoted = [F.concat(F.lit(f'"{c}":"'), _text(c), F.lit('"')) for c in ("event_type", "user_id")]
    event = F.concat(F.lit('{"id":'), _text("event_id"), F.lit(","), _joined(",", *quoted), F.lit(',"value":'), _number("value"), F.lit(',"props":'), F.col("props"), F.lit("}"))
    return {
        "events": (t["events"], _file("event_id"), event, ["event_id"], "\n"),
        "orders": (t["orders"], _file("o_orderkey", 1), _joined(",", _text("o_orderkey"), _text("o_custkey"), F.col("o_orderstatus"), _number("o_totalprice"), _day("o_orderdate"), F.col("o_orderpriority")), ["o_orderkey"], "\n"),
        "lineitem": (t["lineitem"], _file("l_orderkey", 1), _joined("|", _text("l_orderkey"), _text("l_partkey"), _text("l_suppkey"), _number("l_quantity"), _number("l_extendedprice"), F.col("l_returnflag"), F.col("l_linestatus"), _day("l_shipdate")), ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"], "\n"),
        "part": (t["part"], _file("p_partkey", 1), F.concat(F.lit("<part><name>"), F.col("p_name"), F.lit("</name><brand>"), F.col("p_brand"), F.lit("</brand><size>"), _text("p_size"), F.lit("</size></part>")), ["p_partkey"], "\n"),
        "customer": (t["customer"], _file("c_custkey", 1), _joined("\t", _text("c_custkey"), F.col("c_name"), _text("c_nationkey"), _number("c_acctbal"), F.col("c_mktsegment")), ["c_custkey"], "\n"),
        "supplier": (t["supplier"], _file("s_suppkey", 1), F.concat(F.lit("["), _text("s_suppkey"), F.lit("]\nname = "), F.col("s_name"), F.lit("\nnation = "), _text("s_nationkey")), ["s_suppkey"], "\n"),
        "embeddings": (t["embeddings"], _file("vec_id"), F.array_join(F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long").cast("string")), " "), ["vec_id"], "\n"),
    }


KINDS = {"orders": "csv", "lineitem": "tbl", "part": "xml", "customer": "tsv", "supplier": "ini", "embeddings": "vec"}


def rendered(spark: SparkSession, sf: str, table: str) -> DataFrame:
    """Files of rendered rows. Even and odd files of events are the twins `json` and `jsonl`."""
    rows, number, line, order, sep = renderings(spark, sf)[table]
    # Each file is a bounded group of about ROWS_PER_FILE keys.
    lines = rows.select(number.alias("f"), F.struct(*order, line.alias("line")).alias("x")).groupBy("f").agg(F.sort_array(F.collect_list("x")).alias("xs"))
    label = F.when(F.col("f") % 2 == 0, "json").otherwise("jsonl") if table == "events" else F.lit(KINDS[table])
    return _corpus(lines, F.concat(F.lit(table[0:2]), F.col("f").cast("string")), F.array_join(F.transform("xs", lambda x: x["line"]), sep), label, table)


def mixed(spark: SparkSession, sf: str) -> DataFrame:
    """T2: every kind of file."""
    text = prose(spark, sf).withColumn("label", F.concat(F.lit("txt_"), "label"))
    parts = [text, pages(spark, sf), turns(spark, sf), items(spark, sf), *(rendered(spark, sf, t) for t in ("events", *KINDS))]
    return reduce(DataFrame.unionByName, parts)


def dated(spark: SparkSession, sf: str) -> DataFrame:
    """T6: T1 with the time of the event of the same number as arrival."""
    e = load(spark, sf, "events").select(F.concat(F.lit("d"), F.col("event_id").cast("string")).alias("file_id"), F.col("ts").alias("arrival"))
    return prose(spark, sf).join(e, "file_id")


def named(spark: SparkSession, sf: str, corpus: DataFrame | None = None) -> DataFrame:
    """T7: names end in the label; one in ten has no suffix, one in twenty that of another class."""
    df = mixed(spark, sf) if corpus is None else corpus
    labels = df.select("label").distinct()
    following = labels.select("label", F.coalesce(F.lead("label").over(Window.orderBy("label")), F.min("label").over(Window.partitionBy())).alias("other"))  # as many rows as classes
    b = bucket(F.col("file_id"), "name", 100)
    name = F.when(b < 10, F.col("file_id")).when(b < 15, F.concat_ws(".", "file_id", "other")).otherwise(F.concat_ws(".", "file_id", "label"))
    return df.join(F.broadcast(following), "label").withColumn("filename", name).drop("other")


def injected(spark: SparkSession, sf: str) -> DataFrame:
    """T8: documents, and for each twentieth one a planted blob of hash bytes labelled `blob`."""
    text = prose(spark, sf).withColumn("content_bytes", F.encode("content", "UTF-8"))
    d = load(spark, sf, "documents").where(F.col("doc_id") % 20 == 0)
    seeds = F.transform(F.sequence(F.lit(0), F.lit(7)), lambda k: F.sha2(F.concat_ws(":", F.col("doc_id"), k), 256))
    blob = d.select(F.concat(F.lit("x"), F.col("doc_id").cast("string")).alias("file_id"), F.unhex(F.array_join(seeds, "")).alias("content_bytes"))
    return text.select("file_id", "label", "content_bytes").unionByName(blob.withColumn("label", F.lit("blob")).select("file_id", "label", "content_bytes"))
