"""The corpus pipeline: toxic documents go, copies and near copies go, sources are mixed, and what stays is packed.

Every stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept, and returns a DataFrame that is written as
Parquet and read again before the next stage. All but the last return the columns of documents. Null and empty texts
are clean and equal to one another, and hold no tokens for the mix.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from filekind.llm import exact_dedup, mixing, packing, simhash, similar, toxicity
from filekind.llm.common import discard, small_batches, stash_alone, table

#: The pipeline's mix never repeats a document.
MIX = {"share": 0.6, "epochs": 1}


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose nearest labelled examples make them likelier toxic than not are rejected."""
    small_batches(spark)
    model = toxicity.fit(docs, toxicity.training_labels(spark, sf_dir))
    return toxicity.scored(docs, model, prefix="__tox_").where("__tox_score < 0.5").select(*docs.columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.keep_first(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Under the digest contract of op7, which takes almost identical texts only. Not a stage: the pipeline runs drop_similar."""
    return simhash.keep_one(docs)


def drop_similar(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that share at least 0.8 of their five-word shingles, directly or over others, are one document."""
    small_batches(spark)
    return similar.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.keep_mixed(docs, **MIX)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies),
    ("near_dedup", drop_similar),
    ("mix_sources", mix_sources),
    ("best_fit_packing", pack_sequences),
]

#: Hashes and packing have no equivalent in SQL; tests/llm/test_pipeline.py holds each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage. What a stage wrote on its way goes once its result is written, and that once the next one's is."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        before, docs = docs, stash_alone(lambda docs=docs, stage=stage: stage(spark, docs, sf_dir))
        discard(before)
    return docs
