"""Queries of the training-data operators and the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import exact_dedup, fingerprints, html_extract, mixing, packing, sharding, simhash, token_binary, toxicity, url_filter


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "op1_imatch": fingerprints.op1_imatch,
    "op2_hierarchical_mix": mixing.op2_hierarchical_mix,
    "op3_hilbert_sharding": sharding.op3_hilbert_sharding,
    "op4_consensus_paths": html_extract.op4_consensus_paths,
    "op5_nearest_examples": toxicity.op5_nearest_examples,
    "op6_blocked_bloom": url_filter.op6_blocked_bloom,
    "op7_simhash_bytes": simhash.op7_simhash_bytes,
    "op8_simple8b_tokens": token_binary.op8_simple8b_tokens,
    "op9_chunk_recipe_dedup": exact_dedup.op9_chunk_recipe_dedup,
    "op10_best_fit_packing": packing.op10_best_fit_packing,
    "pipeline": pipeline,
}

ORACLES = {
    "op2_hierarchical_mix": mixing.ORACLE_SQL,
    "op6_blocked_bloom": url_filter.ORACLE_SQL,
    "op9_chunk_recipe_dedup": exact_dedup.ORACLE_SQL,
}
