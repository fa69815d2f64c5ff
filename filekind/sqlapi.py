"""The engine's functions for SQL users."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .functions.text import PRINTABLE, SENTINEL, TOKEN


def _quoted(s: str) -> str:
    return "'" + "".join(f"\\u{ord(c):04x}" if ord(c) < 32 else c for c in s).replace("'", "\\'") + "'"


def _raw(s: str) -> str:
    return "r'" + s + "'"


def register(spark: SparkSession, model=None, space=None) -> None:
    """fk_ascii, fk_tokens, fk_ngrams and fk_nonprintable are SQL functions, which the analyzer inlines; fk_ngram_rows is a table
    function; fk_predict, registered where a model is given, is a vectorized Python function."""
    def create(head: str, body: str) -> None:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")

    create("fk_ascii(text STRING) RETURNS STRING", rf"regexp_replace(text, r'[^\x00-\x7f]', {_quoted(SENTINEL)})")
    create("fk_tokens(text STRING) RETURNS ARRAY<STRING>", f"regexp_extract_all(fk_ascii(coalesce(text, '')), {_raw(TOKEN)}, 0)")
    create("fk_ngrams(tokens ARRAY<STRING>, n INT) RETURNS ARRAY<STRING>", "CASE WHEN size(tokens) < n THEN array() ELSE transform(sequence(1, size(tokens) - n + 1), i -> concat_ws(' ', slice(tokens, i, n))) END")
    create("fk_nonprintable(text STRING) RETURNS DOUBLE", f"try_divide(CAST(length(regexp_replace(text, {_raw(PRINTABLE)}, '')) AS DOUBLE), nullif(length(text), 0))")

    @F.udtf(returnType="pos int, ngram string")
    class Ngrams:
        def eval(self, tokens: list, n: int):
            for i in range(len(tokens) - n + 1):
                yield i, " ".join(tokens[i : i + n])

    spark.udtf.register("fk_ngram_rows", Ngrams)
    if model is not None:
        from .operators.features import counter

        count, sent = counter(space), spark.sparkContext.broadcast(model)

        @F.pandas_udf("string")
        def fk_predict(tokens: pd.Series) -> pd.Series:
            m = sent.value
            return pd.Series([m.classes[int(m.logits([count(list(t))])[0].argmax())] for t in tokens], dtype=object)

        spark.udf.register("fk_predict", fk_predict)
