"""Multinomial naive Bayes over the feature space; a file's score is its frequencies against the logarithms of the class models."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import map_unknown, ngrams
from . import vocab
from .features import Space
from .score import Linear


def class_counts(df: DataFrame, space: Space, trimmed: bool = True) -> DataFrame:
    """(label, n, term, count): at most classes x features rows."""
    cfg = space.cfg
    toks = vocab.tokens(df, cfg.head if trimmed else 0, cfg.tail if trimmed else 0, cfg.unit).select("label", map_unknown(F.col("tokens"), space.terms[1]).alias("t"))
    out = None
    for n in cfg.orders:
        grams = map_unknown(ngrams(F.col("t"), n), space.terms[n], n) if n > 1 else F.col("t")
        part = toks.select("label", F.lit(n).alias("n"), F.explode(grams).alias("term")).groupBy("label", "n", "term").agg(F.count("*").alias("count"))
        out = part if out is None else out.unionByName(part)
    return out


def fit(df: DataFrame, space: Space, trimmed: bool = True, prior: bool = False) -> Linear:
    """Add-one smoothed class models; with `prior`, the shares of the classes in df count as well."""
    sizes = {r.label: r.n for r in df.groupBy("label").agg(F.count("*").alias("n")).collect()}
    classes, index = sorted(sizes), space.index
    counts = np.zeros((space.size, len(classes)))
    for r in class_counts(df, space, trimmed).collect():
        counts[index[r.n][r.term], classes.index(r.label)] = r["count"]
    theta = (counts + 1) / (counts.sum(axis=0) + space.size)
    bias = np.array([math.log(sizes[c] / sum(sizes.values())) if prior else 0.0 for c in classes])
    return Linear(classes, np.log(theta), bias)


#: Tokens that a vector of relative frequencies stands for.
SCALE = 100


def fit_vectors(vectors: DataFrame, space: Space) -> Linear:
    """The same from vectors (file_id, label, idx, freq), real or made up: each counts as SCALE tokens."""
    sums = vectors.groupBy("label", "idx").agg((F.sum("freq") * SCALE).alias("n")).collect()  # at most classes x features rows
    classes = sorted({r.label for r in sums})
    at = {c: i for i, c in enumerate(classes)}
    counts = np.zeros((space.size, len(classes)))
    for r in sums:
        counts[r.idx, at[r.label]] = r.n
    return Linear(classes, np.log((counts + 1) / (counts.sum(axis=0) + space.size)), np.zeros(len(classes)))
