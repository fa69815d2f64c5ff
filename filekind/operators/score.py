"""Scoring: one narrow stage from contents to predictions."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .features import Space, batch_counter, counted, token_column

TOP = pa.list_(pa.struct([("class", pa.string()), ("p", pa.float64())]))
PREDICTIONS = "pred string, p double, top array<struct<class: string, p: double>>"


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


@dataclass
class Linear:
    """Logits as a linear map of the vector: naive Bayes, logistic regression."""

    classes: list[str]
    weights: np.ndarray  # features x classes
    bias: np.ndarray

    def logits(self, rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        return np.stack([f.astype(np.float64) @ self.weights[i] + self.bias for i, f in rows]) if rows else np.zeros((0, len(self.classes)))


def ranked(classes: list[str], p: np.ndarray, k: int) -> list[list[dict]]:
    """The k likeliest classes of each row, equal ones by name. Probabilities are compared to twelve places."""
    names = np.array(classes, object)
    by_name = np.argsort(names, kind="stable")
    order = by_name[np.argsort(-np.round(p[:, by_name], 12), axis=1, kind="stable")][:, :k]
    return [[{"class": str(names[j]), "p": float(row[j])} for j in o] for row, o in zip(p, order, strict=True)]


def predict(df: DataFrame, model, space: Space, k: int = 5, keep: tuple[str, ...] = ("file_id", "label"), tokens: Column | None = None) -> DataFrame:
    """Tokenize, vectorize and score in one pass. Nothing is trimmed. Adds pred, p and the k likeliest classes.

    df needs `content` unless a column of tokens is given.
    """
    sent, count = df.sparkSession.sparkContext.broadcast(model), batch_counter(space)
    k = min(k, len(model.classes))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            p = softmax(sent.value.logits(counted(b.column(len(keep)), count))) if b.num_rows else np.zeros((0, k))
            top = ranked(sent.value.classes, p, k) if b.num_rows else []
            yield pa.RecordBatch.from_arrays(
                [*b.columns[: len(keep)], pa.array([t[0]["class"] for t in top], pa.string()), pa.array([t[0]["p"] for t in top], pa.float64()), pa.array(top, TOP)], [*keep, "pred", "p", "top"],
            )

    kinds = ", ".join(f"{c} {df.schema[c].dataType.simpleString()}" for c in keep)
    return df.select(*keep, (token_column(space.cfg, False) if tokens is None else tokens).alias("__tokens")).mapInArrow(run, f"{kinds}, {PREDICTIONS}")


def snippet(tokens: Column, k: int, where: str = "head") -> Column:
    """k tokens from the head, middle or tail of a file."""
    size = F.size(tokens)
    start = {"head": F.lit(0), "mid": F.floor((size - k) / 2).cast("int"), "tail": size - k}[where]
    return F.slice(tokens, F.greatest(start, F.lit(0)) + 1, k)


def snippets(df: DataFrame, model, space: Space, k: int, where: str = "head", **how) -> DataFrame:
    """Predictions from excerpts alone."""
    return predict(df, model, space, tokens=snippet(token_column(space.cfg, False), k, where), **how)


def embedded(df: DataFrame, tag: str = "script") -> DataFrame:
    """Fragments of another kind inside pages: the contents of script or style elements, as files of their own."""
    found = F.posexplode(F.regexp_extract_all("content", F.lit(rf"(?s)<{tag}[^>]*>(.*?)</{tag}>"), F.lit(1)))
    return df.select("file_id", "label", found.alias("pos", "content")).select(F.concat_ws("#", "file_id", "pos").alias("file_id"), "label", "content")
