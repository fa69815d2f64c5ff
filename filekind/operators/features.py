"""Feature spaces and relative-frequency vectors."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import UNKNOWN, map_unknown, ngrams, tokens_of, trim
from . import vocab


@dataclass(frozen=True)
class Config:
    orders: tuple[int, ...] = (1, 2)
    tau: dict = field(default_factory=lambda: dict(vocab.TAU))
    combine: str = "any"
    head: int = 10
    tail: int = 10
    unit: str = "codepoint"
    denom: str = "tokens"
    unknown_in_ngrams: str = "keep"
    max_chars: int = 0  # over 0: of a longer file only as many characters are read, in three windows; approximate, so off by default


@dataclass(frozen=True)
class Space:
    """The ordered features: for each n-gram order its terms by name, then its unknown symbol."""

    terms: dict[int, list[str]]
    cfg: Config

    @property
    def index(self) -> dict[int, dict[str, int]]:
        out, at = {}, 0
        for n in self.cfg.orders:
            out[n] = {t: at + i for i, t in enumerate([*self.terms[n], UNKNOWN[n]])}
            at += len(out[n])
        return out

    @property
    def size(self) -> int:
        return sum(len(self.terms[n]) + 1 for n in self.cfg.orders)

    def table(self, spark: SparkSession) -> DataFrame:
        """(idx, n, term, is_unknown)."""
        rows = [(i, n, t, t == UNKNOWN[n]) for n, terms in self.index.items() for t, i in terms.items()]
        return spark.createDataFrame(sorted(rows), "idx int, n int, term string, is_unknown boolean")


def learn_space(holdout: DataFrame, cfg: Config = Config()) -> Space:
    """Vocabularies of all orders from the files of a (balanced) holdout."""
    toks = vocab.tokens(holdout, cfg.head, cfg.tail, cfg.unit)
    known = vocab.as_list(vocab.build(toks, 1, None, cfg.tau[1], cfg.combine))
    terms = {1: known}
    for n in cfg.orders:
        if n > 1:
            found = vocab.as_list(vocab.build(toks, n, known, cfg.tau[n], cfg.combine))
            if cfg.unknown_in_ngrams == "drop":
                found = [t for t in found if UNKNOWN[1] not in t.split(" ")]
            terms[n] = found
    return Space(terms, cfg)


def vectorize_sql(df: DataFrame, space: Space, trimmed: bool = False) -> DataFrame:
    """(file_id, label, idx, freq) in long form, by rows and joins alone. Files without tokens have no rows."""
    cfg = space.cfg
    toks = vocab.tokens(df, cfg.head if trimmed else 0, cfg.tail if trimmed else 0, cfg.unit)
    mapped = toks.select("file_id", "label", F.size("tokens").alias("size"), map_unknown(F.col("tokens"), space.terms[1]).alias("t"))
    out = None
    for n in cfg.orders:
        grams = map_unknown(ngrams(F.col("t"), n), space.terms[n], n) if n > 1 else F.col("t")
        whole = F.col("size") if cfg.denom == "tokens" else F.col("size") - (n - 1)
        part = mapped.select("file_id", "label", whole.alias("whole"), F.explode(grams).alias("term"), F.lit(n).alias("n"))
        out = part if out is None else out.unionByName(part)
    counted = out.groupBy("file_id", "label", "n", "term", "whole").agg(F.count("*").alias("count"))
    return counted.join(F.broadcast(space.table(df.sparkSession)), ["n", "term"]).select("file_id", "label", "idx", (F.col("count") / F.col("whole")).alias("freq"))


def counter(space: Space):
    """A function from one list of tokens to (indices, frequencies): the plain definition, for single rows."""
    cfg, index = space.cfg, space.index

    def run(tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
        first, size = index[1], len(tokens)
        mapped = [t if t in first else UNKNOWN[1] for t in tokens]
        found: Counter = Counter()
        for n in cfg.orders:
            known, other = index[n], index[n][UNKNOWN[n]]
            grams = mapped if n == 1 else [" ".join(g) for g in zip(*(mapped[i:] for i in range(n)))]
            whole = size if cfg.denom == "tokens" else size - n + 1
            for t, c in Counter(grams).items():
                found[known.get(t, other)] += c / whole
        at = np.array(sorted(found), np.int32)
        return at, np.array([found[i] for i in at.tolist()], np.float64)

    return run


def batch_counter(space: Space):
    """A function from an Arrow array of token lists to (indices, frequencies) of each, by array operations over the whole batch."""
    cfg, first = space.cfg, {t: i for i, t in enumerate(space.terms[1])}
    base, unknown = len(first) + 1, len(first)
    words, width = pa.array(space.terms[1], pa.string()), space.size
    coded, offset, bounds = {}, 0, []
    for n in cfg.orders:
        if n > 1:
            codes = [sum(first.get(t, unknown) * base ** (n - 1 - k) for k, t in enumerate(g.split(" "))) for g in space.terms[n]]
            by = np.argsort(np.array(codes, np.int64), kind="stable")
            coded[n] = np.array(codes, np.int64)[by], by
        bounds.append((n, offset))
        offset += len(space.terms[n]) + 1

    def run(tokens: pa.ListArray) -> list[tuple[np.ndarray, np.ndarray]]:
        starts = tokens.offsets.to_numpy().astype(np.int64)
        sizes = np.diff(starts)
        doc = np.repeat(np.arange(len(sizes)), sizes)
        code = pc.index_in(tokens.flatten(), value_set=words).fill_null(unknown).to_numpy(zero_copy_only=False).astype(np.int64)
        keys = []
        for n, at in bounds:
            if n == 1:
                keys.append(doc * width + at + code)
                continue
            m = max(len(code) - n + 1, 0)
            whole = doc[:m] == doc[n - 1 : n - 1 + m]
            gram = np.zeros(m, np.int64)
            for k in range(n):
                gram = gram * base + code[k : k + m]
            gram, where = gram[whole], doc[:m][whole]
            known, by = coded[n]
            place = np.minimum(np.searchsorted(known, gram), max(len(known) - 1, 0))
            found = known[place] == gram if len(known) else np.zeros(len(gram), bool)
            keys.append(where * width + at + np.where(found, by[place] if len(known) else 0, len(known)))
        key, times = np.unique(np.concatenate(keys), return_counts=True)
        row, idx = key // width, key % width
        size = sizes[row].astype(np.float64)
        if cfg.denom != "tokens":
            for n, at in bounds:
                size[idx >= at] = sizes[row[idx >= at]] - n + 1
        ends = np.searchsorted(row, np.arange(1, len(sizes)))
        return list(zip(np.split(idx, ends), np.split(times / size, ends), strict=True)) if len(sizes) else []

    return run


#: Files that are counted at a time.
TOGETHER = 1000


def counted(tokens: pa.ListArray, count) -> list[tuple[np.ndarray, np.ndarray]]:
    return [row for at in range(0, len(tokens), TOGETHER) for row in count(tokens.slice(at, TOGETHER))]


def windows(content: Column, most: int) -> Column:
    """Head, middle and tail of a text over `most` characters, apart by a line feed; shorter texts as they are."""
    third, size = most // 3, F.length(content)
    middle = F.substring(content, F.floor((size - third) / 2).cast("int") + 1, F.lit(third))
    return F.when(size > most, F.concat_ws("\n", F.left(content, F.lit(third)), middle, F.right(content, F.lit(third)))).otherwise(content)


def token_column(cfg: Config, trimmed: bool) -> Column:
    t = tokens_of(windows(F.col("content"), cfg.max_chars) if cfg.max_chars else F.col("content"), cfg.unit)
    return trim(t, cfg.head, cfg.tail) if trimmed else t


CSR = "file_id string, label string, n_tokens int, indices array<int>, freqs array<float>"


def vectorize(df: DataFrame, space: Space, trimmed: bool = False) -> DataFrame:
    """VECTORS_CSR in one narrow stage; a file without tokens is a zero vector."""
    count = batch_counter(space)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = counted(b.column(2), count)
            ends = np.cumsum([0, *(len(i) for i, _ in rows)]).astype(np.int32)
            flat = [np.concatenate([r[k] for r in rows]) if rows else np.zeros(0) for k in (0, 1)]
            lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(flat[0].astype(np.int32))), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat[1].astype(np.float32)))]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pc.list_value_length(b.column(2)).cast(pa.int32()), *lists], ["file_id", "label", "n_tokens", "indices", "freqs"])

    return df.select("file_id", "label", token_column(space.cfg, trimmed).alias("tokens")).mapInArrow(run, CSR)


def to_sparse(vectors: DataFrame, size: int) -> DataFrame:
    """Adds `features`, a vector column for the ML library."""
    from pyspark.ml.functions import array_to_vector

    dense = F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.coalesce(F.element_at(F.map_from_arrays("indices", "freqs"), i.cast("int")), F.lit(0.0).cast("float")).cast("double"))
    return vectors.withColumn("features", array_to_vector(dense))
