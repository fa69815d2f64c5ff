"""Toxicity by the nearest labelled examples under exact TF-IDF cosine.

Examples are a bounded sample of labelled documents. The term space holds every term of the examples; document frequencies are counted
over all documents, and every text is searched with its whole vector in that space. Terms that many examples hold are dense rows, multiplied for
many texts at once; the others are postings. Cosines fall into blocks of examples, and only blocks whose largest cosine
reaches the k-th best block are opened: the result equals a full scan. The nearest examples and their cosines are the evidence.

Neighbours vote by squared cosine. As a few telling words drown in a long text, a second vote is taken among all examples in the space of the terms whose
presence moves the rate of the label, up or down, beyond chance (a likelihood-ratio test corrected for the number of terms tried). Monotone tables, fitted on
the examples with each left out of its own votes, turn each vote into a rate of the label; the odds of both rates are multiplied, and a third
table turns the product into the score.

The one bound is a parameter: MOST_EXAMPLES labelled rows, those with the smallest hash of their id. All terms of the examples count.
Terms are told apart by 64-bit hashes.

Defined cases: a null, empty or unknown text has no vector; its score is the rate of the label among examples without telling terms,
smoothed towards the rate among all. An
id labelled more than once takes its largest label; null labels and ids teach nothing. Equal cosines go to the earlier example.
With no examples every score is 0. Empty tables give empty results; further columns are left alone, and where one bears the name of a result,
the results' names are led by underscores.
"""

from __future__ import annotations

import math
import re
import uuid
from collections import Counter
from collections.abc import Collection, Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import clean_text, stash, table

MOST_EXAMPLES = 6_144
#: Least examples with a term, and the chance that any term passes by luck.
SUPPORT, ALPHA = 3, 0.05
NEIGHBOURS, BLOCK, EVIDENCE = 25, 64, 5
#: A term that one in so many examples holds is a dense row; texts whose dense parts are multiplied together, and texts whose vectors are held at once.
COMMON, TOGETHER, SLICE = 8, 64, 1024
#: Words whose numbers a task remembers.
MEMO = 200_000
#: Steps of the vote in the calibration table.
STEPS = 20
LETTERS = re.compile(r"[^\W\d_]+")
#: Of each of the first 256 characters: its lower-case form if that is a letter, else a space.
FOLDED = "".join(c if LETTERS.fullmatch(c := chr(i).lower()) else " " for i in range(256)).encode("latin-1")


def words(text: str) -> list[str]:
    """LETTERS.findall(text.lower()); texts of the first 256 characters only go through a table of bytes, which gives the same words."""
    try:
        return text.encode("latin-1").translate(FOLDED).decode("latin-1").split()
    except UnicodeEncodeError:
        return LETTERS.findall(text.lower())


Vector = tuple[np.ndarray, np.ndarray]


class BlockMax:
    """Cosine search over sparse unit vectors; exact, opening only blocks whose largest cosine can be among the k best.

    Terms that at least one in COMMON examples holds are dense rows, the others are postings.
    """

    def __init__(self, vectors: list[Vector], terms: int):
        self.size, self.blocks = len(vectors), max(1, -(-len(vectors) // BLOCK))
        t = np.concatenate([np.zeros(0, np.int32), *(v[0] for v in vectors)]).astype(np.int32)
        w = np.concatenate([v[1] for v in vectors] or [np.zeros(0)])
        p = np.repeat(np.arange(len(vectors), dtype=np.int32), [len(v[0]) for v in vectors])
        held = np.bincount(t, minlength=terms)
        common = np.flatnonzero(held * COMMON >= max(1, len(vectors)))
        self.slot = np.full(terms, -1, np.int32)
        self.slot[common] = np.arange(len(common))
        at = self.slot[t]
        self.rows = np.zeros((len(common), self.blocks * BLOCK))
        self.rows[at[at >= 0], p[at >= 0]] = w[at >= 0]
        by = np.argsort(t, kind="stable").astype(np.int32)
        by = by[at[by] < 0]
        self.place, self.weight = p[by], w[by]
        self.start = np.concatenate([[0], np.cumsum(np.where(self.slot < 0, held, 0))])

    def search(self, t: np.ndarray, w: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, int]:
        """(examples, cosines, blocks opened): the k nearest with a cosine over 0, nearest first, ties by example number."""
        return next(self.search_all([(t, w)], k))

    def search_all(self, vectors: list[Vector], k: int) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
        """search() for each vector."""
        for first in range(0, len(vectors), TOGETHER):
            some = vectors[first : first + TOGETHER]
            asked = np.zeros((len(some), len(self.rows)))
            for i, (t, w) in enumerate(some):
                at = self.slot[t]
                asked[i, at[at >= 0]] = w[at >= 0]
            for (t, w), dense in zip(some, asked @ self.rows, strict=True):
                rare = self.slot[t] < 0
                starts, ends = self.start[t[rare]], self.start[t[rare] + 1]
                lengths = ends - starts
                if total := int(lengths.sum()):
                    # The lists one after the other, gathered at once.
                    at = np.arange(total) + np.repeat(starts - (np.cumsum(lengths) - lengths), lengths)
                    weights = self.weight.take(at) * np.repeat(w[rare], lengths)
                    dense = dense + np.bincount(self.place.take(at), weights, self.blocks * BLOCK)
                yield self.nearest(dense, k)

    def nearest(self, cosine: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, int]:
        cosine = cosine.reshape(self.blocks, BLOCK)
        most = cosine.max(axis=1)
        # The k-th largest of the blocks' maxima is not above the k-th best cosine.
        least = np.partition(most, -k)[-k] - 1e-9 if k < self.blocks else 0.0
        opened = np.flatnonzero((most >= least) & (most > 0))
        got = np.round(cosine[opened], 12)
        b, j = np.nonzero((got > 0) & (got >= least))
        found, near = opened[b] * BLOCK + j, got[b, j]
        top = np.lexsort((found, -near))[:k]
        return found[top], near[top], len(opened)


def calibrate(votes: np.ndarray, truth: np.ndarray) -> np.ndarray:
    """Rate of the label for each step of the vote: smoothed towards the step's own value, then made monotone by pooling neighbours."""
    pools: list[list[float]] = []
    for s in range(STEPS + 1):
        mine = np.round(votes * STEPS) == s if len(votes) else np.zeros(0, bool)
        pools.append([float(truth[mine].sum()) + s / STEPS, float(mine.sum()) + 1, 1])
        while len(pools) > 1 and pools[-2][0] / pools[-2][1] > pools[-1][0] / pools[-1][1]:
            last = pools.pop()
            pools[-1] = [a + b for a, b in zip(pools[-1], last, strict=True)]
    return np.concatenate([np.full(int(n), a / b) for a, b, n in pools])


def rate(votes, table: np.ndarray):
    return np.interp(np.asarray(votes) * STEPS, np.arange(STEPS + 1), table)


def log_odds(p):
    p = np.clip(p, 1e-3, 1 - 1e-3)
    return np.log(p / (1 - p))


class Model:
    """What a scoring task needs; bounded by MOST_EXAMPLES and the terms they hold.

    vocabulary: hashes of terms in ascending order, with idf; telling: the term numbers of the second vote; ids in ascending order, with
    labels; counts: (term numbers, counts) of each example.
    """

    def __init__(self, vocabulary: np.ndarray, idf: np.ndarray, telling: np.ndarray, ids: np.ndarray, label: np.ndarray, counts: list[Vector], k: int = NEIGHBOURS):
        self.k, self.vocabulary, self.idf = k, vocabulary, idf
        self.second = np.full(len(vocabulary), -1, np.int64)
        self.second[telling] = np.arange(len(telling))
        self.ids, self.label = ids, label
        whole = [self.vector(t, n) for t, n in counts]
        short = [self.narrowed(v) for v in whole]
        self.index, self.told = BlockMax(whole, max(1, len(vocabulary))), BlockMax(short, max(1, len(telling)))
        bare = np.array([not len(v[0]) for v in short], bool)
        self.prior = float(self.label.mean()) if len(ids) else 0.0
        self.base = float((self.label[bare].sum() + self.prior) / (bare.sum() + 1)) if len(ids) else 0.0

        def left_out(index: BlockMax, vectors: list[Vector]) -> np.ndarray:
            votes = []
            for i, (near, cosine, _) in enumerate(index.search_all(vectors, self.k + 1)):
                other = near != i
                votes.append(self.vote(near[other][: self.k], cosine[other][: self.k], self.prior))
            return np.array(votes)

        first, second = left_out(self.index, whole), left_out(self.told, short)
        filled = np.array([bool(len(v[0])) for v in whole], bool)
        self.whole_table = calibrate(first[filled], self.label[filled])
        self.told_table = calibrate(second[~bare], self.label[~bare])
        both = self.joint(first, np.where(bare, self.base, rate(second, self.told_table)))
        self.table = calibrate(both[filled], self.label[filled])

    def vector(self, t: np.ndarray, counts: np.ndarray) -> Vector:
        """Unit vector of (1 + ln count) x idf over the term space."""
        w = (1 + np.log(counts)) * self.idf[t]
        return t, w / np.sqrt((w * w).sum()) if len(t) else w

    def narrowed(self, v: Vector) -> Vector:
        """The unit vector over the telling terms alone."""
        at = self.second[v[0]]
        w = v[1][at >= 0]
        return at[at >= 0], w / np.sqrt((w * w).sum()) if len(w) else w

    def vote(self, near: np.ndarray, cosine: np.ndarray, otherwise: float) -> float:
        weight = cosine * cosine
        return float((weight * self.label[near]).sum() / weight.sum()) if len(near) else otherwise

    def joint(self, first, second_rate):
        """The odds of both rates multiplied, over the odds of the label."""
        return 1 / (1 + np.exp(-(log_odds(rate(first, self.whole_table)) + log_odds(second_rate) - log_odds(self.prior))))

    def score_all(self, texts: Iterable[str | None], numbers: Numbers) -> list[tuple[float, list[int], list[float]]]:
        vectors = [self.vector(*numbers(t)) for t in texts]
        out: list = [(self.base, [], [])] * len(vectors)
        if not len(self.ids):
            return out
        known = [i for i, v in enumerate(vectors) if len(v[0])]
        whole = [vectors[i] for i in known]
        short = [self.narrowed(v) for v in whole]
        first, second, shown = [], np.full(len(known), self.base), []
        for near, cosine, _ in self.index.search_all(whole, self.k):
            first.append(self.vote(near, cosine, self.prior))
            shown.append((self.ids[near[:EVIDENCE]].tolist(), cosine[:EVIDENCE].tolist()))
        told = [j for j, v in enumerate(short) if len(v[0])]
        for j, (near, cosine, _) in zip(told, self.told.search_all([short[j] for j in told], self.k), strict=True):
            second[j] = rate(self.vote(near, cosine, self.base), self.told_table)
        scores = rate(self.joint(np.array(first), second), self.table)
        for i, p, (ids, cosines) in zip(known, scores.tolist(), shown, strict=True):
            out[i] = p, ids, cosines
        return out


def hashed(words: Collection[str]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words)).view(np.int64)


class Numbers:
    """Turns texts into (term numbers, counts); the numbers of the first MEMO words seen are kept."""

    def __init__(self, vocabulary: np.ndarray):
        self.vocabulary, self.memo = vocabulary, {}

    def __call__(self, text: str | None) -> Vector:
        counts = Counter(words(text)) if text and len(self.vocabulary) else {}
        at = list(map(self.memo.get, counts))
        if missing := [w for w, i in zip(counts, at, strict=True) if i is None]:
            found = hashed(missing)
            place = np.minimum(np.searchsorted(self.vocabulary, found), len(self.vocabulary) - 1)
            new = dict(zip(missing, np.where(self.vocabulary[place] == found, place, -1).tolist(), strict=True))
            at = [new[w] if i is None else i for w, i in zip(counts, at, strict=True)]
            if len(self.memo) < MEMO:
                self.memo.update(new)
        t, n = np.array(at, np.int64), np.fromiter(counts.values(), np.int64, len(counts))
        return t[t >= 0], n[t >= 0]


def telling_terms(held: np.ndarray, positive: np.ndarray, examples: int, labelled: float) -> np.ndarray:
    """Numbers of the terms whose presence moves the rate of the label beyond chance; held and positive count examples with each term."""
    if not 0 < labelled < examples:
        return np.zeros(0, np.int64)
    tried = np.flatnonzero(held >= SUPPORT)
    m, a, e, p = held[tried].astype(float), positive[tried].astype(float), float(examples), float(labelled)

    def part(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return np.where(x > 0, x * np.log(np.where(x > 0, x, 1) / np.where(x > 0, y, 1)), 0.0)

    ratio = 2 * (part(a, m * p / e) + part(m - a, m * (e - p) / e) + part(p - a, (e - m) * p / e) + part(e - m - p + a, (e - m) * (e - p) / e))
    return tried[ratio >= 2 * math.log(max(len(tried), 1) / ALPHA)]


def frequencies(plain: DataFrame, vocabulary: np.ndarray) -> np.ndarray:
    """Rows of plain (column text) that hold each term of the vocabulary."""
    sent = plain.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers, total = Numbers(sent.value), np.zeros(len(sent.value), np.int64)
        for batch in batches:
            for text in batch.column(0):
                total[numbers(text.as_py())[0]] += 1
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], ["term", "n"])

    got = plain.select("text").mapInArrow(run, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(len(vocabulary), np.int64)
    out[got["term"].to_numpy()] = got["n"].to_numpy()
    return out


def fit(docs: DataFrame, labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "label", most_examples: int = MOST_EXAMPLES, k: int = NEIGHBOURS) -> Model:
    """Fit on the documents that `labelled` (id, label 0 or 1) names; frequencies come from all of docs."""
    wanted = (
        labelled.select(F.col(id_col).cast("long").alias("__id"), F.col(label_col).cast("int").alias("__label")).dropna()
        .groupBy("__id").agg(F.max("__label").alias("__label")).orderBy(F.xxhash64("__id"), "__id").limit(most_examples)
    )
    wanted = F.broadcast(stash(wanted))  # at most most_examples rows
    plain = docs.select(F.col(id_col).cast("long").alias("__id"), clean_text(text_col).alias("text"))
    n = docs.count()
    # Rows that repeat an id are one example.
    held = plain.join(wanted, "__id").groupBy("__id").agg(F.max("__label").alias("label"), F.max("text").alias("text"))

    def counted(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in parts:
            found = [Counter(words(t)) for t in x["text"]]
            yield pd.DataFrame({"id": x["__id"], "label": x["label"], "terms": [hashed(c) for c in found], "counts": [np.fromiter(c.values(), np.int32, len(c)) for c in found]})

    rows = held.mapInPandas(counted, "id long, label int, terms array<long>, counts array<int>").toArrow().sort_by("id").combine_chunks()
    ids, label = rows["id"].to_numpy(), rows["label"].to_numpy().astype(float)
    vocabulary, t = np.unique(np.concatenate([np.zeros(0, np.int64), *(c.flatten().to_numpy() for c in rows["terms"].chunks)]), return_inverse=True)
    t, times = t.astype(np.int32), np.concatenate([np.zeros(0, np.int32), *(c.flatten().to_numpy() for c in rows["counts"].chunks)])
    lengths = np.concatenate([np.zeros(0, np.int64), *(c.value_lengths().to_numpy() for c in rows["terms"].chunks)]).astype(np.int64)
    del rows
    idf = np.log((1 + n) / (1 + frequencies(plain, vocabulary))) + 1 if len(vocabulary) else np.zeros(0)
    telling = telling_terms(np.bincount(t, minlength=len(vocabulary)), np.bincount(t, np.repeat(label, lengths), len(vocabulary)), len(ids), label.sum())
    ends = np.cumsum(lengths)
    return Model(vocabulary, idf, telling, ids, label, [(t[e - m : e], times[e - m : e]) for e, m in zip(ends.tolist(), lengths.tolist(), strict=True)], k)


def scored(df: DataFrame, model: Model, text_col: str = "text", prefix: str = "") -> DataFrame:
    """df with columns score, evidence (ids of the nearest examples) and cosines, named with the prefix. Only the text is read."""
    own = {c.lower() for c in df.columns}
    while own & {(prefix + c).lower() for c in ("score", "evidence", "cosines")}:
        prefix = f"_{prefix}"
    sent = df.sparkSession.sparkContext.broadcast({k: vars(v) if isinstance(v, BlockMax) else v for k, v in vars(model).items()})

    @F.pandas_udf("score double, evidence array<long>, cosines array<double>")
    def run(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        m = Model.__new__(Model)
        vars(m).update(sent.value)
        for name in ("index", "told"):
            index = BlockMax.__new__(BlockMax)
            vars(index).update(sent.value[name])
            setattr(m, name, index)
        numbers = Numbers(m.vocabulary)
        for texts in parts:
            yield pd.DataFrame([r for at in range(0, len(texts), SLICE) for r in m.score_all(texts[at : at + SLICE], numbers)], columns=["score", "evidence", "cosines"])

    got = f"__{uuid.uuid4().hex}"
    out = df.withColumn(got, run(clean_text(text_col)))
    for c in ("score", "evidence", "cosines"):
        out = out.withColumn(prefix + c, F.col(got)[c])
    return out.drop(got)


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 5 == 0, F.lit(False))


def training_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "labels").where(~held_out()).select("doc_id", F.col("toxic").alias("label"))


def op5_nearest_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, training_labels(spark, sf_dir))
    return scored(docs, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "evidence", "cosines")
