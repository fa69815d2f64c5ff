"""A small convolution over tokens, the stand-in for models of order: embedded tokens, runs of WIDTH of them against filters, the largest response of each filter, softmax.

Trained on the driver like the small network, as balanced train sets are small whatever the corpus is; long files are trained on by one seeded window. Prediction
reads whole files, a bounded piece at a time, in one narrow stage.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import Space, token_column
from .mlp import Adam, Spec
from .score import PREDICTIONS, TOP, ranked, softmax

WIDTH = 3
#: Tokens of a file that training reads, and tokens of a file that prediction holds at a time.
WINDOW, PIECE = 400, 20_000
SETTINGS = Spec(hidden=(16, 64), dropout=0.0, lr=5e-3, epochs=12, batch=32)  # embedding and filters


@dataclass
class Convolution:
    classes: list[str]
    weights: list[np.ndarray]  # embedding (tokens + unknown + padding), filters, output
    biases: list[np.ndarray]  # unused, of filters, of output

    def responses(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(runs, responses) of padded token numbers (files x length)."""
        x = self.weights[0][ids]
        runs = np.concatenate([x[:, k : x.shape[1] - WIDTH + 1 + k] for k in range(WIDTH)], axis=2)
        return runs, runs @ self.weights[1] + self.biases[1]

    def pooled(self, ids: np.ndarray) -> np.ndarray:
        """The largest response of each filter over a whole file, at least 0."""
        best = np.zeros(self.weights[1].shape[1])
        ids = np.concatenate([ids, np.full(max(0, WIDTH - len(ids)), len(self.weights[0]) - 1, ids.dtype)])
        for at in range(0, len(ids) - WIDTH + 1, PIECE):
            best = np.maximum(best, self.responses(ids[None, at : at + PIECE + WIDTH - 1])[1].max(axis=(0, 1)))
        return best

    def logits(self, files: list[np.ndarray]) -> np.ndarray:
        return np.stack([self.pooled(f) for f in files]) @ self.weights[2] + self.biases[2]


def gradient(net: Convolution, ids: np.ndarray, y: np.ndarray) -> tuple[list[np.ndarray], float]:
    """(gradients of weights and biases in turn, summed loss) of the mean cross-entropy."""
    runs, r = net.responses(ids)
    place = r.argmax(axis=1)
    files = np.arange(len(y))[:, None]
    h = np.maximum(np.take_along_axis(r, place[:, None, :], axis=1)[:, 0], 0)
    p = softmax(h @ net.weights[2] + net.biases[2])
    loss = float(-np.log(np.maximum(p[np.arange(len(y)), y], 1e-30)).sum())
    d = p
    d[np.arange(len(y)), y] -= 1
    d /= len(y)
    dh = (d @ net.weights[2].T) * (h > 0)
    dw = np.einsum("bf,bfe->ef", dh, runs[files, place])
    dx = dh[:, :, None] * net.weights[1].T[None]
    de, size = np.zeros_like(net.weights[0]), net.weights[0].shape[1]
    for k in range(WIDTH):
        np.add.at(de, ids[files, place + k], dx[:, :, k * size : (k + 1) * size])
    return [de, np.zeros_like(net.biases[0]), dw, dh.sum(axis=0), h.T @ d, d.sum(axis=0)], loss


def numbers(space: Space):
    """A function from an Arrow array of token lists to the token numbers of each; unknown tokens share one."""
    words = pa.array(space.terms[1], pa.string())

    def run(tokens: pa.ListArray) -> list[np.ndarray]:
        code = pc.index_in(tokens.flatten(), value_set=words).fill_null(len(words)).to_numpy(zero_copy_only=False)
        ends = tokens.offsets.to_numpy()
        return [code[a:b] for a, b in zip(ends[:-1] - ends[0], ends[1:] - ends[0], strict=True)]

    return run


def start(tokens: int, classes: list[str], spec: Spec) -> Convolution:
    rng, (embed, filters) = np.random.default_rng(spec.seed), spec.hidden
    weights = [rng.standard_normal((tokens + 2, embed)) * 0.3, rng.standard_normal((WIDTH * embed, filters)) * np.sqrt(2 / (WIDTH * embed)), rng.standard_normal((filters, len(classes))) * np.sqrt(1 / filters)]
    return Convolution(classes, weights, [np.zeros(1), np.zeros(filters), np.zeros(len(classes))])


def fit(train: DataFrame, space: Space, spec: Spec = SETTINGS) -> Convolution:
    """train: a balanced set of file_id, label, content. Every epoch reads a seeded window of each file."""
    rows = train.select("file_id", "label", token_column(space.cfg, False).alias("tokens")).toArrow().sort_by("file_id").combine_chunks()
    classes = sorted(set(rows["label"].to_pylist()))
    y = np.array([classes.index(c) for c in rows["label"].to_pylist()])
    count = numbers(space)
    files = [f for chunk in rows["tokens"].chunks for f in count(chunk)]
    net = start(len(space.terms[1]), classes, spec)
    adam, pad = Adam(net, spec), len(space.terms[1]) + 1
    for epoch in range(spec.epochs):
        rng = np.random.default_rng((spec.seed, epoch))
        order = rng.permutation(len(files))
        for at in range(0, len(order), spec.batch):
            some = order[at : at + spec.batch]
            cut = [files[i][(s := rng.integers(0, max(1, len(files[i]) - WINDOW + 1))) : s + WINDOW] for i in some]
            ids = np.full((len(cut), max(WIDTH, *map(len, cut))), pad)
            for r, c in enumerate(cut):
                ids[r, : len(c)] = c
            adam.step(gradient(net, ids, y[some])[0])
    return net


def predict(df: DataFrame, net: Convolution, space: Space, k: int = 5) -> DataFrame:
    """file_id, label, pred, p, top, from whole files."""
    sent, count = df.sparkSession.sparkContext.broadcast(net), numbers(space)
    k = min(k, len(net.classes))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            top = ranked(sent.value.classes, softmax(sent.value.logits(count(b.column(2)))), k) if b.num_rows else []
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([t[0]["class"] for t in top], pa.string()), pa.array([t[0]["p"] for t in top], pa.float64()), pa.array(top, TOP)], ["file_id", "label", "pred", "p", "top"])

    return df.select("file_id", "label", token_column(space.cfg, False).alias("tokens")).mapInArrow(run, f"file_id string, label string, {PREDICTIONS}")
