"""A second tier of specialists, one for each confusion group."""

from __future__ import annotations


from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import mlp
from .score import softmax


@dataclass
class Tiers:
    """A first-tier model and nets by group; logits of it are logarithms of the combined probabilities.

    route: a file whose likeliest class is in a group is decided by the group's specialist alone;
    product: the group's probability times the specialist's within it.
    """

    base: object
    nets: list[mlp.Net]
    mode: str = "route"

    @property
    def classes(self) -> list[str]:
        return self.base.classes

    def logits(self, rows: mlp.Rows) -> np.ndarray:
        p = softmax(self.base.logits(rows))
        for net in self.nets:
            at = np.array([self.classes.index(c) for c in net.classes])
            mine = np.flatnonzero(np.isin(p.argmax(axis=1), at)) if self.mode == "route" else np.arange(len(p))
            if len(mine):
                inside = softmax(net.logits([rows[i] for i in mine]))
                p[np.ix_(mine, at)] = p[np.ix_(mine, at)].sum(axis=1, keepdims=True) * inside
        return np.log(np.maximum(p, 1e-30))


def disjoint(groups: list[list[str]]) -> list[list[str]]:
    """Groups, larger first, without classes that an earlier one has; what is left of fewer than two is dropped."""
    seen, out = set(), []
    for g in sorted(groups, key=lambda g: (-len(g), g)):
        rest = [c for c in g if c not in seen]
        if len(rest) > 1:
            out.append(sorted(rest))
            seen |= set(rest)
    return out


def fit(vectors: DataFrame, groups: list[list[str]], base, size: int, spec: mlp.Spec, mode: str = "route") -> Tiers:
    """Train the specialists at once, a group to a task. vectors: balanced CSR rows, so groups are bounded."""
    apart = disjoint(groups)
    if not apart:
        return Tiers(base, [], mode)
    member = F.create_map(*(F.lit(x) for g, cs in enumerate(apart) for c in cs for x in (c, g)))

    def train(x: pd.DataFrame) -> pd.DataFrame:
        x = x.sort_values("file_id")
        classes = sorted(x["label"].unique())
        net = mlp.start(size, classes, spec)
        rows = [(np.array(i, np.int64), np.array(f, np.float32)) for i, f in zip(x["indices"], x["freqs"])]
        y, adam = np.array([classes.index(c) for c in x["label"]]), mlp.Adam(net, spec)
        for epoch in range(spec.epochs):
            mlp.epoch_pass(net, adam, rows, y, spec, epoch)
        parts = [p for wb in zip(net.weights, net.biases) for p in wb]
        return pd.DataFrame({"grp": [int(x["grp"].iloc[0])], "classes": [classes], "shapes": [[",".join(map(str, p.shape)) for p in parts]], "data": [[p.astype(np.float32).tobytes() for p in parts]]})

    told = vectors.withColumn("grp", F.try_element_at(member, F.col("label"))).where("grp is not null").select("grp", "file_id", "label", "indices", "freqs")
    nets = []
    for r in sorted(told.groupBy("grp").applyInPandas(train, "grp int, classes array<string>, shapes array<string>, data array<binary>").collect(), key=lambda r: r.grp):
        parts = [np.frombuffer(d, np.float32).reshape([int(v) for v in s.split(",")]) for d, s in zip(r.data, r.shapes)]
        nets.append(mlp.Net(list(r.classes), parts[0::2], parts[1::2]))
    return Tiers(base, nets, mode)


