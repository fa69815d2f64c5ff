"""Connected components of a link table, by alternating star contractions; every round is written to the shared folder.

A table of few links is settled by one task instead, to the same roots: rounds are some ten exchanges each, and every exchange takes a thread of the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stash

#: Links up to which one task settles a table; more are contracted by all.
AT_ONCE = 200_000


def _large(edges: DataFrame) -> DataFrame:
    """Point every larger neighbour of a node at the smallest node of its neighbourhood."""
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small(edges: DataFrame) -> DataFrame:
    """Point every smaller neighbour of a node, and the node, at the smallest of them. Edges have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first())


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, root) of all links of a task: each tree of linked nodes hangs from its smallest."""
    above: dict[int, int] = {}

    def top(x: int) -> int:
        while (up := above.setdefault(x, x)) != x:
            above[x] = x = above[up]
        return x

    for batch in batches:
        for u, v in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            u, v = top(u), top(v)
            above[max(u, v)] = min(u, v)
    nodes = np.fromiter(above, np.int64, len(above))
    roots = np.fromiter(map(top, list(above)), np.int64, len(above))
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(roots)], ["node", "root"])


def components(links: DataFrame, a: str, b: str, rounds: int = 60, at_once: int = AT_ONCE) -> DataFrame:
    """(node, root) for every node that a link between different nodes names; root is the smallest node reachable."""
    edges = stash(links.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct())
    seen = _mark(edges)
    if seen[0] <= at_once and {kind for _, kind in edges.dtypes} == {"bigint"}:
        out = stash(edges.coalesce(1).mapInArrow(_joined, "node long, root long"))
        discard(edges)
        return out
    for _ in range(rounds):
        if not seen[0]:
            break
        nxt = stash(_small(_large(edges)))
        discard(edges)
        edges, mark = nxt, _mark(nxt)
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"links did not settle in {rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).union(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
