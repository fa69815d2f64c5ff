"""What a corpus of a given size will take, from measured rates."""

from __future__ import annotations

from dataclasses import dataclass

from ..operators.mlp import parameters


@dataclass(frozen=True)
class Rates:
    """Per core: bytes tokenized a second, and multiply-adds a second in double pairs."""

    tokenize: float = 20e6
    flops: float = 50e9


def capacity(files: float, mean_bytes: float, classes: int, features: int = 5063, hidden: tuple[int, ...] = (1000, 800, 700), per_class: int = 950, epochs: int = 8, cores: int = 1000, rates: Rates = Rates()) -> dict:
    """Seconds and bytes of each step; all grow in proportion to files, but for training, which grows with classes."""
    p = parameters(features, hidden, classes)
    train = classes * per_class
    return {
        "parameters": p, "train_files": train, "metadata_bytes": files * 60,
        "vocabulary_rows_per_partition": classes * (100 + 1000),
        "tokenize_seconds": files * mean_bytes / rates.tokenize / cores, "score_seconds": files * 2 * p / rates.flops / cores,
        "train_seconds_one_core": epochs * train * 6 * p / rates.flops,
    }
