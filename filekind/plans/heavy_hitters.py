"""Exact class-conditional vocabularies without shuffling every term: frequent-item summaries first, an exact recount of candidates after."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import keep, offered


def summarize(counters: dict[str, int], term: str, times: int, room: int) -> None:
    """Misra-Gries: any term with more than 1 / (room + 1) of all occurrences stays."""
    if term in counters:
        counters[term] += times
    elif len(counters) < room:
        counters[term] = times
    else:
        cut = min(times, min(counters.values()))
        for t in [t for t, n in counters.items() if n == cut]:
            del counters[t]
        for t in counters:
            counters[t] -= cut
        if times > cut:
            counters[term] = times - cut


#: Summaries that are merged at a time.
FAN = 64


def summaries(terms: DataFrame, room: int) -> DataFrame:
    """(label, part, term, n): a summary of each class in each partition, and with term null the number of its terms there."""
    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        held: dict[str, dict[str, int]] = {}
        totals: dict[str, int] = {}
        for x in parts:
            for (label, term), n in x.groupby(["label", "term"], sort=False).size().items():
                summarize(held.setdefault(label, {}), term, int(n), room)
                totals[label] = totals.get(label, 0) + int(n)
        part = TaskContext.get().partitionId()
        rows = [(label, part, t, n) for label, c in held.items() for t, n in c.items()] + [(label, part, None, n) for label, n in totals.items()]
        yield pd.DataFrame(rows, columns=["label", "part", "term", "n"])

    return terms.select("label", "term").mapInPandas(run, "label string, part long, term string, n long")


def merged(held: DataFrame, room: int, partitions: int) -> DataFrame:
    """One summary for each class: FAN of them become one in each round, so a task holds at most FAN x room counters, whatever the number of partitions."""
    def add(x: pd.DataFrame) -> pd.DataFrame:
        counts = x.groupby("term", dropna=False, as_index=False)["n"].sum()
        known = counts[counts["term"].notna()]
        cut = int(known["n"].nlargest(room + 1).iloc[-1]) if len(known) > room else 0
        kept = known[known["n"] > cut].assign(n=lambda y: y["n"] - cut)
        out = pd.concat([kept, counts[counts["term"].isna()]])
        return out.assign(label=x["label"].iloc[0], part=x["part"].iloc[0] // FAN)[["label", "part", "term", "n"]]

    while True:
        held = held.withColumn("group", F.floor(F.col("part") / FAN)).groupBy("label", "group").applyInPandas(add, "label string, part long, term string, n long")
        if partitions <= FAN:
            return held.select("label", "term", "n")
        partitions = -(-partitions // FAN)


def frequent_terms(terms: DataFrame, tau: tuple[int, int]) -> DataFrame:
    """(label, term, n, total) of the terms over the share; equal to counting everything.

    The terms are read twice: for summaries, which hold every term over the share, and for the exact counts of what they hold.
    """
    num, den = tau
    room = den // num + 1
    parts = keep(summaries(terms, room))
    width = parts.agg(F.coalesce(F.max("part"), F.lit(0)) + 1).first()[0]
    held = keep(merged(parts, room, width))
    found = held.where("term is not null").select("label", "term")  # at most classes x (den / num + 1) rows
    totals = held.where("term is null").select("label", F.col("n").alias("total"))
    counted = terms.join(offered(found), ["label", "term"], "left_semi").groupBy("label", "term").agg(F.count("*").alias("n"))
    return counted.join(offered(totals), "label").where(F.col("n") * den > F.col("total") * num).select("label", "term", "n", "total")
