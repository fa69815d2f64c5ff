"""Class-conditional vocabularies of tokens and n-grams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import UNKNOWN, map_unknown, ngrams, tokens_of, trim

#: Least shares as (numerator, denominator), by order.
TAU = {1: (1, 100), 2: (1, 1000), 3: (1, 1000)}


def tokens(df: DataFrame, head: int = 0, tail: int = 0, unit: str = "codepoint", extra: tuple[str, ...] = ()) -> DataFrame:
    """(file_id, label, tokens): trimmed where counts are given. A column `tokens` that df has stands for its content."""
    t = F.col("tokens") if "tokens" in df.columns else tokens_of(F.col("content"), unit)
    return df.select("file_id", "label", *extra, (trim(t, head, tail) if head or tail else t).alias("tokens"))


def terms(toks: DataFrame, n: int = 1, known: list[str] | None = None) -> DataFrame:
    """(file_id, label, term): n-grams, over tokens mapped to `known` for n over 1."""
    col = F.col("tokens") if known is None else map_unknown(F.col("tokens"), known)
    return toks.select("file_id", "label", F.explode(ngrams(col, n)).alias("term"))


def class_term_freq(toks: DataFrame, n: int = 1, known: list[str] | None = None) -> DataFrame:
    """(label, term, n, total). Counts meet as partial sums of each task; totals are as many rows as classes."""
    counted = terms(toks, n, known).groupBy("label", "term").agg(F.count("*").alias("n"))
    totals = toks.groupBy("label").agg(F.sum(F.greatest(F.size("tokens") - (n - 1), F.lit(0))).cast("long").alias("total"))
    return counted.join(F.broadcast(totals), "label").select("label", "term", "n", "total")


def select_terms(freq: DataFrame, tau: tuple[int, int], combine: str = "any", classes: int | None = None) -> DataFrame:
    """(term, n_classes, max_share): terms over the share in any class, in all classes, or in the whole corpus."""
    num, den = tau
    over = F.col("n") * den > F.col("total") * num
    share = F.max(F.col("n") / F.col("total")).alias("max_share")
    if combine == "any":
        return freq.where(over).groupBy("term").agg(F.count("*").alias("n_classes"), share)
    if combine == "all":
        return freq.where(over).groupBy("term").agg(F.count("*").alias("n_classes"), share).where(F.col("n_classes") == classes)
    if combine != "global":
        raise ValueError(f"combine {combine!r}: any, all or global")
    whole = freq.select("label", "total").distinct().agg(F.sum("total").alias("whole"))
    joined = freq.groupBy("term").agg(F.sum("n").alias("n"), F.count("*").alias("n_classes")).join(F.broadcast(whole))  # one row
    return joined.where(F.col("n") * den > F.col("whole") * num).select("term", "n_classes", (F.col("n") / F.col("whole")).alias("max_share"))


def build(toks: DataFrame, n: int = 1, known: list[str] | None = None, tau: tuple[int, int] | None = None, combine: str = "any") -> DataFrame:
    """(term_id, n, term, max_share, n_classes), numbered from 1 in order of the terms. At most classes / tau rows."""
    classes = toks.select("label").distinct().count() if combine == "all" else None
    chosen = select_terms(class_term_freq(toks, n, known), tau or TAU[n], combine, classes).where(F.col("term") != UNKNOWN[1]) if n == 1 else select_terms(class_term_freq(toks, n, known), tau or TAU[n], combine, classes)
    return chosen.select(F.row_number().over(Window.orderBy("term")).alias("term_id"), F.lit(n).alias("n"), "term", "max_share", "n_classes")


def as_list(vocabulary: DataFrame) -> list[str]:
    """The terms, in order; bounded by classes / tau."""
    return [r.term for r in vocabulary.select("term").orderBy("term").collect()]


def cloud(toks: DataFrame, known: list[str], k: int = 50) -> DataFrame:
    """(token, n, share): the most frequent vocabulary tokens without punctuation."""
    counted = toks.select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    total = toks.agg(F.sum(F.size("tokens")).alias("total"))
    return counted.where(F.col("token").isin(known) & F.col("token").rlike(r"^\w+$")).join(F.broadcast(total)).select("token", "n", (F.col("n") / F.col("total")).alias("share")).orderBy(F.desc("n"), "token").limit(k)


def overlap(old: DataFrame, new: DataFrame) -> DataFrame:
    """(n_old, n_new, both, jaccard) of two vocabularies."""
    joined = old.select("term", F.lit(1).alias("o")).join(new.select("term", F.lit(1).alias("w")), "term", "full_outer")
    return joined.agg(F.count("o").alias("n_old"), F.count("w").alias("n_new"), F.count(F.col("o") + F.col("w")).alias("both")).withColumn("jaccard", F.try_divide(F.col("both").cast("double"), F.col("n_old") + F.col("n_new") - F.col("both")))


def unknown_share(toks: DataFrame, known: list[str]) -> DataFrame:
    """(label, share): tokens outside the vocabulary, by class."""
    t = toks.select("label", F.explode(map_unknown(F.col("tokens"), known)).alias("t"))
    return t.groupBy("label").agg((F.count_if(F.col("t") == UNKNOWN[1]) / F.count("*")).alias("share"))
