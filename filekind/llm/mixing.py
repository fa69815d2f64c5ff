"""Mixing sources to target weights by hierarchical budgeting.

The tree has domains, languages within a domain, and sources within a language. A node's capacity is what its leaves hold, times the
epochs allowed. Budgets run from the root down: children share their parent's budget by weight, a child takes no
more than its capacity, and what it cannot take goes to its siblings by their weights. As a child's capacity is that of its
whole subtree, a shortage is made up among siblings first and reaches the next level only when all of them are full.
The water level of each family is found in closed form with windows over the (small) table of nodes.

A leaf then takes whole seeded epochs of its documents, and of the last epoch the prefix, in the epoch's own seeded order, that
reaches its budget; the last document is cut to the tokens still wanted. Positions in an epoch come from slice totals, so no task holds a leaf.

Defined cases: null texts hold no tokens and are in no mix; null languages or sources are nodes of their own; a node whose
weight is not given has weight 1, and one of weight 0 gets nothing; ties in an epoch's order go to the smaller id; rows that repeat an id
are separate documents; an empty table gives an empty result; further columns are left alone.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, clean_text, running_before, shuffle_width, sized, stash, table

LEVELS = ("domain", "lang", "source")
#: Weights of nodes by level; others have weight 1.
WEIGHTS: Mapping[str, Mapping[str, float]] = {"domain": {"d0": 3.0, "d1": 2.0}, "lang": {"en": 5.0, "de": 2.0, "fr": 2.0}}
#: Share of all tokens that the mix holds, and the epochs that a leaf may give.
SHARE, EPOCHS, SEED = 0.6, 2, 42
DOMAINS = 4


def domain_of(source: Column) -> Column:
    """The domain of a source: its trailing number modulo DOMAINS; names without one are in the first."""
    number = F.coalesce(F.expr("try_cast(regexp_extract(source, '([0-9]{1,9})$', 1) AS int)"), F.lit(0))
    return F.concat(F.lit("d"), (number % DOMAINS).cast("string"))


def _weight(level: str, weights: Mapping[str, Mapping[str, float]]) -> Column:
    given = weights.get(level, {})
    out = F.lit(1.0)
    for name, w in given.items():
        out = F.when(F.col(level) == name, F.lit(float(w))).otherwise(out)
    return out


def budgets(leaves: DataFrame, total: Column, weights: Mapping[str, Mapping[str, float]] = WEIGHTS, epochs: int = EPOCHS, levels: tuple[str, ...] = LEVELS, size: int = 0) -> DataFrame:
    """leaves: the levels and `tokens`; size: how many there are, if that is known to be many. Adds `budget`, in tokens (a whole number), no more than tokens x epochs."""
    names = [f"__{c}" for c in levels]
    # Null names are nodes; windows and joins below see them as a name that no text has.
    nodes = leaves.select(*leaves.columns, *(F.coalesce(F.col(c), F.lit("\x00")).alias(n) for c, n in zip(levels, names, strict=True)), F.when(sum((_weight(c, weights) > 0).cast("int") for c in levels) == len(levels), (F.col("tokens") * epochs).cast("double")).otherwise(0.0).alias("__cap"))
    nodes = nodes.withColumn("__b0", F.least(total.cast("double"), F.sum("__cap").over(Window.partitionBy())))
    for depth, level in enumerate(levels):
        above, here = names[:depth], names[: depth + 1]
        family = nodes.groupBy(*here, F.col(f"__b{depth}").alias("__b")).agg(F.sum("__cap").alias("__c"), F.max(_weight(level, weights)).alias("__w"))
        fill = F.when(F.col("__w") > 0, F.col("__c") / F.col("__w")).otherwise(0.0)
        by_fill = Window.partitionBy(*above).orderBy("__fill", names[depth])
        upto, beyond = by_fill.rowsBetween(Window.unboundedPreceding, 0), by_fill.rowsBetween(1, Window.unboundedFollowing)
        family = family.withColumn("__fill", fill).withColumn("__full_c", F.sum("__c").over(upto)).withColumn("__rest_w", F.coalesce(F.sum("__w").over(beyond), F.lit(0.0)))
        # Full are the children that would be filled with all later ones at the same level.
        full = F.col("__full_c") + F.col("__fill") * F.col("__rest_w") <= F.col("__b")
        whole = Window.partitionBy(*above)
        family = family.withColumn("__full", full)
        left = F.col("__b") - F.sum(F.when(F.col("__full"), F.col("__c")).otherwise(0.0)).over(whole)
        open_w = F.sum(F.when(F.col("__full"), 0.0).otherwise(F.col("__w"))).over(whole)
        share = F.when(F.col("__full"), F.col("__c")).otherwise(F.least(F.col("__c"), left * F.col("__w") / F.nullif(open_w, F.lit(0.0))))
        family = family.select(*here, share.alias(f"__b{depth + 1}"))
        nodes = nodes.join(sized(family, size), here)  # as many rows as the tree has nodes at this level
    return nodes.select(*leaves.columns, F.floor(F.col(f"__b{len(levels)}") + 1e-6).cast("long").alias("budget"))


def _order_key(epoch: Column, seed: int) -> Column:
    """A seeded order of an epoch: 60 bits of a hash that SQL engines share, uniform whatever the ids are."""
    name = F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(F.col("__id").cast("string"), F.lit("")))
    return F.conv(F.substring(F.md5(name), 1, 15), 16, 10).cast("long")


def _prepared(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return df.select(
        F.col(id_col).cast("long").alias("__id"), domain_of(F.col("source")).alias("domain"), "lang", "source",
        F.regexp_count(clean_text(text_col), F.lit(WORD)).cast("long").alias("tokens"),
    ).where("tokens > 0")


def mix(df: DataFrame, share: float = SHARE, weights: Mapping[str, Mapping[str, float]] = WEIGHTS, epochs: int = EPOCHS, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(chosen, leaves). chosen: doc_id, domain, lang, source, epoch, start, tokens, taken for each document an epoch takes;
    leaves: the levels, tokens, docs and budget."""
    docs = stash(_prepared(df, id_col, text_col))
    leaves = stash(docs.groupBy(*LEVELS).agg(F.sum("tokens").alias("tokens"), F.count("*").alias("docs")))
    size, rows = leaves.agg(F.count("*"), F.coalesce(F.sum("docs"), F.lit(0))).first()
    leaves = stash(budgets(leaves, F.floor(F.sum("tokens").over(Window.partitionBy()) * share), weights, epochs, size=size))
    most = max(1, rows // (4 * shuffle_width(df.sparkSession)))
    each = leaves.select(*(F.coalesce(c, F.lit("\x00")).alias(f"__{c}") for c in LEVELS), F.col("tokens").alias("__all"), "budget", F.ceil(F.col("docs") / most).alias("__slices"))
    keyed = docs.select("*", *(F.coalesce(c, F.lit("\x00")).alias(f"__{c}") for c in LEVELS)).join(sized(each, size), [f"__{c}" for c in LEVELS])
    # Epochs are numbered from 0; those before the last are whole.
    told = keyed.where("budget > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.ceil(F.col("budget") / F.col("__all")).cast("int") - 1)))
    told = told.withColumn("__key", _order_key(F.col("epoch"), seed)).withColumn("__slice", F.floor(F.col("__key") / F.lit(float(1 << 60)) * F.col("__slices")))
    placed = running_before(told, ["__domain", "__lang", "__source", "epoch"], "__slice", [F.col("__key"), F.col("__id"), F.col("tokens")], {"start": "tokens"}, epochs * (size + 4 * shuffle_width(df.sparkSession)))
    wanted = F.col("budget") - F.col("epoch") * F.col("__all")
    taken = F.least("tokens", wanted - F.col("start"))
    chosen = placed.where(wanted > F.col("start")).select(F.col("__id").alias("doc_id"), *LEVELS, "epoch", F.col("start").cast("long").alias("start"), "tokens", taken.cast("long").alias("taken"))
    return chosen, leaves


def keep_mixed(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """The documents of the mix, with the columns of df: one row for each epoch that takes a document.

    The order of an epoch makes each leaf's choice a prefix, so the last order key that a leaf reaches is
    all that travels: documents are filtered where they are read, and their texts do not move.
    """
    chosen, _ = mix(df, id_col=id_col, text_col=text_col, **how)
    seed = how.get("seed", SEED)
    keyed = chosen.select(*(F.coalesce(c, F.lit("\x00")).alias(f"__{c}") for c in LEVELS), F.col("epoch").alias("__epoch"), F.col("doc_id").alias("__id"), F.col("tokens").alias("__n")).withColumn("__key", _order_key(F.col("__epoch"), seed))
    last = keyed.groupBy("__domain", "__lang", "__source", "__epoch").agg(F.max(F.struct("__key", "__id", "__n")).alias("__last"))
    cuts = stash(last)  # one row for each leaf and epoch
    own = df.columns
    told = df.withColumns({
        "__id": F.col(id_col).cast("long"), "__domain": domain_of(F.col("source")), "__lang": F.coalesce("lang", F.lit("\x00")),
        "__source": F.coalesce("source", F.lit("\x00")), "__n": F.regexp_count(clean_text(text_col), F.lit(WORD)).cast("long"),
    }).where("__n > 0")
    met = told.join(sized(cuts, cuts.count()), ["__domain", "__lang", "__source"]).withColumn("__key", _order_key(F.col("__epoch"), seed))
    return met.where(F.struct("__key", "__id", "__n") <= F.col("__last")).select(*own)


def op2_hierarchical_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"))[0]


def _oracle(share: float = SHARE, epochs: int = EPOCHS, seed: int = SEED) -> str:
    """SQL for op2: each level repeats the water-filling step over its families."""

    def weight(level: str) -> str:
        cases = " ".join(f"WHEN {level} = '{k}' THEN {float(w)}" for k, w in WEIGHTS.get(level, {}).items())
        return f"CASE {cases} ELSE 1.0 END" if cases else "1.0"

    steps, before = [], "b0"
    for i, level in enumerate(LEVELS):
        keys = LEVELS[: i + 1]
        part = f"PARTITION BY {', '.join(LEVELS[:i])}" if i else ""
        steps.append(f"""
f{i} AS (SELECT {", ".join(keys)}, any_value(b) AS b, sum(cap) AS c, max({weight(level)}) AS w FROM n{i} GROUP BY {", ".join(keys)}),
g{i} AS (SELECT *, sum(c) OVER ({part} ORDER BY c / w, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)
                   + c / w * coalesce(sum(w) OVER ({part} ORDER BY c / w, {level} ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) <= b AS closed FROM f{i}),
h{i} AS (SELECT *, b - sum(CASE WHEN closed THEN c ELSE 0 END) OVER ({part}) AS rest, sum(CASE WHEN closed THEN 0 ELSE w END) OVER ({part}) AS open_w FROM g{i}),
n{i + 1} AS (SELECT n.* EXCLUDE (b), CASE WHEN closed THEN c ELSE least(c, rest * w / open_w) END AS b FROM n{i} n JOIN h{i} USING ({", ".join(keys)}))""")
    return f"""
WITH d AS (SELECT doc_id, 'd' || (coalesce(try_cast(nullif(regexp_extract(source, '([0-9]{{1,9}})$', 1), '') AS INT), 0) % {DOMAINS}) AS domain, lang, source,
                  len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS tokens FROM documents),
k AS (SELECT * FROM d WHERE tokens > 0),
l AS (SELECT domain, lang, source, sum(tokens)::BIGINT AS total, (sum(tokens) * {epochs})::DOUBLE AS cap FROM k GROUP BY ALL),
n0 AS (SELECT *, least(floor(sum(total) OVER () * {share}::DOUBLE), sum(cap) OVER ()) AS b FROM l),{",".join(steps)},
e AS (SELECT k.*, total, floor(b + 1e-6)::BIGINT AS budget, epoch::INT AS epoch FROM k JOIN n{len(LEVELS)} USING (domain, lang, source), range({epochs}) r(epoch)),
o AS (SELECT *, coalesce(sum(tokens) OVER (PARTITION BY domain, lang, source, epoch ORDER BY ('0x' || substr(md5('{seed}:' || epoch || ':' || doc_id), 1, 15))::BIGINT, doc_id
                ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS "start" FROM e)
SELECT doc_id, domain, lang, source, epoch, "start", tokens, least(tokens, budget - epoch * total - "start")::BIGINT AS taken
FROM o WHERE budget - epoch * total > "start"
"""


ORACLE_SQL = _oracle()
