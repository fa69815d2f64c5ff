"""Confusion between classes: rates, co-occurrence in the likeliest classes, related pairs and groups.

Predictions have file_id, label, pred and top (class and p, likeliest first).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BUILDERS = ("components", "stars", "cliques", "mutual", "per_statistic")


def t_matrix(pred: DataFrame) -> DataFrame:
    """(i, j, t): share of the files of class i that are predicted as j."""
    n = pred.groupBy(F.col("label").alias("i"), F.col("pred").alias("j")).agg(F.count("*").alias("n"))
    return n.select("i", "j", (F.col("n") / F.sum("n").over(Window.partitionBy("i"))).alias("t"))


def top_k(pred: DataFrame, k: int = 5) -> DataFrame:
    """The k likeliest classes, renormalised to sum to one."""
    first = F.slice("top", 1, k)
    total = F.aggregate(first, F.lit(0.0), lambda a, x: a + x["p"])
    return pred.select("file_id", "label", "pred", F.transform(first, lambda x: F.struct(x["class"].alias("class"), (x["p"] / total).alias("q"))).alias("top"))


def s_matrix(pred: DataFrame, k: int = 5) -> DataFrame:
    """(i, j, s): renormalised probability of j over the files predicted as i, per such file."""
    rows = top_k(pred, k).select(F.col("pred").alias("i"), F.explode("top").alias("x")).groupBy("i", F.col("x.class").alias("j")).agg(F.sum("x.q").alias("mass"))
    size = pred.groupBy(F.col("pred").alias("i")).agg(F.count("*").alias("n"))
    return rows.join(F.broadcast(size), "i").select("i", "j", (F.col("mass") / F.col("n")).alias("s"))  # as many rows as classes


def directed(t: DataFrame, s: DataFrame, tau_t: float = 0.05, tau_s: float = 0.02) -> DataFrame:
    """(i, j, t, s, by_t, by_s): ordered pairs of different classes over either threshold."""
    nothing = F.lit(None).cast("double")
    both = t.select("i", "j", "t", nothing.alias("s")).unionByName(s.select("i", "j", nothing.alias("t"), "s")).where("i <> j")
    one = both.groupBy("i", "j").agg(F.coalesce(F.max("t"), F.lit(0.0)).alias("t"), F.coalesce(F.max("s"), F.lit(0.0)).alias("s"))
    return one.withColumn("by_t", F.round("t", 12) > tau_t).withColumn("by_s", F.round("s", 12) > tau_s).where("by_t or by_s")


def related(t: DataFrame, s: DataFrame, tau_t: float = 0.05, tau_s: float = 0.02) -> DataFrame:
    """(a, b, t_max, s_max, via): unordered pairs over either threshold, and which one said so."""
    pairs = directed(t, s, tau_t, tau_s).groupBy(F.least("i", "j").alias("a"), F.greatest("i", "j").alias("b"))
    via = F.when(F.bool_or("by_t") & F.bool_or("by_s"), "both").when(F.bool_or("by_t"), "t").otherwise("s")
    return pairs.agg(F.max("t").alias("t_max"), F.max("s").alias("s_max"), via.alias("via"))


def _components(pairs: set[tuple[str, str]]) -> set[frozenset]:
    root: dict[str, str] = {}

    def find(x: str) -> str:
        while root.setdefault(x, x) != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in pairs:
        root[find(a)] = find(b)
    out: dict[str, set] = {}
    for x in list(root):
        out.setdefault(find(x), set()).add(x)
    return {frozenset(v) for v in out.values()}


def _cliques(pairs: set[tuple[str, str]]) -> set[frozenset]:
    near: dict[str, set] = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    found = set()

    def grow(inside: set, may: set, out: set) -> None:
        if not may and not out:
            found.add(frozenset(inside))
            return
        pivot = max(may | out, key=lambda x: len(near[x] & may))
        for x in sorted(may - near[pivot]):
            grow(inside | {x}, may & near[x], out & near[x])
            may, out = may - {x}, out | {x}

    grow(set(), set(near), set())
    return {c for c in found if len(c) > 1}


def groups(t: DataFrame, s: DataFrame, builder: str = "components", tau_t: float = 0.05, tau_s: float = 0.02) -> DataFrame:
    """(group_id, members, builder). Classes are few (their square is at most a million rows), so groups are built from the collected pairs.

    components: classes joined by related pairs; stars: a class with all it points to; cliques: maximal sets related pairwise; mutual: components of the
    pairs that hold in both directions; per_statistic: components by each statistic alone. Stars and per_statistic can nest.
    """
    if builder not in BUILDERS:
        raise ValueError(f"builder {builder!r}: one of {BUILDERS}")
    spark = t.sparkSession
    rows = directed(t, s, tau_t, tau_s).collect()
    arrows = {(r.i, r.j) for r in rows}
    if builder == "components":
        sets = _components(arrows)
    elif builder == "stars":
        sets = {frozenset({i, *(b for a, b in arrows if a == i)}) for i, _ in arrows}
    elif builder == "cliques":
        sets = _cliques(arrows)
    elif builder == "mutual":
        sets = _components({(a, b) for a, b in arrows if (b, a) in arrows})
    else:
        sets = _components({(r.i, r.j) for r in rows if r.by_t}) | _components({(r.i, r.j) for r in rows if r.by_s})
    out = [(n, list(m), builder) for n, m in enumerate(sorted(sorted(x) for x in sets))]
    return spark.createDataFrame(out, "group_id int, members array<string>, builder string")


def spread_components(pairs: DataFrame, rounds: int = 30) -> DataFrame:
    """(label, root): components of a pair table too large for the driver, by passing on the smallest label."""
    from ..store import keep

    both = pairs.select("a", "b").union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = keep(both)
    labels = keep(both.select(F.col("a").alias("label")).distinct().withColumn("root", F.col("label")))
    for _ in range(rounds):
        told = both.join(labels.withColumnRenamed("label", "b"), "b").groupBy(F.col("a").alias("label")).agg(F.min("root").alias("near"))
        nxt = labels.join(told, "label").select("label", F.least("root", "near").alias("root"))
        # Follow the root's own root, which halves the distance left.
        jump = nxt.select(F.col("label").alias("root"), F.col("root").alias("top"))
        nxt = keep(nxt.join(jump, "root", "left").select("label", F.least("root", F.coalesce("top", "root")).alias("root")))
        if not nxt.exceptAll(labels).take(1):
            return nxt
        labels = nxt
    raise RuntimeError("labels did not settle")


def clean_classes(classes: DataFrame, pairs: DataFrame) -> DataFrame:
    """Classes in no related pair."""
    taken = pairs.select(F.col("a").alias("label")).union(pairs.select(F.col("b").alias("label")))
    return classes.select("label").distinct().join(taken, "label", "left_anti")


def merge_labels(pred: DataFrame, alias: dict[str, str]) -> DataFrame:
    """Predictions with labels and predictions renamed, for the twins that one name should cover."""
    names = F.create_map(*(F.lit(x) for kv in alias.items() for x in kv)) if alias else None

    def named(c: str):
        return F.coalesce(F.try_element_at(names, F.col(c)), F.col(c)) if alias else F.col(c)

    return pred.withColumn("label", named("label")).withColumn("pred", named("pred"))


