from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from filekind.llm import mixing


def fill(budget, nodes):
    """Water-filling by repeated rounds: nodes are (name, capacity, weight)."""
    got, open_ = dict.fromkeys((n for n, _, _ in nodes), 0.0), [n for n in nodes if n[2] > 0]
    left = min(budget, sum(c for _, c, w in nodes if w > 0))
    while open_ and left > 1e-9:
        level = left / sum(w for _, _, w in open_)
        full = [n for n in open_ if n[1] - got[n[0]] <= level * n[2]]
        for name, c, w in full or open_:
            take = c - got[name] if full else level * w
            got[name] += take
            left -= take
        open_ = [n for n in open_ if n not in full] if full else []
    return got


def plain(leaves, total, weights, epochs):
    """leaves: {(domain, lang, source): tokens}."""
    def weight(level, name):
        return weights.get(level, {}).get(name, 1.0)

    cap = {k: (v * epochs if all(weight(x, n) > 0 for x, n in zip(mixing.LEVELS, k)) else 0.0) for k, v in leaves.items()}
    out = {}

    def down(prefix, budget):
        depth = len(prefix)
        if depth == 3:
            out[prefix] = budget
            return
        below = defaultdict(float)
        for k, c in cap.items():
            if k[:depth] == prefix:
                below[k[depth]] += c
        for name, b in fill(budget, [(n, c, weight(mixing.LEVELS[depth], n)) for n, c in below.items()]).items():
            down((*prefix, name), b)

    down((), min(total, sum(cap.values())))
    return out


@pytest.mark.parametrize(("total", "weights", "epochs"), [(500, {}, 1), (900, {"domain": {"a": 9.0}}, 1), (1500, {"lang": {"x": 3.0, "y": 0.0}}, 2), (10**9, {}, 3), (0, {}, 1)])
def test_budgets_against_rounds(spark, total, weights, epochs):
    leaves = {("a", "x", "p"): 10, ("a", "x", "q"): 300, ("a", "y", "p"): 40, ("b", "x", "p"): 5, ("b", "z", "r"): 700, ("b", "z", "s"): 90, ("c", "x", "t"): 33}
    df = spark.createDataFrame([(*k, v) for k, v in leaves.items()], "domain string, lang string, source string, tokens long")
    got = {(r.domain, r.lang, r.source): r.budget for r in mixing.budgets(df, F.lit(total), weights, epochs).collect()}
    want = plain(leaves, total, weights, epochs)
    assert all(abs(got[k] - want[k]) < 1.001 for k in leaves) and all(got[k] <= leaves[k] * epochs for k in leaves)


def test_leaves_get_their_prefix(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    chosen, leaves = mixing.mix(docs, epochs=2)
    want = {(r.domain, r.lang, r.source): r for r in leaves.collect()}
    taken, runs = defaultdict(int), defaultdict(list)
    for r in chosen.collect():
        k = (r.domain, r.lang, r.source)
        taken[k] += r.taken
        runs[k, r.epoch].append((r.start, r.tokens, r.taken))
    assert all(taken[k] == r.budget for k, r in want.items())
    for run in runs.values():
        run.sort()
        assert run[0][0] == 0 and all(a + n == b for (a, n, _), (b, _, _) in zip(run, run[1:])) and all(n == t for _, n, t in run[:-1])
    assert any(r.budget > r.tokens for r in want.values()) and any(r.budget < r.tokens for r in want.values())
    again = mixing.mix(docs.repartition(7), epochs=2)[0]
    assert sorted(chosen.collect()) == sorted(again.collect())


def test_kept_documents_are_the_chosen_ones(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for epochs in (1, 2):
        want = sorted(r.doc_id for r in mixing.mix(docs, epochs=epochs)[0].collect())
        kept = mixing.keep_mixed(docs, epochs=epochs)
        assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == want


def test_edges(spark):
    rows = [(1, None, "en", "s1"), (2, "", "en", "s1"), (3, "a b c", None, None), (3, "a b c", None, None), (None, "d e", "en", None), (4, "w " * 20_000, "de", "odd"), (5, "x y", "en", "src99999999999")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").selectExpr("*", "7 tokens", "'q' domain", "1 budget")
    chosen, _ = mixing.mix(df, share=1.0, epochs=1)
    assert sorted((r.doc_id or 0, r.taken) for r in chosen.collect()) == [(0, 2), (3, 3), (3, 3), (4, 20_000), (5, 2)]
    assert mixing.keep_mixed(df, share=1.0, epochs=1).count() == 5
    assert mixing.mix(df.limit(0))[0].count() == 0 and mixing.keep_mixed(df.limit(0)).count() == 0
