import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from filekind.llm import toxicity as tox


def unit(rng, terms):
    t = np.array(sorted(rng.sample(range(terms), rng.randint(0, 6))), np.int64)
    w = np.array([rng.choice([1.0, 2.0, 2.0, 3.5]) for _ in t])
    return t, w / np.sqrt((w * w).sum()) if len(t) else w


@pytest.mark.parametrize("k", [1, 7, 25, 1000])
def test_block_max_equals_a_full_scan(k):
    rng = random.Random(k)
    vectors = [unit(rng, 40) for _ in range(700)]
    dense = np.zeros((700, 40))
    for i, (t, w) in enumerate(vectors):
        dense[i, t] = w
    index, opened = tox.BlockMax(vectors, 40), 0
    for _ in range(60):
        t, w = unit(rng, 40)
        if not len(t):
            continue
        cosine = np.round(dense[:, t] @ w, 12)
        want = [i for i in np.lexsort((np.arange(700), -cosine)) if cosine[i] > 0][:k]
        near, got, n = index.search(t, w, k)
        opened += n
        assert near.tolist() == want and np.allclose(got, cosine[want])
    if k == 1:
        assert opened < 0.8 * 60 * index.blocks


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    got = {r.doc_id: r for r in tox.op5_nearest_examples(spark, sf).collect()}
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert set(got) == set(docs)
    assert all(r.held_out == (zlib.crc32(str(d).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for d, r in got.items())
    seen = [(labels[d], got[d].predicted) for d in labels if got[d].held_out]
    assert sum(a == b for a, b in seen) / len(seen) > 0.9
    assert all(labels.get(e) is not None for r in got.values() for e in r.evidence)
    assert any(r.evidence and r.predicted for r in got.values())


def test_scores_are_calibrated(spark):
    sf = "/root/testdata/sf0.1"
    got = {r.doc_id: r for r in tox.op5_nearest_examples(spark, sf).collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    held = [(got[d].score, y) for d, y in labels.items() if got[d].held_out]
    assert abs(np.mean([s for s, _ in held]) - np.mean([y for _, y in held])) < 0.03


def test_edges(spark):
    docs = [(i, ("you scum and trash " if i % 3 == 0 else "a calm day outside ") + f"w{i}") for i in range(60)] + [(None, "scum"), (100, None), (101, ""), (102, "unseen words only"), (103, "Scum!!! " * 30_000), (0, "you scum and trash w0")]
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 score", "'x' label")
    labelled = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(60)] + [(None, 1), (5, None), (6, 0), (999, 1)], "doc_id long, label int")
    model = tox.fit(df, labelled)
    told = tox.scored(df, model)
    assert told.columns == [*df.columns, "_score", "_evidence", "_cosines"] and {r.score for r in told.collect()} == {1}
    got = told.selectExpr("doc_id", "_score score", "_evidence evidence").collect()
    by = {r.doc_id: r.score for r in got}
    assert len(got) == len(docs) and by[None] > 0.5 and by[103] > 0.5 and by[3] > 0.5
    assert by[100] == by[101] == by[102] < 0.5 and by[1] < 0.5
    empty = tox.fit(df, labelled.limit(0))
    assert {r.score for r in tox.scored(df.drop("score"), empty).collect()} == {0.0}
    assert tox.scored(df.limit(0).drop("score"), model).count() == 0
    assert len(tox.fit(df, labelled, most_examples=10).ids) <= 10


def test_every_text_is_searched_with_its_whole_vector(spark, sf):
    """Plain words that no test ties to the label find their examples: cosines of a full scan over all terms of the examples."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in tox.op5_nearest_examples(spark, sf).collect()}
    text = {r.doc_id: r.text for r in docs.collect()}
    examples = [r.doc_id for r in tox.training_labels(spark, sf).where("label IS NOT NULL").collect() if r.doc_id in text]
    counts = {d: Counter(tox.LETTERS.findall((t or "").lower())) for d, t in text.items()}
    df = Counter(w for c in counts.values() for w in c)
    space = {w for e in examples for w in counts[e]}

    def unit(d):
        v = {w: (1 + math.log(n)) * (math.log((1 + len(text)) / (1 + df[w])) + 1) for w, n in counts[d].items() if w in space}
        size = math.sqrt(sum(x * x for x in v.values()))
        return {w: x / size for w, x in v.items()}

    units = {d: unit(d) for d in text}
    for d, r in got.items():
        want = sorted((sum(x * units[e].get(w, 0.0) for w, x in units[d].items()) for e in examples), reverse=True)[:5]
        assert np.allclose(r.cosines, [c for c in want if c > 1e-12], atol=1e-9), d
    assert sum(bool(r.evidence) for r in got.values()) > 0.95 * sum(bool(t) for t in text.values())
    assert len({r.score for r in got.values()}) > 1 and all(r.evidence for d, r in got.items() if units[d])


def test_scores_against_brute_force(spark):
    """The whole query against dense matrices: all cosines, both votes, and the three tables by plain pooling."""
    sf = "/root/testdata/sf0.01"
    text = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r.doc_id: r.label for r in tox.training_labels(spark, sf).where("label IS NOT NULL").collect() if r.doc_id in text}
    ids, examples = sorted(text), sorted(labels)
    counts = {d: Counter(tox.LETTERS.findall(t.lower())) for d, t in text.items()}
    df = Counter(w for c in counts.values() for w in c)
    space = sorted({w for e in examples for w in counts[e]})
    at = {w: i for i, w in enumerate(space)}
    y = np.array([labels[e] for e in examples], float)

    def rows(of):
        m = np.zeros((len(of), len(space)))
        for r, d in enumerate(of):
            for w, n in counts[d].items():
                if w in at:
                    m[r, at[w]] = (1 + math.log(n)) * (math.log((1 + len(text)) / (1 + df[w])) + 1)
        return m / np.maximum(np.sqrt((m * m).sum(axis=1, keepdims=True)), 1e-300)

    every, mine = rows(ids), rows(examples)
    e, p = float(len(examples)), y.sum()
    held = [(j, m, a) for j in range(len(space)) if (m := (mine[:, j] > 0).sum()) >= tox.SUPPORT for a in [float(y[mine[:, j] > 0].sum())]]

    def term(x, z):
        return x * math.log(x / z) if x > 0 else 0.0

    def strength(m, a):
        return 2 * (term(a, m * p / e) + term(m - a, m * (e - p) / e) + term(p - a, (e - m) * p / e) + term(e - m - p + a, (e - m) * (e - p) / e))

    telling = [j for j, m, a in held if strength(float(m), a) >= 2 * math.log(len(held) / tox.ALPHA)]
    assert telling

    def narrow(m):
        m = m[:, telling]
        return m / np.maximum(np.sqrt((m * m).sum(axis=1, keepdims=True)), 1e-300)

    def vote(cosines, otherwise, leave=None):
        c = np.round(cosines, 12)
        order = [i for i in np.lexsort((np.arange(len(c)), -c)) if c[i] > 0]
        if leave is not None:
            order = [i for i in order[: tox.NEIGHBOURS + 1] if i != leave]
        order = order[: tox.NEIGHBOURS]
        return float((c[order] ** 2 * y[order]).sum() / (c[order] ** 2).sum()) if order else otherwise

    def table(votes, truth):
        values = [((truth[np.round(votes * tox.STEPS) == s].sum() + s / tox.STEPS), (np.round(votes * tox.STEPS) == s).sum() + 1) for s in range(tox.STEPS + 1)]
        # The monotone fit: at each step the largest over starts of the smallest mean over ends.
        return [max(min(sum(v[0] for v in values[a : b + 1]) / sum(v[1] for v in values[a : b + 1]) for b in range(i, len(values))) for a in range(i + 1)) for i in range(len(values))]

    def read(v, t):
        return np.interp(np.asarray(v) * tox.STEPS, np.arange(len(t)), t)

    def odds(x):
        x = np.clip(x, 1e-3, 1 - 1e-3)
        return np.log(x / (1 - x))

    prior = y.mean()
    bare = (mine[:, telling] > 0).sum(axis=1) == 0
    base = (y[bare].sum() + prior) / (bare.sum() + 1)
    near, told = mine @ mine.T, narrow(mine) @ narrow(mine).T
    first = np.array([vote(near[i], prior, i) for i in range(len(examples))])
    second = np.array([vote(told[i], prior, i) for i in range(len(examples))])
    filled = (mine > 0).any(axis=1)
    one, two = table(first[filled], y[filled]), table(second[~bare], y[~bare])

    def joint(a, b):
        return 1 / (1 + np.exp(-(odds(read(a, one)) + odds(b) - odds(prior))))

    last = table(joint(first, np.where(bare, base, read(second, two)))[filled], y[filled])
    near, told = every @ mine.T, narrow(every) @ narrow(mine).T
    got = {r.doc_id: r.score for r in tox.op5_nearest_examples(spark, sf).collect()}
    for i, d in enumerate(ids):
        if not every[i].any():
            want = base
        else:
            b = read(vote(told[i], base), two) if (every[i, telling] > 0).any() else base
            want = read(joint(vote(near[i], prior), b), last)
        assert abs(got[d] - want) < 1e-6, (d, got[d], want)


def test_words_are_those_of_the_expression(monkeypatch):
    """By a table of bytes, the expression being left for texts with other characters than the first 256."""
    rng = random.Random(5)
    every = [chr(i) for i in range(256)]
    texts = ["", "".join(every), "Ä-ß_µ²x9ÿ\x85\xa0Ünd 1½", *("".join(rng.choices(every, k=300)) for _ in range(200))]
    other = ["Ελλάς ΟΔΟΣ İx naïve", "a—b “c” d", *(t + "Ж" for t in texts)]
    want = [tox.LETTERS.findall(t.lower()) for t in texts + other]
    assert [tox.words(t) for t in texts + other] == want
    monkeypatch.setattr(tox, "LETTERS", None)
    assert [tox.words(t) for t in texts] == want[: len(texts)]
