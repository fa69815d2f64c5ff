from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from filekind.operators import mlp, nb, score, sequence, splits, tiering, tune
from filekind.operators.features import Config, counter, learn_space, vectorize, vectorize_sql
from filekind.plans.capacity import capacity
from filekind.queries.workloads import training
from filekind.sources import corpus


@pytest.fixture(scope="module")
def t1(spark, sf):
    return splits.assign(corpus.prose(spark, sf)).cache()


@pytest.fixture(scope="module")
def space(t1):
    return learn_space(training(t1).where("split = 'vocab'"))


@pytest.mark.parametrize(("orders", "denom"), [((1, 2), "tokens"), ((1,), "tokens"), ((1, 2, 3), "ngrams")])
def test_both_vectorizers_agree(t1, orders, denom):
    sp = learn_space(training(t1).where("split = 'vocab'"), Config(orders=orders, denom=denom))
    rows = t1.limit(40)
    long = {(r.file_id, r.idx): r.freq for r in vectorize_sql(rows, sp).collect()}
    csr = {(r.file_id, i): f for r in vectorize(rows, sp).collect() for i, f in zip(r.indices, r.freqs)}
    assert set(long) == set(csr) and all(abs(long[k] - csr[k]) < 1e-6 for k in long)
    mass = Counter()
    for (f, i), v in long.items():
        mass[f] += v if i <= len(sp.terms[1]) else 0
    assert all(abs(m - 1) < 1e-9 for m in mass.values())


def test_batch_counts_equal_single_counts(t1):
    import pyarrow as pa

    from filekind.functions.text import tokens_of
    from filekind.operators.features import batch_counter, counted

    for orders, denom in (((1,), "tokens"), ((1, 2), "tokens"), ((1, 2, 3), "ngrams")):
        sp = learn_space(training(t1).where("split = 'vocab'"), Config(orders=orders, denom=denom))
        lists = [r[0] for r in t1.limit(60).select(tokens_of(F.col("content"))).collect()] + [[], ["x"], ["the", "the"], []]
        one, many = counter(sp), counted(pa.array(lists, pa.list_(pa.string())).slice(1), batch_counter(sp))
        for got, tokens in zip(many, lists[1:], strict=True):
            want = one(tokens)
            assert got[0].tolist() == want[0].tolist() and np.allclose(got[1], want[1])


def test_empty_files_are_zero_vectors(spark, space):
    df = spark.createDataFrame([("a", "", "x"), ("b", None, "x"), ("c", "one", "x")], "file_id string, content string, label string")
    got = {r.file_id: r for r in vectorize(df, space).collect()}
    assert got["a"].indices == got["b"].indices == [] and got["c"].n_tokens == 1 and got["c"].freqs == [1.0]
    assert {r.file_id for r in vectorize(df, space, trimmed=True).collect() if r.indices} == set()


def test_windows_of_long_files(spark):
    from filekind.operators.features import windows

    df = spark.createDataFrame([("abcdefghijklmnopqrstuvwxyz",), ("short",), (None,)], "s string")
    assert [r[0] for r in df.select(windows(F.col("s"), 9)).collect()] == ["abc\nlmn\nxyz", "short", None]


def test_unknowns_can_leave_ngrams(t1):
    sp = learn_space(training(t1).where("split = 'vocab'"), Config(unknown_in_ngrams="drop"))
    assert not any("<unk>" in t for t in sp.terms[2]) and sp.terms[2]


def test_naive_bayes_by_hand(t1, space):
    train = training(t1).where("split = 'train'").cache()
    model = nb.fit(train, space)
    count = counter(space)
    from filekind.functions.text import tokens_of, trim

    sums = {c: np.zeros(space.size) for c in model.classes}
    for r in train.select("label", trim(tokens_of(F.col("content"))).alias("t")).collect():
        i, f = count(r.t)
        sums[r.label][i] += np.round(f * len(r.t))
    for j, c in enumerate(model.classes):
        want = np.log((sums[c] + 1) / (sums[c].sum() + space.size))
        assert np.allclose(model.weights[:, j], want)
    test = t1.where("split = 'test'")
    pred = score.predict(test, model, space)
    rows = pred.collect()
    assert sum(r.label == r.pred for r in rows) / len(rows) > 0.65
    assert all(abs(sum(x.p for x in r.top) - 1) < 1e-9 and r.top[0]["class"] == r.pred for r in rows)
    short = score.snippets(test, model, space, 5, "tail").collect()
    assert len(short) == len(rows)


def test_gradient_against_differences():
    rng = np.random.default_rng(1)
    net = mlp.start(7, ["a", "b", "c"], mlp.Spec(hidden=(6, 5)), np.float64)
    x, y = rng.random((9, 7)), rng.integers(0, 3, 9)
    grads, _ = mlp.gradient(net, x, y)
    params = [p for wb in zip(net.weights, net.biases) for p in wb]
    for p, g in zip(params, grads):
        for at in list(np.ndindex(p.shape))[::3]:
            kept, step = p[at], 1e-6
            p[at] = kept + step
            up = mlp.gradient(net, x, y)[1] / 9
            p[at] = kept - step
            down = mlp.gradient(net, x, y)[1] / 9
            p[at] = kept
            assert abs((up - down) / (2 * step) - g[at]) < 1e-6


def test_sparse_first_layer_equals_dense():
    net = mlp.start(20, ["a", "b"], mlp.Spec(hidden=(8,)))
    rng = np.random.default_rng(2)
    rows = [(np.sort(rng.choice(20, n, replace=False)), rng.random(n).astype(np.float32)) for n in (0, 3, 20, 0, 1)] * 40
    assert np.allclose(net.first(rows), mlp.dense(rows, 20) @ net.weights[0] + net.biases[0], atol=1e-6)


SPEC = mlp.Spec(hidden=(16, 12), dropout=0.1, lr=5e-3, epochs=12, batch=16)


@pytest.mark.parametrize("mode", ["local", "average", "sync"])
def test_training_modes_learn(t1, space, mode):
    train = vectorize(training(t1).where("split in ('train', 'vocab')"), space, True).repartition(2).cache()
    val = vectorize(t1.where("split = 'val'"), space).cache()
    net = mlp.fit(train, val, space.size, SPEC, mode)
    first, last = net.history[0], net.history[-1]
    assert last["train_loss"] < first["train_loss"]
    again = mlp.fit(train, val, space.size, SPEC, mode) if mode == "local" else net
    assert all((a == b).all() for a, b in zip(net.weights, again.weights))


def test_sync_does_not_depend_on_partitions(t1, space):
    train = vectorize(training(t1).where("split = 'train'"), space, True).cache()
    net = mlp.start(space.size, ["de", "en", "es", "fr"], SPEC)
    one, four = (mlp.sync_gradient(train.repartition(k), net, space.size) for k in (1, 4))
    assert abs(one[1] - four[1]) < 1e-6 and all(np.allclose(a, b, atol=1e-6) for a, b in zip(one[0], four[0]))
    spec = mlp.Spec(hidden=SPEC.hidden, dropout=0.5, steps=3)  # batches and masks follow names
    parts = [[mlp.sync_gradient(train.repartition(k), net, space.size, spec, 2, step) for step in range(3)] for k in (1, 4)]
    assert sum(n for _, _, n in parts[0]) == train.count()
    for a, b in zip(*parts):
        assert a[2] == b[2] and abs(a[1] - b[1]) < 1e-6 and all(np.allclose(x, y, atol=1e-6) for x, y in zip(a[0], b[0]))
    masks = mlp.masks_of(["f1", "f2"], [4000], spec, 0)[0]
    assert abs((masks >= 0.5).mean() - 0.5) < 0.03 and (mlp.masks_of(["f2"], [4000], spec, 0)[0][0] == masks[1]).all() and (mlp.masks_of(["f2"], [4000], spec, 1)[0][0] != masks[1]).any()


def test_distributed_validation_equals_a_local_one(t1, space):
    val = vectorize(t1.where("split = 'val'"), space)
    net = mlp.start(space.size, ["de", "en", "fr"], SPEC)
    rows, y, _ = mlp.collected(val, net.classes)
    loss, accuracy, n = mlp.judge_all(net, val.repartition(3))
    assert n == len(y) and np.allclose((loss, accuracy), mlp.judge(net, rows, y))
    assert mlp.judge_all(net, val.limit(0))[2] == 0


def test_a_train_set_does_not_lie_in_the_driver_s_memory(spark):
    import tracemalloc

    n, wide = 60_000, 100
    indices = F.when(F.col("id") % 7 == 0, F.array().cast("array<int>")).otherwise(F.sequence(F.lit(0), F.lit(wide - 1)))
    vectors = spark.range(n).select(F.concat(F.lit("f"), "id").alias("file_id"), F.concat(F.lit("c"), F.col("id") % 3).alias("label"), indices.alias("indices"), F.col("id").alias("id"))
    vectors = vectors.withColumn("freqs", F.transform("indices", lambda i: ((F.col("id") + i) / n).cast("float"))).repartition(5)
    tracemalloc.start()
    rows, y, classes = mlp.collected(vectors)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < n * wide * 8 * 6 // 7  # the bytes of the numbers alone
    order = sorted(range(n), key=lambda i: f"f{i}")
    assert classes == ["c0", "c1", "c2"] and len(rows) == n and (y == np.array(order) % 3).all()
    for at in (*range(0, n, 997), n - 1):
        i = order[at]
        want = np.arange(wide if i % 7 else 0)
        assert (rows[at][0] == want).all() and np.allclose(rows[at][1], (i + want) / n) and len(rows[at][0]) == len(want)


def test_stored_rows_train_as_rows_in_memory(t1, space):
    train = vectorize(training(t1).where("split = 'train'"), space, True).cache()
    stored, y, classes = mlp.collected(train)
    known = sorted(train.collect(), key=lambda r: r.file_id)
    assert [classes[k] for k in y] == [r.label for r in known] and classes == sorted({r.label for r in known})
    rows, nets = [(np.array(r.indices, np.int64), np.array(r.freqs, np.float32)) for r in known], []
    for some in (stored, rows):
        net = mlp.start(space.size, classes, SPEC)
        nets.append((mlp.epoch_pass(net, mlp.Adam(net, SPEC), some, y, SPEC, 0), net))
    assert nets[0][0] == nets[1][0] and all((a == b).all() for a, b in zip(nets[0][1].weights, nets[1][1].weights))
    few, z, kept = mlp.collected(train, classes[:2])
    assert kept == classes[:2] and [kept[k] for k in z] == [r.label for r in known if r.label in kept] and len(few) == len(z) > 0
    assert len(mlp.collected(train.limit(0))[0]) == 0


def test_convolution(t1, space):
    net = sequence.start(6, ["a", "b", "c"], mlp.Spec(hidden=(4, 5)))
    rng = np.random.default_rng(4)
    ids, y = rng.integers(0, 8, (7, 9)), rng.integers(0, 3, 7)
    grads, _ = sequence.gradient(net, ids, y)
    params = [p for wb in zip(net.weights, net.biases) for p in wb]
    for p, g in zip(params, grads):
        for at in list(np.ndindex(p.shape))[::2]:
            kept, step = p[at], 1e-6
            p[at] = kept + step
            up = sequence.gradient(net, ids, y)[1] / 7
            p[at] = kept - step
            down = sequence.gradient(net, ids, y)[1] / 7
            p[at] = kept
            assert abs((up - down) / (2 * step) - g[at]) < 1e-5
    long = rng.integers(0, 8, 50_000)
    assert np.allclose(net.pooled(long), np.maximum(net.responses(long[None])[1].max(axis=(0, 1)), 0)) and net.logits([long[:0], long[:2]]).shape == (2, 3)
    fitted = sequence.fit(training(t1).where("split in ('train', 'vocab')"), space)
    got = sequence.predict(t1.where("split = 'test'"), fitted, space).collect()
    assert sum(r.label == r.pred for r in got) > 0.6 * len(got) and all(abs(sum(x.p for x in r.top) - 1) < 1e-6 for r in got)


def test_model_store(spark, space, tmp_path):
    net = mlp.start(space.size, ["a", "b"], SPEC)
    mlp.save(spark, net, str(tmp_path / "m"))
    back = mlp.load(spark, str(tmp_path / "m"))
    assert back.classes == net.classes and all((a == b).all() for a, b in zip([*net.weights, *net.biases], [*back.weights, *back.biases]))


def test_tiers(t1, space):
    train = vectorize(training(t1).where("split in ('train', 'vocab')"), space, True)
    base = nb.fit(training(t1).where("split = 'train'"), space)
    assert tiering.disjoint([["a", "b"], ["b", "c", "d"], ["a", "d"]]) == [["b", "c", "d"]]
    tiers = tiering.fit(train, [["es", "fr"]], base, space.size, SPEC)
    assert [n.classes for n in tiers.nets] == [["es", "fr"]]
    for mode in ("route", "product"):
        rows = score.predict(t1.where("split = 'test'"), tiering.Tiers(base, tiers.nets, mode), space).collect()
        assert all(abs(sum(x.p for x in r.top) - 1) < 1e-6 for r in rows)


def test_parameter_count_and_capacity():
    assert mlp.parameters(5063, (1000, 800, 700), 133) == 6_518_733
    small, large = capacity(1e6, 1e4, 133), capacity(1e10, 1e4, 133)
    assert abs(large["score_seconds"] / small["score_seconds"] - 1e4) < 1 and large["train_seconds_one_core"] == small["train_seconds_one_core"]


def test_search(spark):
    runs = tune.grid(spark, lambda a, b: {"m": -(a - 2) ** 2 + b}, {"a": [1, 2, 3], "b": [0, 1]})
    assert max(runs, key=lambda r: r["m"]) == {"a": 2, "b": 1, "m": 1} and len(runs) == 6
    best, tried = tune.climb(lambda a, b: {"m": -(a - 2) ** 2 + b}, {"a": 1, "b": 0}, {"a": [1, 2, 3], "b": [0, 1]}, "m")
    assert best == {"a": 2, "b": 1} and len(tried) < 12
    cost = tune.profile(spark.range(100).groupBy((F.col("id") % 3).alias("k")).count())
    assert cost["rows"] == 3 and cost["exchanges"] == 1 and cost["shuffled_bytes"] > 0
