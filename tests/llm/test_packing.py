import random
from collections import Counter, defaultdict

import numpy as np
import pytest

from filekind.llm import packing


def plain_best_fit(sizes, lengths, least):
    bins = []
    for s in sizes:
        free = [(b[0] - b[1], -i) for i, b in enumerate(bins) if b[0] - b[1] >= s]
        if free:
            bins[-min(free)[1]][1] += s
        else:
            n = min((n for n in lengths if n >= max(s, least)), key=lambda n: (packing.cost(n) / n, n))
            bins.append([n, s])
    return sorted(b[0] - b[1] for b in bins)


@pytest.mark.parametrize("seed", range(6))
def test_best_fit_against_a_scan(seed):
    rng = random.Random(seed)
    lengths = (8, 16, 32)
    sizes = sorted((rng.randint(1, 32) for _ in range(300)), reverse=True)
    for least in lengths:
        place, used, opened = packing.best_fit(np.array(sizes), lengths, least)
        held = defaultdict(int)
        for s, b in zip(sizes, place):
            held[b] += s
        assert [held[b] for b in range(len(used))] == used and all(u <= o for u, o in zip(used, opened))
        assert sorted(o - u for o, u in zip(opened, used)) == plain_best_fit(sizes, lengths, least)


def check(rows, want, lengths):
    pieces, bins = defaultdict(list), defaultdict(list)
    for r in rows:
        pieces[r.doc_id].append((r.piece, r.start, r.length))
        if r.bin is not None:
            bins[r.bin, r.bin_length].append((r.offset, r.length))
    assert set(pieces) == set(want)
    for d, n in want.items():
        assert sum(x for _, _, x in pieces[d]) == n
    assert len({b for b, _ in bins}) == len(bins)
    for (_, n), run in bins.items():
        run.sort()
        used = run[-1][0] + run[-1][1]
        assert run[0][0] == 0 and all(a + x == b for (a, x), (b, _) in zip(run, run[1:])) and n == packing.fit_length(used, lengths)
    return bins


def test_whole_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = {r.doc_id: len((r.text or "").split()) for r in docs.collect()}
    bins = check(packing.op10_best_fit_packing(spark, sf).collect(), want, packing.LENGTHS)
    total = sum(want.values())
    assert total / sum(n for _, n in bins) > 0.9
    # All lengths together cost no more than fewer that cut documents at the same places.
    mixed = sum(packing.cost(n) for _, n in bins)
    for fewer in ((4096,), (2048, 4096), (512, 4096)):
        alone = check(packing.pack(docs, lengths=fewer).collect(), want, fewer)
        assert mixed <= sum(packing.cost(x) for _, x in alone)


def test_edges(spark):
    rows = [(1, None), (2, ""), (3, "a"), (3, "a"), (None, "b c"), (4, "w " * 25), (5, "x " * 8)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 bin", "'g' grp", "2 piece")
    got = packing.pack(df, lengths=(8, 4), group=2).collect()
    check(got, {1: 0, 2: 0, 3: 2, None: 2, 4: 25, 5: 8}, (4, 8))
    assert sorted(r.length for r in got if r.doc_id == 4) == [1, 8, 8, 8] and [r.bin for r in got if r.doc_id in (1, 2)] == [None, None]
    assert packing.pack(df.limit(0)).count() == 0


def test_repeated_rows_are_dealt_to_many_groups(spark):
    df = spark.createDataFrame([(None, "a b c")] * 3000 + [(7, "d e f")] * 3000, "doc_id long, text string")
    got = packing.pack(df, lengths=(4, 8), group=200).collect()
    groups = Counter(r.bin.split(":")[0] for r in got)
    assert len(got) == 6000 and len(groups) == 30 and max(groups.values()) < 400
    assert len({(r.bin, r.offset) for r in got}) == 6000 and all(r.length == 3 for r in got)


@pytest.mark.parametrize("seed", range(4))
def test_plan_of_a_group_is_the_cheapest_of_all(seed):
    """Every plan by the plain scan: new bins of the least length or more, or of the lengths up to one as far as pieces fit."""
    rng = random.Random(seed)
    lengths = (8, 16, 32)
    sizes = np.array([rng.choice((rng.randint(1, 32), rng.randint(1, 6))) for _ in range(120)])
    down = sorted(sizes.tolist(), reverse=True)

    def total(allowed, least):
        bins = []
        for s in down:
            free = [(b[0] - b[1], -i) for i, b in enumerate(bins) if b[0] - b[1] >= s]
            if free:
                bins[-min(free)[1]][1] += s
            else:
                bins.append([min((n for n in allowed if n >= max(s, least)), key=lambda n: (packing.cost(n) / n, n)), s])
        return sum(packing.cost(min(n for n in lengths if n >= used)) for _, used in bins)

    tried = [total(lengths, n) for n in lengths]
    for top in lengths[:-1]:
        allowed = [n for n in lengths if n <= top or n >= min(x for x in lengths if x >= down[0]) and n > top]
        tried.append(total(allowed, lengths[0]))
    bins, offsets, final = packing.pack_group(sizes, lengths)
    assert abs(sum(map(packing.cost, final)) - min(tried)) < 1e-9
    used = Counter()
    for b, n in zip(bins, sizes.tolist()):
        used[b] += n
    assert all(used[b] <= n for b, n in enumerate(final))
