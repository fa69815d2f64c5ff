import random

import pytest
from filekind.llm import components as co


def plain(links):
    root = {x: x for link in links for x in link if link[0] != link[1]}
    for _ in root:
        for a, b in links:
            if a != b:
                root[a] = root[b] = min(root[a], root[b])
    return root


@pytest.mark.parametrize("at_once", [0, co.AT_ONCE])
def test_few_and_many_links_have_the_same_roots(spark, at_once):
    rng = random.Random(3)
    links = [(rng.randrange(-150, 150), rng.randrange(-150, 150)) for _ in range(130)] + [(i, i + 1) for i in range(1000, 1040)] + [(7, 7), (-(1 << 63), (1 << 63) - 1)]
    got = co.components(spark.createDataFrame(links, "a long, b long"), "a", "b", at_once=at_once).collect()
    assert len(got) == len({r.node for r in got}) and {r.node: r.root for r in got} == plain(links)
    assert co.components(spark.createDataFrame([], "a long, b long"), "a", "b").count() == 0
    names = spark.createDataFrame([("b", "a"), ("c", "b"), ("x", "y")], "a string, b string")
    assert {tuple(r) for r in co.components(names, "a", "b").collect()} == {("a", "a"), ("b", "a"), ("c", "a"), ("x", "x"), ("y", "x")}


def test_few_links_take_few_jobs(spark):
    """Each exchange takes a thread of the driver, which a pipeline of many small link tables has too few megabytes for."""
    links = spark.createDataFrame([(i, i + 1) for i in range(200)], "a long, b long")
    sc = spark.sparkContext
    sc.setJobGroup("few links", "few links")
    out = co.components(links, "a", "b")
    jobs = sc.statusTracker().getJobIdsForGroup("few links")
    sc._jsc.clearJobGroup()
    assert "Exchange" not in out._jdf.queryExecution().executedPlan().toString() and len(jobs) <= 8
    assert {r.root for r in out.collect()} == {0} and out.count() == 201
