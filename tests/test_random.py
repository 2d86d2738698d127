"""Random and edge inputs against a plain enumeration."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pytest

from utilmine.functions import thresholds as T
from utilmine.operators.baselines import Levelwise, frequent_multi
from utilmine.operators.mine import Miner, mine
from utilmine.sources import baskets
from utilmine.sources.synthetic import quest_like


def brute(rows, mu):
    per = {}
    for t, i, u in rows:
        per.setdefault(t, {})
        per[t][i] = per[t].get(i, 0) + u
    found = {}
    for items in per.values():
        for k in range(1, len(items) + 1):
            for c in combinations(sorted(items), k):
                u, n = found.get(c, (0, 0))
                found[c] = u + sum(items[x] for x in c), n + 1
    return {",".join(map(str, c)): (u, n) for c, (u, n) in found.items() if u >= min(mu[x] for x in c)}


@pytest.mark.parametrize("seed", range(3))
def test_random(spark, seed):
    rng = np.random.default_rng(seed)
    rows = [(t, int(i), int(rng.integers(0, 30))) for t in range(25) for i in rng.choice(8, rng.integers(1, 7), replace=False)]
    mu = {i: int(rng.integers(20, 200)) for i in range(8)}
    if seed == 2:
        mu = dict.fromkeys(mu, 60)
    lines = spark.createDataFrame(rows, "tid long, item long, u long")
    thresholds = spark.createDataFrame(list(mu.items()), "item long, mu long")
    want = brute(rows, mu)
    m = Miner(lines, thresholds)
    for how in ({"variant": "pair"}, {"variant": "both"}, {"engine": "lists", "variant": "look"}, {"engine": "subtree", "variant": "both"}, {"engine": "hybrid", "variant": "base", "root_budget": 60}):
        assert {r["key"]: (r["utility"], r["support"]) for r in m.search(**how)[0].collect()} == want, how
    assert {r["key"] for r in Levelwise(lines, thresholds, with_tids=True).huis().collect()} == set(want)


def test_edges(spark):
    schema = "tid long, item long, u long"
    mu = spark.createDataFrame([(1, 5), (2, 5), (9, 1)], "item long, mu long")
    assert mine(spark.createDataFrame([], schema), mu).count() == 0
    assert mine(spark.createDataFrame([], schema), mu, engine="hybrid").count() == 0
    one = spark.createDataFrame([(1, 1, 5)], schema)
    assert [(r["key"], r["utility"]) for r in mine(one, mu).collect()] == [("1", 5)]
    zero = T.uniform(one, 0)
    assert mine(spark.createDataFrame([(1, 1, 0), (1, 2, 0)], schema), T.uniform(spark.createDataFrame([(1,), (2,)], "item long"), 0)).count() == 3
    assert zero.first()["mu"] == 0
    big = 1 << 61
    assert [r["utility"] for r in mine(spark.createDataFrame([(1, 1, big), (1, 2, big)], schema), spark.createDataFrame([(1, big), (2, 2 * big)], "item long, mu long"), engine="subtree").collect()].count(2 * big) == 1
    with pytest.raises(Exception, match="no threshold"):
        mine(spark.createDataFrame([(1, 7, 5)], schema), mu).collect()


def test_lines(spark):
    raw = spark.createDataFrame([(1, "a", 2, 3), (1, "a", 1, 3), (1, None, 1, 1), (None, "a", 1, 1), (2, "b", 0, 4)], "t long, i string, q long, p long")
    assert [tuple(r) for r in baskets.from_lines(raw, "t", "i", "q", "p").collect()] == [(1, "a", 3, 3, 9)]
    assert baskets.dropped(raw, "t", "i", "q").first()[0] == 3
    bad = spark.createDataFrame([(1, "a", -2)], "t long, i string, u long")
    with pytest.raises(Exception, match="negative"):
        baskets.from_lines(bad, "t", "i", utility="u").collect()
    assert baskets.from_lines(bad, "t", "i", utility="u", on_negative="drop").count() == 0
    with pytest.raises(Exception, match="one threshold"):
        T.from_table(spark.createDataFrame([("a", 1), ("a", 2)], "item string, mu long")).collect()


def test_frequent_and_synthetic(spark):
    lines = quest_like(spark, 300, items=40, mean_len=5, patterns=20).cache()
    again = quest_like(spark, 300, items=40, mean_len=5, patterns=20, partitions=7)
    assert lines.exceptAll(again).count() == 0 and lines.count() == again.count()
    mis = lines.select("item").distinct().selectExpr("item", "20 + item % 5 as mis")
    for r in frequent_multi(lines, mis, 3).collect():
        assert r["support"] >= r["miu"]
