"""The running example: golden facts of measures, tables and searches."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from utilmine.functions import measures as M
from utilmine.functions import thresholds as T
from utilmine.functions import tree
from utilmine.operators import baselines, stats, verify
from utilmine.operators.mine import Miner, mine
from utilmine.plans import lists, planner
from utilmine.sources import workloads

HUIS = {"b": 108, "d": 126, "a,d": 90, "b,c": 79, "b,d": 126, "c,d": 83, "d,e": 96, "a,c,d": 76, "b,d,e": 93, "c,d,e": 55, "b,c,d,e": 50}


@pytest.fixture(scope="module")
def toy(spark):
    return workloads.toy(spark).cache(), workloads.toy_thresholds(spark).cache()


@pytest.fixture(scope="module")
def miner(toy):
    return Miner(*toy)


def keyed(df, value="utility"):
    return {r["key"]: r[value] for r in df.collect()}


def test_measures(toy):
    lines, mu = toy
    assert {r["tid"]: r["tu"] for r in M.basket_utility(lines).collect()} == dict(enumerate([35, 27, 41, 24, 45, 42, 50, 15, 23, 23], 1))
    assert {r["item"]: r["twu"] for r in M.twu_items(lines).collect()} == {"a": 124, "b": 178, "c": 211, "d": 269, "e": 169}
    assert T.lmu(mu).first()[0] == 50


def test_order_and_information(miner):
    ranks = {r["item"]: r["rank"] for r in miner.dictionary.items.collect()}
    assert sorted(ranks, key=ranks.get) == ["d", "c", "a", "b", "e"]
    names = {v: k for k, v in ranks.items()}
    one = lists.item_lists(miner.enc)
    both = lists.information_table(one).unionByName(lists.information_table(lists.construct(one)))
    got = {"".join(names[x] for x in r["node"]): (r["iu"], r["ru"]) for r in both.collect()}
    assert {k: got[k] for k in ("d", "c", "a", "b", "e", "dc", "be")} == {"d": (126, 143), "c": (19, 120), "a": (48, 12), "b": (108, 9), "e": (24, 0), "dc": (83, 72), "be": (57, 0)}
    table = {"".join(sorted(names[r["a"]] + names[r["b"]])): r["twu"] for r in lists.pair_table(miner.enc).collect()}
    assert table == {"ac": 97, "ad": 109, "ae": 51, "bc": 91, "bd": 137, "be": 95, "cd": 155, "ce": 97, "de": 169}


@pytest.mark.parametrize("variant,nodes,joins", [("base", 22, 20), ("pair", 21, 16), ("look", 16, 20), ("both", 16, 16)])
def test_variants(miner, variant, nodes, joins):
    found, counts = miner.search(variant=variant, want_stats=True)
    assert keyed(found) == HUIS
    assert (counts.total("nodes"), counts.total("joins")) == (nodes, joins)


@pytest.mark.parametrize("engine", ["lists", "subtree", "hybrid"])
def test_engines(miner, engine):
    assert keyed(miner.search(engine, root_budget=10)[0]) == HUIS


def test_options(toy, miner):
    assert keyed(miner.search(carry="rejoin")[0]) == HUIS
    assert keyed(miner.search(variant="look", seed="prefix")[0]) == HUIS
    assert keyed(miner.search(global_at_nodes=True)[0]) == HUIS
    assert keyed(mine(*toy, tu_scope="promising")) == HUIS
    assert keyed(mine(*toy, engine="auto")) == HUIS
    assert keyed(miner.search(pair_cap=3)[0]) == HUIS == keyed(miner.search("subtree", pair_cap=3)[0])
    assert keyed(miner.search(max_len=2)[0]) == {k: v for k, v in HUIS.items() if k.count(",") < 2}
    assert keyed(miner.search(roots=miner.roots(["c", "b"]))[0]) == {"b": 108, "b,c": 79}
    assert keyed(miner.search("lists", roots=miner.roots(["c", "b"]))[0]) == {"b": 108, "b,c": 79}


def test_levelwise(toy):
    for tids in (False, True):
        run = baselines.Levelwise(*toy, with_tids=tids)
        kept = run.named()
        assert kept.count() == 19
        assert run.stats.total("candidates") == 27
        huis = run.huis()
        assert keyed(huis) == HUIS
        assert verify.subset(huis, kept).count() == 0


def test_baselines(toy):
    lines, mu = toy
    assert "b,c,d,e" not in keyed(baselines.naive_closure(lines, mu))
    assert keyed(baselines.enumerated_huis(lines, mu)) == HUIS
    for v in ("base", "pair", "look"):
        assert baselines.uniform(lines, 50, v).count() == 12
    everything = baselines.enumerate_all(lines, mu)
    assert verify.diff(everything.where("utility >= miu"), mine(lines, mu)).count() == 0


def test_counts(toy):
    lines, mu = toy
    row = stats.characteristics(lines).first()
    assert (row["baskets"], row["items"], row["max_length"]) == (10, 5, 4)
    assert stats.ratios({"hui": 1, "hui_star": 2, "htwui": 4, "n2": 10, "n3": 5}) == {"hui/hui_star": 0.5, "hui/htwui": 0.25, "n3/n2": 0.5}
    assert stats.timed(lambda: lines)["done"]


def test_planner(miner):
    told = {r["what"]: r["value"] for r in planner.explain(miner.enc, miner.dictionary).collect()}
    assert (told["items"], told["baskets"], told["max_length"], told["engine"], told["carry"]) == ("5", "10", "4", "subtree", "suffix")
    assert planner.plan(miner.enc, miner.dictionary, root_budget=1).engine == "frontier"
    whole = {r["root"]: r["weight"] for r in planner.root_weights(miner.enc).collect()}
    assert whole[1] == 25 and set(planner.root_weights(miner.enc, 0.9).toPandas()["root"]) <= set(whole)


def test_ratio(toy):
    assert T.glmu_of(toy[0], 0.1) == 32


def test_tree(spark):
    assert tree.size(5) == 31 == tree.all_nodes(spark, 5).count()
    assert tree.children([1, 2], 5) == [[1, 2, 3], [1, 2, 4], [1, 2, 5]]
    assert tree.descendants(spark, [1, 2], 5).count() == 7


def test_plans_have_no_products(miner):
    plan = miner.enc._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
    assert lists.construct(lists.item_lists(miner.enc)).where(F.lit(True))._jdf.queryExecution().executedPlan().toString().count("CartesianProduct") == 0


def test_children_cut_after_their_sums(toy, monkeypatch):
    monkeypatch.setattr("utilmine.operators.search.MOST_ROWS", 0)
    counts = {}
    for v in ("pair", "both"):
        found, seen = Miner(*toy).search(variant=v, want_stats=True)
        assert keyed(found) == HUIS
        counts[v] = seen.total("nodes"), seen.total("joins")
    assert counts == {"pair": (21, 16), "both": (16, 16)}
