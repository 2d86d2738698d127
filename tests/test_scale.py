"""Plans and paths that matter on larger tables, on small ones."""

from __future__ import annotations

import datetime
import itertools
import math
import random

import numpy as np
from pyspark.sql import functions as F

from utilmine import catalog
from utilmine.functions import measures
from utilmine.operators import baselines, stats, subtree, verify
from utilmine.operators.mine import Miner
from utilmine.operators.search import VARIANTS, Frontier, Options
from utilmine.operators.subtree import Walk


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def made(spark, baskets):
    """lines(tid, item, u) of dicts of item: utility."""
    return spark.createDataFrame([(t, i, u) for t, b in enumerate(baskets) for i, u in b.items()], "tid long, item long, u long")


def test_enumeration_joins_no_itemsets(spark):
    rng = random.Random(5)
    baskets = [{i: rng.randrange(1, 9) for i in rng.sample(range(12), rng.randrange(1, 10))} for _ in range(20)]
    lines, mu = made(spark, baskets), spark.range(12).select(F.col("id").alias("item"), (F.col("id") * 7 % 12).alias("mu"))
    got = baselines.enumerate_all(lines, mu)
    assert plan_of(got).count("Join") == 1  # lines with thresholds
    want = {}
    for b in baskets:
        for items in itertools.chain.from_iterable(itertools.combinations(sorted(b), k) for k in range(1, len(b) + 1)):
            u, n, twu = want.get(items, (0, 0, 0))
            want[items] = u + sum(b[i] for i in items), n + 1, twu + sum(b.values())
    assert {tuple(r["items"]): (r["utility"], r["support"], r["twu"]) for r in got.collect()} == want
    assert all(r["miu"] == min(i * 7 % 12 for i in r["items"]) and r["k"] == len(r["items"]) for r in got.collect())
    assert {tuple(r["items"]) for r in baselines.enumerate_all(lines, mu, 3).collect()} == {i for i in want if len(i) <= 3}


def test_prices_are_not_broadcast(spark):
    at = lambda y: datetime.datetime(y, 1, 1)
    lines = spark.createDataFrame([(1, 5, 2, at(1995)), (2, 5, 3, at(1990)), (3, 6, 1, at(1999))], "tid long, item long, qty long, ts timestamp")
    prices = spark.createDataFrame([(i, y - 1990 + i, at(y)) for i in (5, 6) for y in range(1991, 1998)], "item long, pr long, valid_from timestamp")
    got = measures.asof_profit(lines, prices)
    assert "Broadcast" not in plan_of(got) and {(r["tid"], r["pr"], r["u"]) for r in got.collect()} == {(1, 10, 20), (3, 13, 13)}


def test_basket_minus_reads_the_tables(spark, sf):
    got = catalog.QUERIES["basket_minus"](spark, sf)
    whole = {}
    for r in catalog.brand(spark, sf).collect():
        whole.setdefault(r["tid"], []).append(r["item"])
    want = {t: ",".join(str(i) for i in sorted(its) if i not in (3, 7)) or None for t, its in whole.items() if {3, 7} <= set(its)}
    assert want and {r["tid"]: r["items"] for r in got.collect()} == want and "FileScan parquet" in plan_of(got)


def repeated(spark):
    """Baskets of few item sets, each many times with other utilities, and thresholds."""
    rng = random.Random(6)
    sets = [rng.sample(range(8), rng.randrange(2, 7)) for _ in range(5)]
    return made(spark, [{i: rng.randrange(1, 20) for i in s} for s in sets for _ in range(12)]), spark.range(8).select(F.col("id").alias("item"), (60 + 40 * F.col("id")).alias("mu"))


def test_equal_baskets_are_searched_once(spark):
    lines, mu = repeated(spark)
    m = Miner(lines, mu)
    assert m.enc.count() == 60 and m.merged.count() == 5 and m.merged.agg(F.sum("n")).first()[0] == 60
    want = baselines.enumerated_huis(lines, mu)
    for engine in ("frontier", "lists", "subtree"):
        assert verify.diff(want, m.search(engine)[0]).count() == 0
    for tids in (False, True):
        assert verify.diff(want, baselines.Levelwise(lines, mu, with_tids=tids).huis()).count() == 0


def test_walks_count_what_the_frontier_visits(spark):
    m = Miner(*repeated(spark))
    for v in VARIANTS:
        found, seen = m.search(variant=v)
        assert m.visited(v) == (seen.total("nodes"), found.count()) == m.visited(v, root_budget=1)


def test_level_wise_scans_join_no_unkept_itemsets(spark):
    """A scan gives only rows of baskets that hold a candidate, each once."""
    lines, mu = repeated(spark)
    run = baselines.Levelwise(lines, mu)
    kept = {tuple(r["node"]) for r in run.htwuis().collect()}
    rows = [(tuple(r["node"]), r["tid"]) for r in run._met(3).collect()]
    assert rows and len(rows) == len(set(rows)) and {n for n, _ in rows} == {n for n in kept if len(n) == 3}


def test_grids_run_each_method_once(spark, monkeypatch):
    lines = repeated(spark)[0].withColumn("pr", F.col("item") + 1)
    runs, own = [], stats.Levelwise
    monkeypatch.setattr(stats, "Levelwise", lambda *a, **k: runs.append(a) or own(*a, **k))
    grid = [(100, 30), (200, 30), (300, 90)]
    got = [tuple(r) for r in stats.pattern_counts(lines, grid).collect()]
    assert len(runs) == 1
    for g, b, hui, star, kept in got:
        every = baselines.enumerate_all(lines, lines.groupBy("item").agg(F.greatest(F.lit(b) * F.min("pr"), F.lit(g)).alias("mu")))
        assert (hui, star, kept) == tuple(every.agg(F.count_if(F.col("utility") >= F.col("miu")), F.count_if(F.col("utility") >= g), F.count_if(F.col("twu") >= F.col("miu"))).first())


def test_workers_give_out_what_they_find_in_batches(spark, monkeypatch):
    entries = 12
    r, u = np.arange(entries), np.ones(entries, np.int64)
    walk = Walk(r, u, u[::-1].cumsum()[::-1] - 1, np.full(entries, entries), u, Options(variant="base"), None, entries + 1)
    monkeypatch.setattr("utilmine.operators.subtree.BATCH", 100)
    held, rows = [], 0
    for batch in walk.run(np.arange(1), np.zeros(1, np.int64)):
        rows += batch.num_rows
        held.append(batch.num_rows)
    assert rows == walk.visited == 2 ** (entries - 1) and len(held) > 2 and not walk.found


def test_chunks_are_bounded_by_what_they_expand_to(monkeypatch):
    width, baskets = 24, 40
    r = np.tile(np.arange(1, width + 1, dtype=np.int32), baskets)
    u, stop = np.ones(len(r), np.int64), np.repeat(width * np.arange(1, baskets + 1), width)
    walk = Walk(r, u, width - r.astype(np.int64), stop, u, Options(variant="both", max_len=3), None, width + 1)
    expanded, after = [], subtree._after
    monkeypatch.setattr(subtree, "CHUNK", 2000)
    monkeypatch.setattr(subtree, "_after", lambda a, b: expanded.append((b - a).sum()) or after(a, b))
    found = sum(x.num_rows for x in walk.run(np.arange(len(r)), np.full(len(r), 3 * baskets)))
    assert found == math.comb(width, 3) and max(expanded) <= 2000


def one_basket(entries, options):
    r, u = np.arange(1, entries + 1, dtype=np.int32), np.ones(entries, np.int64)
    return Walk(r, u, entries - r.astype(np.int64), np.full(entries, entries), u, options, None, entries + 1)


def test_batches_are_bounded_by_their_items(monkeypatch):
    """Chunks find many itemsets at once, and long ones: neither makes a large batch."""
    monkeypatch.setattr(subtree, "BATCH", 100)
    monkeypatch.setattr(subtree, "CELLS", 600, raising=False)
    seen, shape = set(), []
    for batch in one_basket(13, Options()).run(np.arange(13), np.zeros(13, np.int64)):
        rows = batch["node"].to_pylist()
        seen |= {tuple(x) for x in rows}
        shape.append((len(rows), sum(map(len, rows))))
    assert sum(n for n, _ in shape) == len(seen) == 2**13 - 1
    assert max(n for n, _ in shape) <= 100 and max(n for _, n in shape) <= 600


def test_chunks_that_wait_are_bounded_at_any_depth(monkeypatch):
    """Long itemsets are spelled right, and what waits does not grow by a whole chunk for each of their items."""
    for name, value in (("CHUNK", 1000), ("STACK", 8000), ("LEAST", 60)):
        monkeypatch.setattr(subtree, name, value, raising=False)
    waits, own = [], Walk._room
    monkeypatch.setattr(Walk, "_room", staticmethod(lambda held: waits.append(held) or own(held)))
    entries, got = 60, []
    for batch in one_basket(entries, Options()).run(np.arange(entries), np.full(entries, entries - 2)):
        got += [tuple(x) for x in batch["node"].to_pylist()]
    whole = set(range(1, entries + 1))
    assert sorted(got) == sorted(tuple(sorted(whole - set(gone))) for k in range(3) for gone in itertools.combinations(whole, k))
    assert 2000 < max(waits) <= 8000 + 60 * entries


def test_walks_name_pairs_of_many_items(spark):
    names = np.array([60_000 * 70_000 + 60_001], np.int64)
    r = np.array([60_000, 60_001], np.int32)
    walk = Walk(r, np.array([2, 3]), np.array([3, 0]), np.array([2, 2]), np.array([1, 1]), Options(), (names, np.array([5])), 70_000)
    assert [x["node"].to_pylist() for x in walk.run(np.array([0]), np.array([5]))] == [[[60_000, 60_001]]]


def test_brand_thresholds_read_the_kept_lines(spark, sf):
    lines, mu = catalog.brand_input(spark, sf)
    assert "InMemoryTableScan" in plan_of(mu) and {tuple(r) for r in mu.collect()} == {tuple(r) for r in catalog.brand_mu(spark, sf).collect()}


def test_baskets_go_to_workers_packed(spark, monkeypatch):
    """A group's part of a chunk is one row of bytes, without the tail items that the pair table rules out."""
    rng = random.Random(11)
    lines = made(spark, [{i: rng.randrange(1, 9) * (1 if i % 5 else 10) for i in rng.sample(range(20), rng.randrange(2, 9))} for _ in range(60)])
    mu = spark.range(20).select(F.col("id").alias("item"), (300 + F.col("id")).alias("mu"))
    m, o = Miner(lines, mu), Options()
    table = subtree.shipped(m._pairs(o), m.dictionary)
    rows = subtree.packed(m.merged.coalesce(1), m.dictionary, 4, table)
    assert {f.dataType.typeName() for f in rows.schema} == {"integer", "long", "binary"}
    got = rows.collect()
    assert sum(r["root"] is not None for r in got) == m.dictionary.n and sum(r["size"] is not None for r in got) == 4
    whole = m.merged.selectExpr("size(its) as w").selectExpr("sum(w * (w + 1) / 2) as n").first()["n"]
    assert 0 < sum(len(r["r"] or b"") // 4 for r in got) < whole
    want = baselines.enumerated_huis(lines, mu)
    assert want.count() and verify.diff(want, m.search("subtree")[0]).count() == 0
    monkeypatch.setattr(subtree, "shipped", lambda *a: None)
    assert verify.diff(want, m.search("subtree")[0]).count() == 0
    assert verify.diff(want, m.search("hybrid", root_budget=30)[0]).count() == 0


def test_packed_walks_of_bounded_length(spark):
    """Many groups, chunks of a few entries and a longest length: roots and tails come together as in one group."""
    lines, mu = repeated(spark)
    m = Miner(lines, mu)
    want = baselines.enumerated_huis(lines, mu, 3)
    rows = subtree.packed(m.merged, m.dictionary, 7, None)
    assert rows.where("root is null").select("__group").distinct().count() == min(7, m.dictionary.n)
    assert want.count() and verify.diff(want, m.search("subtree", root_budget=3, max_len=3)[0]).count() == 0


def test_scalability_counts_kept_itemsets_without_candidates(spark, monkeypatch):
    lines = repeated(spark)[0].withColumn("pr", F.col("item") + 1)
    monkeypatch.setattr(stats, "n1", lambda *a: 1 / 0)  # the level-wise method makes a candidate of any two items
    got = stats.scalability({"all": lines}, 500, 100).first()
    every = baselines.enumerate_all(lines, lines.groupBy("item").agg(F.greatest(F.lit(100) * F.min("pr"), F.lit(500)).alias("mu")))
    want = every.agg(F.count_if(F.col("utility") >= F.col("miu")), F.count_if(F.col("twu") >= F.col("miu"))).first()
    assert (got["hui"], got["htwui"], got["baskets"]) == (*want, 60) and want[1] > want[0] > 0
    m = Miner(lines, lines.groupBy("item").agg(F.greatest(F.lit(100) * F.min("pr"), F.lit(500)).alias("mu")))
    assert m.kept() == m.kept(root_budget=1) == want[1]


def test_runtimes_make_lines_once(spark, monkeypatch):
    lines = repeated(spark)[0].withColumn("pr", F.col("item") + 1)
    seen, own = [], stats.Miner
    monkeypatch.setattr(stats, "Miner", lambda *a: seen.append(a) or own(*a))
    assert stats.runtimes(lines, [(500, 100)], engines=("hybrid",), with_levelwise=False).count() == 4
    assert len(seen) == 4 and all("InMemoryTableScan" in plan_of(df) for a in seen for df in a)


def test_counts_share_the_pair_table_and_are_dealt_by_groups(spark, monkeypatch):
    """A search and the counts of one input make one pair table; their walks go to a task for each group, whatever the bytes."""
    lines, mu = repeated(spark)
    made_, own = [], subtree.shipped
    monkeypatch.setattr(subtree, "shipped", lambda *a: made_.append(a) or own(*a))
    m = Miner(lines, mu)
    found = m.search("hybrid")[0]
    assert m.visited("both") == (m.search("frontier", want_stats=True)[1].total("nodes"), found.count())
    assert m.kept() == m.kept(root_budget=1) > 0 and len(made_) == 1
    assert "REPARTITION_BY_NUM" in plan_of(found)


def test_counts_spell_no_itemsets(spark, monkeypatch):
    lines, mu = repeated(spark)
    m, o = Miner(lines, mu), Options()
    rows = subtree.packed(m.merged, m.dictionary, 1, None).toArrow().to_batches()
    monkeypatch.setattr(subtree.Walk, "_named", lambda *a: 1 / 0)
    counts = [b.to_pylist()[0] for b in subtree.counter(o, None, m.dictionary.n + 1)(iter(rows))]
    assert sum(c["found"] for c in counts) == baselines.enumerated_huis(lines, mu).count() > 0


def test_shares_of_a_workload_read_its_written_lines(spark, sf):
    shares = catalog._nested(catalog.brand(spark, sf))
    assert all("Join" not in plan_of(lines) and "FileScan" in plan_of(lines) for lines in shares.values())


def test_runs_leave_no_cached_tables(spark):
    lines = repeated(spark)[0].withColumn("pr", F.col("item") + 1)
    held = spark.sparkContext._jsc.getPersistentRDDs
    before = set(held())
    assert stats.scalability({"all": lines}, 500, 100).count() == 1 and set(held()) <= before
    assert stats.runtimes(lines, [(500, 100), (600, 100)], engines=("hybrid",), with_levelwise=False).where("done").count() == 8
    assert len(set(held()) - before) <= 2  # the lines and profits


def test_small_pair_tables_are_not_counted(spark, monkeypatch):
    """A dictionary of few items has few pairs: workers get their table without a count of it, and the frontier its bound."""
    lines, mu = repeated(spark)
    m, own, counted = Miner(lines, mu), type(lines).count, []
    m.merged
    monkeypatch.setattr(type(lines), "count", lambda df: counted.append(df) or own(df))
    names = subtree.shipped(m._pairs(Options()), m.dictionary).value[0]
    run = Frontier(m.merged, m.dictionary, Options())
    assert not counted and 0 < len(names) <= run.n_pairs == m.dictionary.n * (m.dictionary.n - 1) // 2
    assert subtree.shipped(m._pairs(Options()), m.dictionary, most_pairs=len(names) - 1) is None


def test_plans_do_not_spell_out_what_made_the_dictionary(spark):
    """A plan's text has the plans of all cached tables below it, one within the other."""
    lines, mu = repeated(spark)
    m = Miner(lines, mu)
    assert "Window" not in plan_of(m.dictionary.items.select("rank")) and len(plan_of(m.search("hybrid")[0])) < 60_000
