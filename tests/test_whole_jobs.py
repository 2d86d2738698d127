"""Queries without SQL that do a whole job, against brute force on small tables."""

from __future__ import annotations

import datetime
import itertools
import os
import random
import re
from collections import Counter, defaultdict

import pyarrow as pa
import pyarrow.compute as pc
import pytest

from utilmine import catalog
from utilmine.operators import pairs

TOKEN = re.compile("[a-zéèàêçïü]+")


@pytest.fixture(scope="module")
def texts(spark, tmp_path_factory):
    """A folder with documents of up to 1,500 characters whose ends have words of their own, and the documents."""
    rng, folder = random.Random(4), tmp_path_factory.mktemp("texts")
    words = ["Éclair", "lantern", "bridges", "cat", "windmill", "harbour", "tea", "ça"]
    docs = [(i, " ".join(rng.choices(words, k=rng.randrange(1, 180))) + f", late{'xyz'[i % 3]}") for i in range(30)] + [(30, ""), (31, None)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{folder}/documents.parquet")
    return str(folder), docs


def brute(found, glmu, beta, longest=None):
    """Every (key, utility, support) of itemsets at or above their threshold; found: counted tokens of each document."""
    utility, support = Counter(), Counter()
    for counts in found:
        for k in range(1, min(longest or len(counts), len(counts)) + 1):
            for items in itertools.combinations(sorted(counts), k):
                utility[items] += sum(counts[t] * len(t) for t in items)
                support[items] += 1
    return {(",".join(i), u, support[i]) for i, u in utility.items() if u >= max(glmu, beta * min(map(len, i)))}


def counted(docs):
    return [c for _, t in docs if (c := Counter(TOKEN.findall((t or "").lower())))]


def mined(rows):
    return {(r["key"], r["utility"], r["support"]) for r in rows.collect()}


def test_doc_tokens_reads_whole_texts(spark, texts):
    folder, docs = texts
    want = brute(counted(docs), 100, 30, 2)
    assert mined(catalog.QUERIES["hui_doc_tokens_whole_k2"](spark, folder)) == want and any("late" in k for k, _, _ in want)


def test_doc_tokens_make_no_rows_of_pairs(spark, texts, monkeypatch):
    monkeypatch.setattr(catalog, "Miner", None)  # its pair table and candidates are rows
    plan = catalog.QUERIES["hui_doc_tokens_whole_k2"](spark, texts[0])._jdf.queryExecution().executedPlan().toString()
    assert "posexplode" not in plan and "Join" not in plan


@pytest.mark.parametrize("wide", [0, 1 << 40], ids=["sorted", "rows of sums"])
def test_tiles_of_pairs(wide, monkeypatch):
    rng = random.Random(wide)
    weigh = {f"{c}{i}": 1 + 3 * i for i in range(12) for c in "aé"}
    found = [(t, {x: rng.randrange(1, 5) * weigh[x] for x in rng.sample(list(weigh), rng.randrange(1, 20))}) for t in range(-20, 20)]
    mu = {x: 40 * w for x, w in weigh.items()} | {"never": 0}
    utility, support = Counter(), Counter()
    for _, b in found:
        for items in itertools.chain(itertools.combinations(sorted(b), 1), itertools.combinations(sorted(b), 2)):
            utility[items] += sum(b[i] for i in items)
            support[items] += 1
    want = {(",".join(i), u, least, support[i]) for i, u in utility.items() if u >= (least := min(mu[x] for x in i))}
    for name, value in (("WIDE", wide), ("BATCH", 50), ("GIVEN", 7), ("PACKED", 30)):
        monkeypatch.setattr(pairs, name, value)
    lines = pa.Table.from_pylist([{"tid": t, "item": i, "u": u} for t, b in found for i, u in b.items()]).to_batches(max_chunksize=20)
    least = pa.Table.from_pylist([{"item": i, "mu": m} for i, m in mu.items()]).to_batches()

    def grouped(batches):
        rows = pa.Table.from_batches(batches)
        return [rows.filter(pc.equal(rows["__key"], k)).to_batches(max_chunksize=1) for k in sorted(set(rows["__key"].to_pylist()))]

    for n in (1, 3, 40):
        packed = [*pairs._by_bucket(n, "lines")(lines), *pairs._by_bucket(n, "thresholds")(least)]
        tiles = [b for group in grouped(packed) for b in pairs._to_tiles(n)(group)]
        got = [r for group in grouped(tiles) for b in pairs._tile(n)(group) for r in b.to_pylist()]
        assert len(got) == len(want) and {(r["key"], r["utility"], r["miu"], r["support"]) for r in got} == want and {r["k"] for r in got} == {1, 2}


def test_characteristics_of_whole_texts(spark, sf):
    own = next(r for r in catalog.QUERIES["dataset_characteristics"](spark, sf).collect() if r["name"] == "doc_tokens")
    found = counted((r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect())
    assert (own["baskets"], own["items"], own["max_length"]) == (len(found), len({t for c in found for t in c}), max(map(len, found)))
    assert own["mean_length"] == pytest.approx(sum(map(len, found)) / len(found))


def test_doc_tokens_to_full_depth(spark, texts):
    folder, docs = texts
    want = brute(counted(docs), 100, 30)
    assert mined(catalog.QUERIES["hui_doc_tokens"](spark, folder)) == want and max(k.count(",") for k, _, _ in want) == 8


def enumerated(baskets, least):
    """(group, key, utility, support) of every itemset of the baskets (group, {item: utility}) at or above least(items)."""
    utility, support = Counter(), Counter()
    for group, b in baskets:
        for k in range(1, len(b) + 1):
            for items in itertools.combinations(sorted(b), k):
                utility[group, items] += sum(b[i] for i in items)
                support[group, items] += 1
    return {(g, ",".join(map(str, i)), u, support[g, i]) for (g, i), u in utility.items() if u >= least(i)}


@pytest.mark.parametrize("workload", ["part", "supplier"])
def test_customer_years_to_full_depth(spark, tmp_path, workload):
    rng, size = random.Random(8), {i: 10 + 5 * i for i in range(1, 9)}
    orders = [(o, 1 + o % 3, datetime.datetime(1995 + o % 2, 5, 1)) for o in range(60)]
    lines = [(o, i, i, float(rng.randrange(20, 51)) * (40 if workload == "supplier" else 1)) for o in range(60) for i in rng.sample(range(1, 9), 3)]
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, o_orderdate timestamp").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_suppkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame(list(size.items()), "p_partkey long, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    price, beta, glmu = (size, 200, 5000) if workload == "part" else ({i: 1 + i % 10 for i in size}, 5000, 20_000)
    year = defaultdict(Counter)
    for o, i, _, q in lines:
        year[orders[o][1], orders[o][2].year][i] += int(q) * price[i]
    want = {x[1:] for x in enumerated([(0, b) for b in year.values()], lambda items: max(glmu, beta * min(price[i] for i in items)))}
    assert mined(catalog.QUERIES[f"hui_customer_year_{workload}"](spark, str(tmp_path))) == want and max(k.count(",") for k, _, _ in want) > 2


def test_stream_windows_to_full_depth(spark, tmp_path):
    rng, start = random.Random(9), datetime.datetime(2024, 1, 4)
    events = [(u, start + datetime.timedelta(days=7 * w, hours=j), 100.0 + rng.randrange(300), f'{{"k": {rng.randrange(8)}}}') for u in range(6) for w in range(2) for j in range(7)]
    spark.createDataFrame(events, "user_id long, ts timestamp, value double, props string").coalesce(1).write.parquet(f"{tmp_path}/made")
    os.rename(next((tmp_path / "made").glob("part-*.parquet")), tmp_path / "events.parquet")
    week = defaultdict(Counter)
    for u, ts, value, props in events:
        week[(ts - start).days // 7, u][int(props[6:-1])] += round(value * 100)
    want = enumerated([(w, b) for (w, _), b in week.items()], lambda items: 100_000)
    rows = catalog.QUERIES["stream_window_huis_full"](spark, str(tmp_path)).collect()
    assert {((r["start"] - start).days // 7, r["key"], r["utility"], r["support"]) for r in rows} == want and max(k.count(",") for _, k, _, _ in want) > 2


def test_stream_patterns_are_not_written_by_the_stream(spark, sf, monkeypatch):
    put, seen = catalog.windows.run_to_table, []
    monkeypatch.setattr(catalog.windows, "run_to_table", lambda *a: seen.append(put(*a)) or seen[-1])
    assert "key" in catalog.QUERIES["stream_window_huis"](spark, sf).columns
    assert seen[0].columns == ["start", "end", "user", "tu", "its"]


def test_pruning_grids_are_whole(spark, sf, monkeypatch):
    monkeypatch.setattr(catalog.stats, "pruning_counts", lambda lines, grid: grid)
    for name, grid in (("glmu", catalog.GRID_GLMU), ("beta", catalog.GRID_BETA)):
        assert catalog.QUERIES[f"pruning_counts_by_{name}"](spark, sf) == grid and len(grid) == 5


def test_runtime_query_has_the_baselines(spark, sf, monkeypatch):
    asked = {}
    monkeypatch.setattr(catalog.stats, "runtimes", lambda lines, grid, **how: asked.update(grid=grid, **how))
    catalog.QUERIES["search_stats_runtime"](spark, sf)
    assert {*catalog.GRID_GLMU, *catalog.GRID_BETA, (catalog.GLMU, catalog.BETA)} == set(asked["grid"]) and asked.get("with_levelwise", True)


def test_scalability_runs_on_the_tables(spark, sf, monkeypatch):
    seen = {}

    def counted_runs(sizes, glmu, beta):
        seen.update({name: lines for name, lines in sizes.items()})
        return spark.createDataFrame([(n,) for n in sizes], "size string")

    monkeypatch.setattr(catalog.stats, "scalability", counted_runs)
    assert catalog.QUERIES["scalability_runs"](spark, sf).count() == 17
    baskets = [seen[f"order_brand {i}/4"].select("tid").distinct().count() for i in range(1, 5)]
    assert baskets == sorted(set(baskets)) and baskets[-1] == catalog.brand(spark, sf).select("tid").distinct().count()
    assert {f"generated {n}" for n in (100_000, 500_000)} <= set(seen)
