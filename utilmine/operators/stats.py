"""Cost and accuracy measures, and the experiments over grids of thresholds."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from utilmine.functions import thresholds as T
from utilmine.functions.measures import with_tu
from utilmine.operators.baselines import Levelwise
from utilmine.operators.mine import Miner, decoded
from utilmine.operators.search import VARIANTS
from utilmine.plans.cut import cached, released, written
from utilmine.sources import baskets


def characteristics(lines: DataFrame) -> DataFrame:
    """One row: baskets, items, mean and longest length."""
    sizes = lines.groupBy("tid").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("baskets"), F.avg("n").alias("mean_length"), F.max("n").alias("max_length"))
    return sizes.join(F.broadcast(lines.agg(F.count_distinct("item").alias("items"))))


def timed(fn: Callable[[], DataFrame], cap_s: float = 10_000) -> dict:
    """Seconds until all rows of fn() are made, whether it stayed below the cap, after which its jobs are cancelled."""
    import threading

    spark = SparkSession.getActiveSession()
    tag, began = f"timed-{time.time_ns()}", time.perf_counter()
    timer = threading.Timer(cap_s, lambda: spark.sparkContext.cancelJobsWithTag(tag))
    spark.sparkContext.addJobTag(tag)
    timer.start()
    try:
        fn().write.format("noop").mode("overwrite").save()
        done = True
    except Exception:
        done = time.perf_counter() - began < cap_s
        if done:
            raise
    finally:
        timer.cancel()
        spark.sparkContext.removeJobTag(tag)
    return {"seconds": time.perf_counter() - began, "done": done}


def memory(spark: SparkSession) -> dict:
    """Peak MB: the heap of all executors as Spark's status store has it, and the largest Python worker of this machine."""
    peaks = []
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    for i in range(executors.size()):
        metrics = executors.apply(i).peakMemoryMetrics()
        if metrics.isDefined():
            peaks.append(metrics.get().getMetricValue("JVMHeapMemory") / 1e6)
    runtime = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    heap = max([*peaks, (runtime.totalMemory() - runtime.freeMemory()) / 1e6])
    return {"heap_mb": heap, "python_mb": resource.getrusage(resource.RUSAGE_CHILDREN).ru_maxrss / 1e3}


def _lowest(profit: DataFrame, grid: list[tuple[int, int]]) -> DataFrame:
    """The least threshold that an item has in any setting."""
    each = [T.from_profit(profit, beta, glmu).select("item", "mu") for glmu, beta in grid]
    out = each[0]
    for more in each[1:]:
        out = out.unionByName(more)
    return out.groupBy("item").agg(F.min("mu").alias("mu"))


def _reaching(sets: DataFrame, by: str, profit: DataFrame, grid: list[tuple[int, int]]) -> list[int]:
    """How many of sets(key, items, a measure) reach their own threshold in each setting."""
    own = profit.select("item", *(F.greatest(F.lit(b) * F.col("pr"), F.lit(g)).alias(f"mu{i}") for i, (g, b) in enumerate(grid)))
    least = sets.select("key", by, F.explode("items").alias("item")).join(own, "item").groupBy("key", by).agg(*(F.min(f"mu{i}").alias(f"miu{i}") for i in range(len(grid))))
    return list(least.agg(*(F.count(F.when(F.col(by) >= F.col(f"miu{i}"), 1)) for i in range(len(grid)))).first())


def pattern_counts(lines: DataFrame, grid: Iterable[tuple[int, int]]) -> DataFrame:
    """glmu, beta, hui, hui_star (one threshold, glmu) and htwui (kept by the level-wise method) for each setting.

    What reaches a threshold reaches a lower one, so each method runs once, with the least thresholds of the grid, and each setting counts among its results.
    """
    spark, grid = lines.sparkSession, list(grid)
    profit, lines = cached(baskets.profit_of(lines)), cached(with_tu(lines.select("tid", "item", "u")))
    hui = Miner(lines, _lowest(profit, grid)).search("hybrid")[0]
    star = Miner(lines, T.uniform(profit, min(g for g, _ in grid)), "twu").search("hybrid", variant="pair")[0]
    stars = star.agg(*(F.count(F.when(F.col("utility") >= g, 1)) for g, _ in grid)).first()
    rows = [(g, b, h, s, k) for (g, b), h, s, k in zip(grid, _reaching(hui, "utility", profit, grid), stars, kept_counts(lines, profit, grid), strict=True)]
    return spark.createDataFrame(rows, "glmu long, beta long, hui long, hui_star long, htwui long")


def kept_counts(lines: DataFrame, profit: DataFrame, grid: list[tuple[int, int]]) -> list[int]:
    """What the level-wise method keeps in each setting, from one run with the least thresholds of the grid."""
    run = Levelwise(lines, _lowest(profit, grid), with_tids=True)
    kept = decoded(run.htwuis().select("node", "mu1", F.col("twu").alias("iu"), F.lit(0).cast("long").alias("support")), run.dictionary)
    return _reaching(kept, "utility", profit, grid)


def search_counts(lines: DataFrame, thresholds: DataFrame, variants: Iterable[str] = VARIANTS, **options) -> dict[str, dict]:
    """nodes, joins, aborted and empty of each variant."""
    m, out = Miner(lines, thresholds), {}
    for v in variants:
        stats = m.search(variant=v, want_stats=True, **options)[1]
        out[v] = {k: stats.total(k) for k in ("nodes", "joins", "aborted", "empty")}
    return out


def n1(lines: DataFrame, thresholds: DataFrame) -> dict:
    """Itemsets that the level-wise methods make while they find theirs: candidates and kept."""
    run = Levelwise(lines, thresholds, with_tids=True)
    run.htwuis()
    return {"candidates": run.stats.total("candidates"), "kept": run.stats.total("kept")}


def pruning_counts(lines: DataFrame, grid: Iterable[tuple[int, int]]) -> DataFrame:
    """glmu, beta, n1 (kept by the level-wise method), n2 to n5 (visited nodes of base, pair, look, both)."""
    grid, spark = list(grid), lines.sparkSession
    profit, lines = cached(baskets.profit_of(lines)), cached(with_tu(lines.select("tid", "item", "u")))
    rows = []
    for (glmu, beta), n1_ in zip(grid, kept_counts(lines, profit, grid), strict=True):
        m = Miner(lines, T.from_profit(profit, beta, glmu))
        rows.append((glmu, beta, n1_, *(m.visited(v)[0] for v in VARIANTS)))
    return spark.createDataFrame(rows, "glmu long, beta long, n1 long, n2 long, n3 long, n4 long, n5 long")


def joins(lines: DataFrame, thresholds: DataFrame) -> DataFrame:
    """variant, joins attempted."""
    counts = search_counts(lines, thresholds)
    return lines.sparkSession.createDataFrame([(v, c["joins"]) for v, c in counts.items()], "variant string, joins long")


def ratios(counts: dict[str, int]) -> dict[str, float]:
    """hui / hui_star, hui / htwui, and each visited count over that of the base miner."""
    out = {f"hui/{k}": counts["hui"] / counts[k] for k in ("hui_star", "htwui") if counts.get(k)}
    return out | {f"{k}/n2": counts[k] / counts["n2"] for k in ("n3", "n4", "n5") if k in counts and counts.get("n2")}


def runtimes(lines: DataFrame, grid: Iterable[tuple[int, int]], engines: Iterable[str] = ("frontier", "hybrid"), cap_s: float = 10_000, with_levelwise: bool = True) -> DataFrame:
    """glmu, beta, method, seconds, done, heap_mb, python_mb for the miners' variants and the level-wise baseline. The lines are made once, before any run.
    What the runs of a setting cache is dropped after them; each run encodes its own baskets."""
    spark, rows, profit = lines.sparkSession, [], cached(written(baskets.profit_of(lines)))
    lines = cached(with_tu(lines.select("tid", "item", "u")))
    for made in (profit, lines):
        made.count()
    for glmu, beta in grid:
        own = T.from_profit(profit, beta, glmu)
        methods = {f"{e}/{v}": (lambda e=e, v=v: Miner(lines, own).search(e, variant=v)[0]) for e in engines for v in VARIANTS}
        if with_levelwise:
            methods |= {"levelwise": lambda: Levelwise(lines, own).huis(), "levelwise_tid": lambda: Levelwise(lines, own, with_tids=True).huis()}
        with released():
            for name, fn in methods.items():
                run = timed(fn, cap_s)
                rows.append((glmu, beta, name, run["seconds"], run["done"], *memory(spark).values()))
    return spark.createDataFrame(rows, "glmu long, beta long, method string, seconds double, done boolean, heap_mb double, python_mb double")


def scalability(sizes: dict[str, DataFrame], glmu: int, beta: int) -> DataFrame:
    """size, baskets, seconds, heap_mb, hui, htwui, nodes of the combined miner, for inputs of several sizes. seconds: of encoding and search, from lines that are kept."""
    rows = []
    for name, lines in sizes.items():
        with released():
            profit = cached(written(baskets.profit_of(lines)))
            own, lines = T.from_profit(profit, beta, glmu), cached(with_tu(lines.select("tid", "item", "u")))
            n = lines.agg(F.count_distinct("tid")).first()[0]  # makes the lines
            profit.count()
            m = []
            run = timed(lambda: (m.append(Miner(lines, own)), m[0].search("hybrid")[0])[1])  # noqa: B023
            visited, found = m[0].visited("both")
            rows.append((name, n, run["seconds"], memory(lines.sparkSession)["heap_mb"], found, m[0].kept(), visited))
    return next(iter(sizes.values())).sparkSession.createDataFrame(rows, "size string, baskets long, seconds double, heap_mb double, hui long, htwui long, nodes long")
