"""Runs the headline queries and prints one JSON line. BENCH_SF_DIR: the tables; BENCH_CPUS: local threads; BENCH_FULL=1 adds the experiment families."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import DataFrame, SparkSession

from utilmine.functions import thresholds as T
from utilmine.operators import baselines
from utilmine.operators.mine import Miner
from utilmine.plans.ship import to_workers
from utilmine.sources import baskets, workloads

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")

#: name: workload, glmu, beta, engine, options
MINED = {
    "hui_order_brand_both": ("order_brand", 40_000, 10_000, "hybrid", {}),
    "hui_order_brand_base": ("order_brand", 40_000, 10_000, "hybrid", {"variant": "base"}),
    "hui_order_brand_frontier": ("order_brand", 40_000, 10_000, "frontier", {}),
    "hui_order_part": ("order_part", 6_500, 100, "hybrid", {}),
    "hui_order_record": ("order_record", 200_000, 0, "hybrid", {}),
    "hui_customer_year_supplier_k3": ("customer_year_supplier", 20_000, 5_000, "hybrid", {"max_len": 3}),
    "hui_user_day": ("user_day_key", 20_000, 5_000, "hybrid", {}),
}


def session() -> SparkSession:
    builder = SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.ui.enabled", "false").config("spark.driver.memory", "12g")
    return builder.config("spark.sql.shuffle.partitions", CPUS).config("spark.sql.session.timeZone", "UTC").getOrCreate()


def mined(spark: SparkSession, workload: str, glmu: int, beta: int, engine: str, options: dict) -> DataFrame:
    lines = workloads.ALL[workload](spark, SF_DIR)
    return Miner(lines, T.from_profit(baskets.profit_of(lines), beta, glmu)).search(engine, **options)[0]


def levelwise(spark: SparkSession) -> DataFrame:
    lines = workloads.order_brand(spark, SF_DIR)
    return baselines.Levelwise(lines, T.from_profit(baskets.profit_of(lines), 10_000, 40_000), with_tids=True).huis()


def main() -> None:
    spark = to_workers(session())
    spark.sparkContext.setLogLevel("ERROR")
    mined(spark, "order_brand", 200_000, 0, "hybrid", {}).count()  # warm-up
    seconds, rows = {}, {}
    runs = {name: (lambda how=how: mined(spark, *how)) for name, how in MINED.items()} | {"levelwise_tid_order_brand": lambda: levelwise(spark)}
    for name, run in runs.items():
        began = time.perf_counter()
        rows[name] = run().count()
        seconds[name] = round(time.perf_counter() - began, 3)
        spark.catalog.clearCache()
    out = {"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "rows": rows, "sf": os.path.basename(SF_DIR.rstrip("/"))}
    if os.environ.get("BENCH_FULL"):
        from utilmine.operators import stats

        lines, grid = workloads.order_brand(spark, SF_DIR), [(g, b) for g in (40_000, 60_000, 100_000) for b in (5_000, 10_000, 20_000)]
        families = {"runtime": stats.runtimes(lines, grid), "patterns": stats.pattern_counts(lines, grid), "pruning": stats.pruning_counts(lines, grid)}
        root = os.path.dirname(SF_DIR.rstrip("/"))
        families["scale"] = stats.scalability({s: workloads.order_brand(spark, f"{root}/{s}") for s in ("sf0.001", "sf0.01", "sf0.1")}, 40_000, 10_000)
        out["experiments"] = {k: [r.asDict() for r in v.collect()] for k, v in families.items()}
    print(json.dumps(out))


if __name__ == "__main__":
    main()
