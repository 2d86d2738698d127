"""Generated baskets for scale runs, in the manner of published basket generators: weighted patterns, corrupted, filling baskets of Poisson length."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def quest_like(spark: SparkSession, n: int, items: int = 4000, mean_len: int = 10, pattern_len: int = 4, patterns: int = 2000, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """lines(tid, item, qty, u, pr) of n baskets, from spark.range and hashes alone: the same rows for any partitioning.

    A basket draws about mean_len / pattern_len patterns by skewed weights, each of whose items stays with chance 0.75.
    """
    u = lambda *c: (F.shiftrightunsigned(F.xxhash64(F.lit(seed), *c), 12) + 0.5) / float(1 << 52)
    base = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    # the sum of uniform draws about a mean: between 1 and 2 * mean - 1 patterns
    mean = mean_len / (pattern_len * 0.75)
    baskets = base.select(F.col("id").alias("tid"), F.explode(F.sequence(F.lit(1), 1 + F.floor(u("id", F.lit("n")) * (2 * mean - 1)).cast("int"))).alias("slot"))
    drawn = baskets.withColumn("pattern", F.floor(F.pow(u("tid", "slot"), 2) * patterns))
    each = drawn.select("tid", "pattern", F.explode(F.sequence(F.lit(1), F.lit(pattern_len))).alias("j"))
    kept = each.where(u("tid", "pattern", "j") < 0.75)
    item = 1 + F.floor(F.pow(u("pattern", "j", F.lit("i")), 1.5) * items)
    lines = kept.select("tid", item.cast("long").alias("item")).distinct()
    qty = 1 + F.floor(u("tid", "item", F.lit("q")) * 10)
    pr = 1 + F.floor(u("item", F.lit("p")) * 100)
    return lines.select("tid", "item", qty.cast("long").alias("qty"), (qty * pr).cast("long").alias("u"), pr.cast("long").alias("pr"))
