"""Reports over found patterns: tables with items, key, k, utility, miu, support."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def topn(huis: DataFrame, n: int, per_k: bool = False) -> DataFrame:
    """The n patterns of most utility (ties by key), of all or of each length."""
    if not per_k:
        return huis.orderBy(F.col("utility").desc(), "key").limit(n)
    return huis.withColumn("__n", F.row_number().over(Window.partitionBy("k").orderBy(F.col("utility").desc(), "key"))).where(F.col("__n") <= n).drop("__n")


def containing(huis: DataFrame, item) -> DataFrame:
    return huis.where(F.array_contains("items", item))


def maximal(huis: DataFrame) -> DataFrame:
    """Patterns without a longer pattern that holds them. A pattern meets others at its rarest item, so that postings stay short."""
    postings = huis.select("key", "k", "items", F.explode("items").alias("item"))
    weight = postings.groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    rarest = postings.join(weight, "item").groupBy("key").agg(F.min(F.struct("n", "item")).alias("r")).select("key", F.col("r.item").alias("item"))
    own = huis.join(rarest, "key").select("key", "k", "items", "item")
    others = postings.select(F.col("item").alias("i2"), F.col("k").alias("k2"), F.col("items").alias("items2"))
    held = own.join(others, (F.col("item") == F.col("i2")) & (F.col("k2") > F.col("k")) & (F.size(F.array_except("items", "items2")) == 0))
    return huis.join(held.select("key").distinct(), "key", "left_anti")


def rare_items(huis: DataFrame, thresholds: DataFrame, q: float) -> DataFrame:
    """Patterns with an item whose threshold is below the q-quantile of thresholds (a value of the table), and their rarest item's."""
    bar = F.broadcast(thresholds.agg(F.percentile("mu", F.lit(q)).alias("bar")))  # one row
    low = thresholds.join(bar, F.col("mu") < F.col("bar")).select("item", "mu")
    return huis.select("key", "k", "utility", F.explode("items").alias("item")).join(low, "item").groupBy("key", "k", "utility").agg(F.count(F.lit(1)).alias("rare_items"), F.min("mu").alias("least_mu"))


def share(huis: DataFrame, total: DataFrame) -> DataFrame:
    """key, utility and the running utility of patterns from the best on, beside the total utility of all baskets (one row, total).

    The running sum orders all patterns; it is a report over patterns, which are few beside their baskets.
    """
    order = Window.orderBy(F.col("utility").desc(), "key").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return huis.select("key", "utility", F.sum("utility").over(order).alias("running")).join(F.broadcast(total))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("key").join(b.select("key"), "key", "left_anti")


def utility_rollup(lines: DataFrame, dims: list[Column | str]) -> DataFrame:
    return lines.rollup(*dims).agg(F.sum("u").alias("u"), F.count(F.lit(1)).alias("n"))


def utility_cube(lines: DataFrame, dims: list[Column | str]) -> DataFrame:
    return lines.cube(*dims).agg(F.sum("u").alias("u"), F.count(F.lit(1)).alias("n"))


def customers_of(lines: DataFrame, itemsets: DataFrame) -> DataFrame:
    """key, customers: how many customers have a basket with all items of a set. lines carry cust."""
    from utilmine.functions.measures import tids

    owners = lines.groupBy("tid").agg(F.min("cust").alias("cust"))
    return tids(lines, itemsets).join(owners, "tid").groupBy("key").agg(F.count_distinct("cust").alias("customers"))
