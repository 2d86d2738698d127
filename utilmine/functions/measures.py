"""Utilities of items, baskets and itemsets, and the transaction-weighted bound, over lines(tid, item, qty, u, pr)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def line_utility(lines: DataFrame, profit: DataFrame) -> DataFrame:
    """lines(tid, item, qty) with pr and u = qty * pr; a missing profit drops nothing and fails."""
    joined = lines.drop("pr", "u").join(profit.select("item", "pr"), "item", "left")
    pr = F.coalesce("pr", F.raise_error(F.lit("an item has no profit")).cast("long"))
    return joined.withColumn("pr", pr).withColumn("u", (F.col("qty") * F.col("pr")).cast("long"))


def asof_profit(lines: DataFrame, prices: DataFrame) -> DataFrame:
    """lines(tid, item, qty, ts) with the price valid at ts: prices(item, pr, valid_from), the last one that is not later.

    Prices are as many as items times changes and their size is often underestimated, so both sides are sorted by item and none is broadcast.
    """
    spans = prices.withColumn("valid_to", F.lead("valid_from").over(Window.partitionBy("item").orderBy("valid_from")))
    inside = (lines["item"] == spans["item"]) & (F.col("ts") >= F.col("valid_from")) & (F.col("valid_to").isNull() | (F.col("ts") < F.col("valid_to")))
    return lines.join(spans.hint("merge"), inside).select(*(lines[c] for c in lines.columns if c not in ("pr", "u")), "pr", (F.col("qty") * F.col("pr")).cast("long").alias("u"))


def basket_utility(lines: DataFrame) -> DataFrame:
    return lines.groupBy("tid").agg(F.sum("u").alias("tu"))


def with_tu(lines: DataFrame) -> DataFrame:
    """lines with tu, the utility of their basket; lines that have it already stay as they are."""
    return lines if "tu" in lines.columns else lines.withColumn("tu", F.sum("u").over(Window.partitionBy("tid")))


def twu_items(lines: DataFrame) -> DataFrame:
    """item, u, twu, support."""
    return with_tu(lines).groupBy("item").agg(F.sum("u").alias("u"), F.sum("tu").alias("twu"), F.count(F.lit(1)).alias("support"))


def tids(lines: DataFrame, itemsets: DataFrame) -> DataFrame:
    """key, tid, u: the baskets that hold all items of a set, with the set's utility there. itemsets(key, items)."""
    wanted = itemsets.select("key", F.size("items").alias("k"), F.explode("items").alias("item"))
    found = lines.select("tid", "item", "u").join(wanted, "item").groupBy("key", "k", "tid").agg(F.count(F.lit(1)).alias("n"), F.sum("u").alias("u"))
    return found.where("n = k").select("key", "tid", "u")


def itemset_utility(lines: DataFrame, itemsets: DataFrame) -> DataFrame:
    return tids(lines, itemsets).groupBy("key").agg(F.sum("u").alias("u"), F.count(F.lit(1)).alias("support"))


def support(lines: DataFrame, itemsets: DataFrame) -> DataFrame:
    return itemset_utility(lines, itemsets).select("key", "support")


def twu_itemsets(lines: DataFrame, itemsets: DataFrame) -> DataFrame:
    return tids(lines, itemsets).join(basket_utility(lines), "tid").groupBy("key").agg(F.sum("tu").alias("twu"))


def is_htwui(twu: Column | str = "twu", miu: Column | str = "miu") -> Column:
    return (F.col(twu) if isinstance(twu, str) else twu) >= (F.col(miu) if isinstance(miu, str) else miu)


def is_hui(u: Column | str = "u", miu: Column | str = "miu") -> Column:
    """No less than the threshold: a utility equal to it counts."""
    return is_htwui(u, miu)
