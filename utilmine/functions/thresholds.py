"""Per-item minimum utilities: tables of (item, mu), ways to derive them, and the thresholds of itemsets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def from_table(thresholds: DataFrame, items: DataFrame | None = None, default: int | None = None) -> DataFrame:
    """A given table, checked: one mu for each item, none negative. Items without one get the default, or are an error at run time."""
    given = thresholds.select("item", F.col("mu").cast("long").alias("mu"))
    checked = given.groupBy("item").agg(F.min("mu").alias("mu"), F.count_distinct("mu").alias("__n"))
    checked = checked.select("item", F.when((F.col("__n") == 1) & (F.col("mu") >= 0), F.col("mu")).otherwise(F.raise_error(F.lit("an item needs one threshold that is not negative")).cast("long")).alias("mu"))
    if items is None:
        return checked
    missing = F.lit(default).cast("long") if default is not None else F.raise_error(F.lit("an item has no threshold")).cast("long")
    return items.select("item").distinct().join(checked, "item", "left").select("item", F.coalesce("mu", missing).alias("mu"))


def from_profit(profit: DataFrame, beta: int | Column, glmu: int) -> DataFrame:
    """mu = max(beta * pr, glmu); beta is a number or a column of profit, such as spread()."""
    factor = beta if isinstance(beta, Column) else F.lit(beta)
    return profit.select("item", F.greatest((factor * F.col("pr")).cast("long"), F.lit(glmu).cast("long")).alias("mu"))


def spread(low: int, high: int) -> Column:
    """A factor for each item between low and high, spread by the item's number; deterministic."""
    return F.lit(low) + F.pmod(F.col("item").cast("long") * 31, F.lit(high - low + 1))


def uniform(items: DataFrame, glmu: int) -> DataFrame:
    return items.select("item").distinct().select("item", F.lit(glmu).cast("long").alias("mu"))


def lmu(thresholds: DataFrame) -> DataFrame:
    """One row: the least threshold."""
    return thresholds.agg(F.min("mu").alias("lmu"))


def miu(itemsets: DataFrame, thresholds: DataFrame) -> DataFrame:
    """key, items -> key, miu: the least threshold among the items of each set."""
    return itemsets.select("key", F.explode("items").alias("item")).join(thresholds, "item").groupBy("key").agg(F.min("mu").alias("miu"))


def glmu_of(lines: DataFrame, ratio: float) -> int:
    """A floor for thresholds as a share of the whole utility, so that it grows with the data. One number comes to the driver."""
    return int(ratio * (lines.agg(F.sum("u")).first()[0] or 0))
