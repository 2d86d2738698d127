"""Utility-lists as rows: (node, tid, iu, ru), one row for each basket that holds the itemset."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def item_lists(enc: DataFrame) -> DataFrame:
    """The lists of single items: node, tid, iu, ru and the prefix's utility piu (0)."""
    one = enc.select("tid", F.explode("its").alias("x"))
    return one.select(F.array("x.r").alias("node"), "tid", F.col("x.u").alias("iu"), F.col("x.ru").alias("ru"), F.lit(0).cast("long").alias("piu"))


def construct(lists: DataFrame) -> DataFrame:
    """The lists of one more item, from siblings joined on (prefix, tid): iu = iu + iu - piu, ru of the later one; bound: iu + ru of the earlier one, for lookahead."""
    parts = lists.select(F.slice("node", 1, F.size("node") - 1).alias("prefix"), F.element_at("node", -1).alias("last"), "tid", "iu", "ru", "piu")
    a, b = parts.alias("a"), parts.alias("b")
    pairs = a.join(b, (F.col("a.prefix") == F.col("b.prefix")) & (F.col("a.tid") == F.col("b.tid")) & (F.col("a.last") < F.col("b.last")))
    return pairs.select(F.concat("a.prefix", F.array("a.last", "b.last")).alias("node"), F.col("a.tid").alias("tid"), (F.col("a.iu") + F.col("b.iu") - F.col("a.piu")).alias("iu"), F.col("b.ru").alias("ru"), F.col("a.iu").alias("piu"), (F.col("a.iu") + F.col("a.ru")).alias("bound"))


def information_table(lists: DataFrame) -> DataFrame:
    """node, iu, ru, support: sums over a list."""
    return lists.groupBy("node").agg(F.sum("iu").alias("iu"), F.sum("ru").alias("ru"), F.count(F.lit(1)).alias("support"))


def pair_table(enc: DataFrame, min_twu: int = 0) -> DataFrame:
    """a, b, twu of the pairs of ranks a < b that occur together; those below min_twu are left out, as no threshold is lower."""
    each = enc.select("tu", F.posexplode("its").alias("p", "x"), "its")
    pairs = each.select("tu", F.col("x.r").alias("a"), F.explode(F.slice("its", F.col("p") + 2, F.size("its"))).alias("y"))
    return pairs.groupBy("a", F.col("y.r").alias("b")).agg(F.sum("tu").alias("twu")).where(F.col("twu") >= min_twu)


def pair_bounds(enc: DataFrame, cap: int) -> tuple[DataFrame, DataFrame]:
    """For long baskets, whose pairs would be quadratic: the pair table of baskets of up to cap items, and long_twu(r, twu) of items in longer ones.

    The weight of a pair is at most its weight in the table, 0 if absent, plus the lesser of its items' long weights.
    """
    long = enc.where(F.size("its") > cap).select("tu", F.explode("its").alias("x"))
    return pair_table(enc.where(F.size("its") <= cap)), long.groupBy(F.col("x.r").alias("r")).agg(F.sum("tu").alias("twu"))
