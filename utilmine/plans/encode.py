"""Baskets encoded for the search: arrays of (rank, utility, remaining utility), in the order of ranks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from utilmine.functions import measures, ordering
from utilmine.plans.cut import broadcast_if, cached, written


class Dictionary:
    """The promising items: item, mu, twu, u, support, rank. n, lmu: their number and the least threshold of all items."""

    def __init__(self, lines: DataFrame, thresholds: DataFrame, order_by: str = "mu", tu_scope: str = "all", prune: bool = True):
        thresholds = cached(thresholds.select("item", "mu"))  # read twice, and often made from all lines
        measured = measures.twu_items(lines).join(thresholds.select("item", "mu"), "item", "left")
        mu = F.coalesce("mu", F.raise_error(F.lit("an item has no threshold")).cast("long"))
        measured = measured.withColumn("mu", mu)
        least = F.broadcast(thresholds.agg(F.min("mu").alias("lmu")))  # one row
        kept = measured.join(least, (F.col("twu") >= F.col("lmu")) if prune else F.lit(True))
        kept = cached(kept)
        # written, as plans spell out what made the cached tables that they read, at every step that they are adapted
        self.items = cached(written(ordering.rank_items(kept, order_by, kept.count()).select("item", "rank", "mu", "twu", "u", "support", "lmu")))
        row = self.items.agg(F.count(F.lit(1)), F.max("lmu")).first()
        self.n, self.lmu, self.tu_scope = row[0], row[1], tu_scope

    def names(self) -> DataFrame:
        return broadcast_if(self.items.select("rank", "item"), self.n)


def baskets(lines: DataFrame, dictionary: Dictionary) -> DataFrame:
    """tid, tu, its: ARRAY<STRUCT<r, u, ru>> by r. tu over all lines, or over promising ones with tu_scope="promising".

    One exchange by tid: the utility of the basket, the sums over later items and the array use the same
    partitioning. The dictionary is joined by broadcast unless it is large.
    """
    whole = measures.with_tu(lines)
    kept = whole.select("tid", "item", "u", "tu").join(broadcast_if(dictionary.items.select("item", "rank"), dictionary.n), "item")
    later = Window.partitionBy("tid").orderBy(F.col("rank").desc()).rowsBetween(Window.unboundedPreceding, -1)
    kept = kept.withColumn("ru", F.coalesce(F.sum("u").over(later), F.lit(0).cast("long")))
    tu = F.sum("u") if dictionary.tu_scope == "promising" else F.first("tu")
    entry = F.struct(F.col("rank").alias("r"), "u", "ru")
    return kept.groupBy("tid").agg(tu.alias("tu"), F.array_sort(F.collect_list(entry)).alias("its"))


def merged(enc: DataFrame) -> DataFrame:
    """tid (the least), tu, n, its: baskets of the same items as one, with their number and added utilities. Every sum of a search over the n
    baskets is the same. Written if at most half as many baskets are left; else each stays for itself, with n = 1."""
    ranks = F.transform("its", lambda x: x["r"])
    baskets, sets = enc.agg(F.count(F.lit(1)), F.approx_count_distinct(F.xxhash64(ranks))).first()
    if 2 * sets > baskets:
        return enc.withColumn("n", F.lit(1).cast("long"))
    each = enc.select("tid", "tu", ranks.alias("ranks"), F.posexplode("its").alias("p", "x"))
    sums = each.groupBy("ranks", "p").agg(F.min("tid").alias("tid"), F.sum("tu").alias("tu"), F.count(F.lit(1)).alias("n"), F.sum("x.u").alias("u"), F.sum("x.ru").alias("ru"))
    entry = F.struct(F.col("ranks")[F.col("p")].alias("r"), "u", "ru")
    whole = sums.groupBy("ranks").agg(F.min("tid").alias("tid"), F.max("tu").alias("tu"), F.max("n").alias("n"), F.array_sort(F.collect_list(entry)).alias("its"))
    return written(whole.drop("ranks"))


def tail_after(its: Column, position: Column) -> Column:
    """What stands after a position (from 0) of a basket."""
    return F.slice(its, position + 2, F.size(its))


def minus(basket: Column, items: Column) -> Column:
    return F.array_except(basket, items)
