"""Exactness checks between pattern tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def diff(a: DataFrame, b: DataFrame, columns: tuple[str, ...] = ("key", "utility", "miu", "support")) -> DataFrame:
    """side, and columns: rows of a that b lacks (missing) and of b that a lacks (extra)."""
    one, two = a.select(*columns), b.select(*columns)
    return one.exceptAll(two).withColumn("side", F.lit("missing")).unionByName(two.exceptAll(one).withColumn("side", F.lit("extra")))


def subset(inner: DataFrame, outer: DataFrame) -> DataFrame:
    """Keys of inner that outer lacks; empty if every high-utility itemset is among the kept itemsets of the level-wise method."""
    return inner.select("key").join(outer.select("key"), "key", "left_anti")
