"""The threshold-ordered enumeration tree over a small dictionary, for teaching and tests."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def size(m: int) -> int:
    """Itemsets over m items."""
    return 2**m - 1


def all_nodes(spark: SparkSession, m: int) -> DataFrame:
    """node: every array of increasing ranks 1..m, for m up to 20."""
    if m > 20:
        raise ValueError("the whole tree is for small dictionaries")
    bits = spark.range(1, 2**m).select(F.col("id").alias("b"))
    return bits.select(F.filter(F.sequence(F.lit(1), F.lit(m)), lambda r: F.expr("b").bitwiseAND(F.pow(F.lit(2), r - 1).cast("long")) > 0).alias("node"))


def children(node: list[int], m: int) -> list[list[int]]:
    return [[*node, r] for r in range((node[-1] if node else 0) + 1, m + 1)]


def descendants(spark: SparkSession, node: list[int], m: int) -> DataFrame:
    own = F.array(*(F.lit(r) for r in node))
    return all_nodes(spark, m).where((F.size("node") > len(node)) & (F.slice("node", 1, len(node)) == own)) if node else all_nodes(spark, m)
