"""Total orders of items as dense ranks from 1."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from utilmine.plans.cut import written

ORDERS = {"mu": ["mu", "item"], "twu": ["twu", "item"], "item": ["item"], "utility": ["u", "item"], "support": ["support", "item"]}
#: Dictionaries up to this size are ranked in one task; larger ones by ranges.
ONE_TASK = 10_000_000


def rank_items(items: DataFrame, by: str = "mu", n_items: int | None = None) -> DataFrame:
    """items with rank. Orders other than by mu are sound for equal thresholds only, where the first item of a set does not matter."""
    columns = ORDERS[by]
    if n_items is None or n_items <= ONE_TASK:
        return items.withColumn("rank", F.row_number().over(Window.orderBy(*columns)))
    # written, as a second computation of the ranges could cut elsewhere and give ranks that clash
    ranged = written(items.repartitionByRange(max(2, n_items // 1_000_000), *columns).withColumn("__part", F.spark_partition_id()))
    counts = ranged.groupBy("__part").count()
    before = counts.select("__part", F.coalesce(F.sum("count").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__before"))
    inside = F.row_number().over(Window.partitionBy("__part").orderBy(*columns))
    return ranged.join(F.broadcast(before), "__part").withColumn("rank", (inside + F.col("__before")).cast("int")).drop("__part", "__before")
