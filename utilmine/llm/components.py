"""Connected components of a table of links, by label propagation with pointer jumping over written tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from utilmine.llm.shared import written


def components(links: DataFrame) -> DataFrame:
    """links(a, b) of longs, in any direction -> node, label: the least node of its component, for every node with a link.

    Each round takes the least label among neighbours, then the label of that label, so that chains
    shrink by half. Only a count of changed labels comes to the driver.
    """
    both = written(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    labels = written(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("label")))
    while True:
        near = both.join(labels, F.col("b") == F.col("node")).groupBy("a").agg(F.min("label").alias("near"))
        step = labels.join(near, F.col("node") == F.col("a")).select("node", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        above = labels.select(F.col("node").alias("up"), F.col("label").alias("up_label"))
        labels = written(step.join(above, F.col("label") == F.col("up")).select("node", F.least("label", "up_label").alias("label"), (F.col("old") != F.least("label", "up_label")).alias("changed")))
        if not labels.where("changed").limit(1).count():
            return labels.select("node", "label")
