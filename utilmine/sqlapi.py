"""SQL over the miners: views of lines, thresholds and patterns, and a table function that walks projected baskets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql.functions import udtf

from utilmine.operators.mine import Miner
from utilmine.operators.search import Options
from utilmine.operators.subtree import Walk, projected


@udtf(returnType="node array<int>, mu1 long, iu long, support long")
class MineSubtree:
    """mine_subtree(TABLE(tails) PARTITION BY root): itemsets of the roots of a partition. tails has root, mu1, n and tail (r, u, ru)."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, int, list]] = []

    def eval(self, row: Row) -> None:
        self.rows.append((row["mu1"], row["n"], row["tail"]))

    def terminate(self) -> Iterator[tuple]:
        sizes = np.array([len(t) for *_, t in self.rows])
        ends = np.cumsum(sizes)
        r, u, ru = (np.array([x[c] for *_, t in self.rows for x in t], np.int64) for c in ("r", "u", "ru"))
        n = np.repeat(np.array([n for _, n, _ in self.rows], np.int64), sizes)
        walk = Walk(r, u, ru, np.repeat(ends, sizes), n, Options(variant="look"), None, int(r.max(initial=0)) + 1)
        for found in walk.run(ends - sizes, np.array([m for m, *_ in self.rows], np.int64)):
            for row in found.to_pylist():
                yield row["node"], row["mu1"], row["iu"], row["support"]


def register(spark: SparkSession, lines: DataFrame, thresholds: DataFrame, huis: DataFrame | None = None) -> None:
    """Views lines, thresholds, items, tails (and huis), and the table function mine_subtree."""
    m = Miner(lines, thresholds)
    lines.createOrReplaceTempView("lines")
    thresholds.createOrReplaceTempView("thresholds")
    m.dictionary.items.createOrReplaceTempView("items")
    projected(m.merged, m.dictionary).createOrReplaceTempView("tails")
    if huis is not None:
        huis.createOrReplaceTempView("huis")
    spark.udtf.register("mine_subtree", MineSubtree)
