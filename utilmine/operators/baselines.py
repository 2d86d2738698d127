"""The methods that the miners are measured against: level-wise generate and test, uniform thresholds, exhaustive and frequency-based ones."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from utilmine.functions import thresholds as T
from utilmine.operators.mine import Miner, decoded
from utilmine.plans import encode
from utilmine.plans.cut import broadcast_if, cached, written


@dataclass
class LevelwiseStats:
    """By level: candidates generated and kept (those whose transaction-weighted utility reaches their threshold)."""

    levels: list[dict] = field(default_factory=list)

    def total(self, what: str) -> int:
        return sum(x[what] for x in self.levels)


class Levelwise:
    """Two phases: itemsets whose transaction-weighted utility reaches their threshold, level by level from sorted prefixes; then a
    scan for exact utilities. A scan meets baskets along the kept prefixes of candidates, one item at a time. with_tids keeps the baskets of
    each candidate with what follows in them, so that later levels and the second phase read only these."""

    def __init__(self, lines: DataFrame, thresholds: DataFrame, with_tids: bool = False, subset_check: bool = False, max_len: int | None = None, keep_ordinary_closure: bool = False):
        m = Miner(lines, thresholds)
        self.dictionary, self.enc = m.dictionary, m.merged
        self.with_tids, self.subset_check, self.max_len, self.naive = with_tids, subset_check, max_len, keep_ordinary_closure
        self.stats = LevelwiseStats()
        self.levels: list[DataFrame] = []  # node, mu1, twu
        self.tids: list[DataFrame] = []  # node, tid, tu, n, iu, tail

    def _single(self) -> DataFrame:
        items = self.dictionary.items
        ok = F.col("twu") >= F.col("mu")
        return items.select(F.array("rank").alias("node"), F.col("mu").alias("mu1"), "twu", ok.alias("starts"))

    def _pairs(self, single: DataFrame) -> DataFrame:
        """Candidates of two items: one that starts an itemset and any later promising one. The second ranks come from a sequence."""
        first = F.element_at("node", 1)
        follow = F.explode(F.sequence(first + 1, F.lit(self.dictionary.n)))
        starts = single.where("starts").where(first < self.dictionary.n)
        if self.naive:  # the wrong closure: every single item must reach its own threshold
            own = single.where("starts").select(F.element_at("node", 1).alias("y"))
            return starts.select("node", "mu1", follow.alias("y")).join(own, "y").select(F.concat("node", F.array("y")).alias("node"), "mu1")
        return starts.select("node", "mu1", follow.alias("y")).select(F.concat("node", F.array("y")).alias("node"), "mu1")

    def candidates(self, level: DataFrame, k: int) -> DataFrame:
        """node, mu1 of k items from two kept ones of k - 1 that differ in the last item."""
        parts = level.select(F.slice("node", 1, k - 2).alias("prefix"), F.element_at("node", -1).alias("last"), "mu1")
        a, b = parts.alias("a"), parts.alias("b")
        joined = a.join(b, (F.col("a.prefix") == F.col("b.prefix")) & (F.col("a.last") < F.col("b.last")))
        out = joined.select(F.concat("a.prefix", F.array("a.last", "b.last")).alias("node"), F.col("a.mu1").alias("mu1"))
        if self.subset_check or self.naive:
            # subsets with the first item have the same threshold and no less weight; the wrong closure asks for all subsets
            least = 1 if self.naive else 2
            subsets = out.select("node", "mu1", F.explode(F.transform(F.sequence(F.lit(least), F.lit(k)), lambda i: F.filter("node", lambda x, j: j != i - 1))).alias("part"))
            found = subsets.join(level.select(F.col("node").alias("part")), "part", "left_semi").groupBy("node", "mu1").agg(F.count(F.lit(1)).alias("n"))
            out = found.where(F.col("n") == k - least + 1).select("node", "mu1")
        return out

    def _rows(self) -> DataFrame:
        """node, tid, tu, n, iu, tail: a row for each item of a basket, with what follows it there."""
        each = self.enc.select("tid", "tu", "n", F.posexplode("its").alias("p", "x"), "its")
        return each.select(F.array("x.r").alias("node"), "tid", "tu", "n", F.col("x.u").alias("iu"), encode.tail_after(F.col("its"), F.col("p")).alias("tail"))

    def _longer(self, rows: DataFrame, wanted: DataFrame, n: int) -> DataFrame:
        """The rows of wanted itemsets, n of them, that have one item more."""
        each = rows.select("*", F.posexplode("tail").alias("p", "x"))
        below = each.select(F.concat("node", F.array("x.r")).alias("node"), "tid", "tu", "n", (F.col("iu") + F.col("x.u")).alias("iu"), encode.tail_after(F.col("tail"), F.col("p")).alias("tail"))
        return below.join(broadcast_if(wanted, n), "node")

    def _met(self, k: int) -> DataFrame:
        """From a scan of all baskets, the rows of kept itemsets of k items."""
        rows = self._rows()
        for i, level in enumerate(self.levels[:k]):
            kept, n = level.select("node"), self.stats.levels[i]["kept"]
            rows = self._longer(rows, kept, n) if i else rows.join(broadcast_if(kept, n), "node")
        return rows

    def htwuis(self) -> DataFrame:
        """node, mu1, twu of all kept itemsets."""
        single = cached(self._single())
        kept = written(single.where("starts").drop("starts"))
        self.levels = [kept]
        self.stats.levels = [{"level": 1, "candidates": self.dictionary.n, "kept": kept.count()}]
        if self.with_tids:
            self.tids = [self._met(1)]
        k = 2
        while self.max_len is None or k <= self.max_len:
            wanted = written(self._pairs(single) if k == 2 else self.candidates(kept, k))
            n = wanted.count()
            if not n:
                break
            rows = self._longer(self.tids[-1] if self.with_tids else self._met(k - 1), wanted, n)
            rows = written(rows) if self.with_tids else rows
            scores = rows.groupBy("node", "mu1").agg(F.sum("tu").alias("twu"))
            kept = written(scores.where("twu >= mu1"))
            found = kept.count()
            self.stats.levels.append({"level": k, "candidates": n, "kept": found})
            if not found:
                break
            self.levels.append(kept)
            if self.with_tids:
                self.tids.append(rows.drop("mu1").join(broadcast_if(kept.select("node"), found), "node", "left_semi"))
            k += 1
        out = self.levels[0]
        for more in self.levels[1:]:
            out = out.unionByName(more)
        return out

    def huis(self) -> DataFrame:
        """The second phase: items, key, k, utility, miu, support of the kept itemsets whose utility reaches their threshold."""
        if not self.levels:
            self.htwuis()
        out = rows = None
        for k, level in enumerate(self.levels, 1):
            if self.with_tids:
                rows = self.tids[k - 1]
            else:  # one more scan, whose rows of a level are those that the next one goes on from
                rows = written(self._longer(rows, level.select("node"), self.stats.levels[k - 1]["kept"])) if rows is not None else self._met(1)
            exact = rows.groupBy("node").agg(F.sum("iu").alias("iu"), F.sum("n").alias("support")).join(broadcast_if(level.select("node", "mu1"), self.stats.levels[k - 1]["kept"]), "node")
            own = exact.where("iu >= mu1").select("node", "mu1", "iu", "support")
            out = own if out is None else out.unionByName(own)
        return decoded(out, self.dictionary)

    def named(self) -> DataFrame:
        """key, twu, miu of the kept itemsets."""
        rows = self.htwuis().select("node", "mu1", F.col("twu").alias("iu"), F.lit(0).cast("long").alias("support"))
        return decoded(rows, self.dictionary).select("key", F.col("utility").alias("twu"), "miu")


def levelwise(lines: DataFrame, thresholds: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    """(kept itemsets, high-utility itemsets)."""
    run = Levelwise(lines, thresholds, **options)
    return run.named(), run.huis()


def levelwise_tid(lines: DataFrame, thresholds: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    return levelwise(lines, thresholds, with_tids=True, **options)


def uniform(lines: DataFrame, glmu: int, variant: str = "base", order_by: str = "twu", **options) -> DataFrame:
    """One threshold for all items: the utility-list miner (base), with pair pruning (pair) or lookahead (look)."""
    m = Miner(lines, T.uniform(lines, glmu), order_by)
    return m.search(variant=variant, **options)[0]


def naive_closure(lines: DataFrame, thresholds: DataFrame) -> DataFrame:
    """A negative control: the ordinary closure, under which itemsets are lost."""
    return Levelwise(lines, thresholds, keep_ordinary_closure=True).huis()


def enumerate_all(lines: DataFrame, thresholds: DataFrame, max_len: int | None = None) -> DataFrame:
    """items, key, k, utility, miu, support, twu of every itemset that some basket holds, from all sub-arrays of each basket.

    Each line brings its threshold, so an itemset's is a minimum of the same aggregate and no table of itemsets is joined. A sub-array is a number
    whose bits choose items, in two halves that are exploded one after the other: no row holds more than the square root of a basket's sub-arrays.
    """
    priced = lines.select("tid", "item", "u").join(thresholds.select("item", "mu"), "item", "left")
    whole = priced.groupBy("tid").agg(F.sum("u").alias("tu"), F.array_sort(F.collect_list(F.struct("item", "u", "mu"))).alias("its"))
    half = F.floor(F.size("its") / 2).cast("int")
    bits = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.call_function("shiftleft", F.lit(1).cast("long"), n) - 1))
    high = whole.select("tu", "its", half.alias("half"), bits(F.size("its") - half).alias("high"))
    low = high.select("tu", "its", "half", "high", bits(F.col("half")).alias("low"))
    chosen = lambda x, i: F.getbit(F.when(i < F.col("half"), F.col("low")).otherwise(F.col("high")), F.when(i < F.col("half"), i).otherwise(i - F.col("half"))) == 1
    longest = F.bit_count("low") + F.bit_count("high")
    sets = low.where((longest > 0) & (longest <= max_len) if max_len else longest > 0).select("tu", F.filter("its", chosen).alias("s"))
    each = sets.select("tu", F.col("s.item").alias("items"), F.aggregate("s", F.lit(0).cast("long"), lambda a, x: a + x["u"]).alias("u"), F.array_min("s.mu").alias("miu"))
    sums = each.groupBy("items").agg(F.sum("u").alias("utility"), F.min("miu").alias("miu"), F.count(F.lit(1)).alias("support"), F.sum("tu").alias("twu"))
    key = F.array_join(F.transform("items", lambda x: x.cast("string")), ",")
    return sums.where("miu is not null").select("items", key.alias("key"), F.size("items").alias("k"), "utility", "miu", "support", "twu")


def enumerated_huis(lines: DataFrame, thresholds: DataFrame, max_len: int | None = None) -> DataFrame:
    return enumerate_all(lines, thresholds, max_len).where("utility >= miu").drop("twu")


def frequent(lines: DataFrame, min_support: float) -> DataFrame:
    """key, support of frequent itemsets by the built-in pattern growth; min_support is a share of baskets."""
    from pyspark.ml.fpm import FPGrowth

    baskets = lines.groupBy("tid").agg(F.collect_set("item").alias("items"))
    found = FPGrowth(itemsCol="items", minSupport=min_support).fit(baskets).freqItemsets
    return found.select(F.array_join(F.transform(F.array_sort("items"), lambda x: x.cast("string")), ",").alias("key"), F.size("items").alias("k"), F.col("freq").alias("support"))


def frequent_multi(lines: DataFrame, supports: DataFrame, max_len: int | None = None) -> DataFrame:
    """key, k, support, miu of itemsets whose support reaches the least of their items' supports(item, mis)."""
    m = Miner(lines.withColumn("u", F.lit(1).cast("long")), supports.select("item", F.col("mis").cast("long").alias("mu")))
    return m.search(variant="base", measure="support", max_len=max_len)[0].select("key", "k", "support", "miu")
