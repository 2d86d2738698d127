"""High-utility itemsets with per-item thresholds: the miners."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from utilmine.functions.measures import with_tu
from utilmine.operators import subtree
from utilmine.operators.search import VARIANTS, Frontier, ListJoin, Options, SearchStats
from utilmine.plans import encode, lists, planner
from utilmine.plans.cut import cached

#: auto asks the planner for the engine and for how rows carry tails.
ENGINES = ("frontier", "lists", "subtree", "hybrid", "auto")
ROOT_BUDGET = planner.ROOT_BUDGET
NAMES_IN_A_ROW = 500_000
GROUPS_A_SLOT = 4


def decoded(found: DataFrame, dictionary: encode.Dictionary) -> DataFrame:
    """items (ascending), key, k, utility, miu, support of itemsets given by ranks."""
    out = found
    if dictionary.n <= NAMES_IN_A_ROW:
        names = dictionary.items.agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "item"))), lambda x: x["item"]).alias("names"))
        out = out.join(F.broadcast(names)).withColumn("items", F.array_sort(F.transform("node", lambda r: F.element_at("names", r))))
    else:
        each = out.select("node", F.explode("node").alias("rank")).join(dictionary.names(), "rank")
        out = out.join(each.groupBy("node").agg(F.array_sort(F.collect_list("item")).alias("items")), "node")
    return out.select("items", F.array_join(F.transform("items", lambda x: x.cast("string")), ",").alias("key"), F.size("items").alias("k"), F.col("iu").alias("utility"), F.col("mu1").alias("miu"), "support")


class Miner:
    """Encoded baskets and dictionary of one input, for one or several searches.

    keep_lines caches the lines with their baskets' utilities, dealt by basket, between the two passes over them; without it the
    input is read and exchanged twice. Lines that carry tu are taken as the caller keeps them.
    """

    def __init__(self, lines: DataFrame, thresholds: DataFrame, order_by: str = "mu", tu_scope: str = "all", keep_lines: bool = True):
        if "tu" in lines.columns:  # with their baskets' utilities: kept by the caller
            lines = lines.select("tid", "item", "u", "tu")
        else:
            lines = with_tu(lines.select("tid", "item", "u"))
            lines = cached(lines) if keep_lines else lines
        self.dictionary = encode.Dictionary(lines, thresholds, order_by, tu_scope)
        self.enc = cached(encode.baskets(lines, self.dictionary))

    @cached_property
    def merged(self) -> DataFrame:
        """What is searched: the baskets, those of the same items as one."""
        return cached(encode.merged(self.enc))

    def roots(self, names: list) -> DataFrame:
        return self.dictionary.items.where(F.col("item").isin(names)).select("rank")

    def search(self, engine: str = "frontier", root_budget: int = ROOT_BUDGET, want_stats: bool = False, **options) -> tuple[DataFrame, SearchStats]:
        o = Options(**options)
        if o.variant not in VARIANTS or engine not in ENGINES:
            raise ValueError(f"variant is one of {VARIANTS}, engine one of {ENGINES}")
        if engine == "auto":
            chosen = planner.plan(self.merged, self.dictionary, root_budget=root_budget)
            engine, o.carry = chosen.engine, chosen.carry
        if engine in ("frontier", "lists"):
            run = (Frontier if engine == "frontier" else ListJoin)(self.merged, self.dictionary, o)
            return decoded(run.run(want_stats), self.dictionary), run.stats
        return decoded(self._walked(o, engine, root_budget), self.dictionary), SearchStats()

    def visited(self, variant: str, root_budget: int = ROOT_BUDGET, **options) -> tuple[int, int]:
        """Itemsets that a search visits, and those it finds: counted by walks in workers, or by the frontier if a root or the pair table is too heavy."""
        o = Options(variant=variant, **options)
        weights, groups, heavy = self._dealt("hybrid", root_budget)
        if not heavy:
            table = self._shipped(o)
            if not self._has_pairs(o) or table is not None:  # without the pair table more would be visited
                counts = subtree.count_subtrees(subtree.packed(self.merged, self.dictionary, groups, table, o.roots), o, table, self.dictionary.n + 1, groups)
                return tuple(x or 0 for x in counts.agg(F.sum("visited"), F.sum("found")).first())
        run = Frontier(self.merged, self.dictionary, o)
        found = run.run().count()
        return run.stats.total("nodes"), found

    def kept(self, root_budget: int = ROOT_BUDGET) -> int:
        """Itemsets whose transaction-weighted utility reaches their threshold, which are those that level-wise methods keep: counted by walks in workers (or the
        frontier if a root is too heavy) as itemsets whose support does, where a basket counts as often as its utility. No candidate is made that no basket holds."""
        o, weighed = Options(variant="pair", measure="support"), self.merged.withColumn("n", F.col("tu"))
        groups, heavy = self._dealt("hybrid", root_budget)[1:]
        if heavy:
            return Frontier(weighed, self.dictionary, o).run().count()
        table = self._shipped(o)
        counts = subtree.count_subtrees(subtree.packed(weighed, self.dictionary, groups, table), o, table, self.dictionary.n + 1, groups)
        return counts.agg(F.sum("found")).first()[0] or 0

    @cached_property
    def _weights(self) -> DataFrame:
        return cached(planner.root_weights(self.merged))

    def _dealt(self, engine: str, root_budget: int) -> tuple[DataFrame, int, int]:
        limit = root_budget if engine == "hybrid" else None
        total, heavy = self._weights.agg(F.coalesce(F.sum("weight"), F.lit(0)), F.count(F.when(F.col("weight") > limit, 1)) if limit else F.lit(0)).first()
        # several groups for each slot, as their walks differ in length
        slots = GROUPS_A_SLOT * self.merged.sparkSession.sparkContext.defaultParallelism
        return self._weights, max(slots, -(-total // root_budget)), heavy

    @staticmethod
    def _has_pairs(o: Options) -> bool:
        return o.pair and not o.pair_cap

    def _pairs(self, o: Options) -> DataFrame | None:
        return lists.pair_table(self.merged, self.dictionary.lmu or 0) if self._has_pairs(o) else None

    def _shipped(self, o: Options):
        """The pair table for workers, made once for all searches and counts of this input."""
        if self._has_pairs(o) and not hasattr(self, "_table"):
            self._table = subtree.shipped(self._pairs(o), self.dictionary)
        return self._table if self._has_pairs(o) else None

    def _walked(self, o: Options, engine: str, root_budget: int) -> DataFrame:
        """Subtrees in workers. hybrid leaves roots above the budget to the frontier; subtree walks them all."""
        weights, groups, heavy = self._dealt(engine, root_budget)
        limit = root_budget
        light = weights if not heavy else weights.where(F.col("weight") <= limit)
        chosen = light.select(F.col("root").alias("rank"))
        chosen = chosen.join(o.roots, "rank", "left_semi") if o.roots is not None else chosen if heavy else None
        table = self._shipped(o)
        rows = subtree.packed(self.merged, self.dictionary, groups, table, chosen)
        found = subtree.mine_subtrees(rows, o, table, self.dictionary.n + 1, groups)
        if not heavy:
            return found
        large = weights.where(F.col("weight") > limit).select(F.col("root").alias("rank"))
        large = large.join(o.roots, "rank", "left_semi") if o.roots is not None else large
        return found.unionByName(self.in_waves(o, weights, large))

    def in_waves(self, o: Options, weights: DataFrame, roots: DataFrame, wave_budget: int = planner.WAVE_BUDGET) -> DataFrame:
        """The frontier over roots in waves of bounded weight, small ones first; subtrees of different roots are independent."""
        sized = roots.join(weights, F.col("rank") == F.col("root"))
        before = F.sum("weight").over(Window.orderBy("weight", "rank").rowsBetween(Window.unboundedPreceding, -1))
        waves = cached(sized.select("rank", F.floor(F.coalesce(before, F.lit(0)) / wave_budget).alias("wave")))
        mean = self.merged.agg(F.sum(F.size("its") * F.col("n")) / F.sum("n")).first()[0] or 0
        carry, out = "rejoin" if mean > planner.LONG_BASKETS else o.carry, None
        for (w,) in sorted(waves.select("wave").distinct().collect()):
            own = Options(**{**o.__dict__, "carry": carry, "roots": waves.where(F.col("wave") == w).select("rank")})
            found = Frontier(self.merged, self.dictionary, own).run()
            out = found if out is None else out.unionByName(found)
        return out


def mine(lines: DataFrame, thresholds: DataFrame, variant: str = "both", engine: str = "frontier", order_by: str = "mu", tu_scope: str = "all", roots: list | None = None, **options) -> DataFrame:
    """items, key, k, utility, miu, support of all high-utility itemsets. lines(tid, item, u), thresholds(item, mu)."""
    m = Miner(lines, thresholds, order_by, tu_scope)
    return m.search(engine, variant=variant, roots=m.roots(roots) if roots is not None else None, **options)[0]
