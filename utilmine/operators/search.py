"""The search for high-utility itemsets over encoded baskets, in three physical forms.

frontier: level by level in DataFrames. A candidate row is an itemset in a basket, with its utility there, what remains and the
    tail of the basket. A level explodes tails into children and sums them by itemset in one aggregate, which yields
    every bound at once: utility, utility plus remainder, and the lookahead residue.
lists: the same levels by joining the lists of sibling itemsets on (prefix, basket).
subtree: baskets projected on their first items, walked depth-first inside workers (see subtree.py).

Whether an itemset is visited depends on its prefixes and on earlier siblings alone, so all forms visit the same ones.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from utilmine.plans import lists
from utilmine.plans.cut import MOST_ROWS, broadcast_if, broadcast_if_small, cached, written
from utilmine.plans.encode import Dictionary

VARIANTS = ("base", "pair", "look", "both")
RESULT = "node array<int>, mu1 long, iu long, support long"


@dataclass
class Options:
    """variant: which prunings; max_len: the longest itemsets; roots: first ranks to search, all if none; seed: where the lookahead residue starts,
    "extended" (the extended itemset) or "prefix" (its prefix, looser); measure: "utility", or "support" for frequent itemsets;
    global_at_nodes: drop nodes whose transaction-weighted utility is below the least threshold; carry: "suffix" keeps tails in candidate rows,
    "rejoin" fetches them by basket, for long baskets; pair_cap: baskets longer than this bound pairs by their items' weights instead of being
    exploded into pairs (looser, still exact). Rows and nodes of each level are tables in the shared folder, which cuts the plan and survives lost executors."""

    variant: str = "both"
    max_len: int | None = None
    roots: DataFrame | None = None
    seed: str = "extended"
    measure: str = "utility"
    global_at_nodes: bool = False
    carry: str = "suffix"
    pair_cap: int | None = None

    @property
    def pair(self) -> bool:
        return self.variant in ("pair", "both")

    @property
    def look(self) -> bool:
        return self.variant in ("look", "both")


@dataclass
class SearchStats:
    """By level: nodes visited, joins attempted from them, candidates among these that were empty or cut by lookahead, occurrence rows."""

    levels: list[dict] = field(default_factory=list)

    def total(self, what: str) -> int:
        return sum(x[what] for x in self.levels)


class Frontier:
    def __init__(self, enc: DataFrame, dictionary: Dictionary, options: Options):
        # n: how many baskets of the same items a row stands for
        self.enc, self.dictionary, self.options = enc if "n" in enc.columns else enc.withColumn("n", F.lit(1).cast("long")), dictionary, options
        self.stats = SearchStats()
        self.pairs = self.long = None
        if options.pair and options.pair_cap:
            self.pairs, self.long = map(cached, lists.pair_bounds(enc, options.pair_cap))
        elif options.pair:
            self.pairs = cached(lists.pair_table(enc, dictionary.lmu or 0))
        most = dictionary.n * (dictionary.n - 1) // 2
        # a table that is small for its items alone is not counted before it is used
        self.n_pairs = 0 if not options.pair else most if most <= MOST_ROWS else self.pairs.count()
        self.late = False  # whether children are cut after their sums are made

    # candidate rows: node, mu1, iu, ru, bound, n, tu, tid, tail

    def first(self) -> DataFrame:
        mu = broadcast_if(self.dictionary.items.select(F.col("rank").alias("r"), F.col("mu").alias("mu1")), self.dictionary.n)
        rows = self.enc.select("tid", "tu", "n", F.posexplode("its").alias("p", "x"), "its").withColumn("r", F.col("x.r")).join(mu, "r")
        if self.options.roots is not None:
            rows = rows.join(broadcast_if_small(self.options.roots.select(F.col("rank").alias("r"))), "r", "left_semi")
        tail = F.slice("its", F.col("p") + 2, F.size("its"))
        return self._row(rows, F.array("r"), F.col("x.u"), F.col("x.ru"), F.lit(0).cast("long"), tail)

    def _row(self, rows: DataFrame, node, iu, ru, bound, tail) -> DataFrame:
        o = self.options
        columns = [node.alias("node"), "mu1", iu.alias("iu"), ru.alias("ru"), bound.alias("bound"), "n"]
        columns += ["tu"] if o.global_at_nodes else []
        return rows.select(*columns, *(["tid"] if o.carry == "rejoin" else [tail.alias("tail")]))

    def children(self, rows: DataFrame, nodes: DataFrame, level: int, total: int, expanding: int) -> DataFrame:
        """Candidate rows of the level below: tails of expanding nodes, one row for each item.

        Items that may not follow go here if what tells them is small enough to broadcast, else after the sums are made, by one join of itemsets
        (not of their rows). So no node holds an array of its siblings.
        """
        o = self.options
        rows = rows.join(broadcast_if(nodes.where("expand").select("node"), expanding), "node")
        if o.carry == "rejoin":
            last = F.element_at("node", -1)
            rows = rows.join(self.enc.select("tid", "its"), "tid").withColumn("tail", F.filter("its", lambda x: x["r"] > last)).drop("its")
        rows = rows.where(F.size("tail") > 0).select("*", F.posexplode("tail").alias("p", "x"))
        below = self._row(rows, F.concat("node", F.array("x.r")), F.col("iu") + F.col("x.u"), F.col("x.ru"), F.col("iu") + F.col("ru"), F.slice("tail", F.col("p") + 2, F.size("tail")))
        self.late = max(total, self.n_pairs) > MOST_ROWS
        return below if self.late else self.beside(self.paired(below, level), nodes, level, total)

    def beside(self, below: DataFrame, nodes: DataFrame, level: int, total: int) -> DataFrame:
        """Children whose last item stays beside their prefix. base needs no cut: every later sibling with a basket in common stays."""
        if level == 1 or self.options.variant == "base":
            return below
        sibling = F.concat(F.slice("node", 1, level - 1), F.array(F.element_at("node", -1)))
        return below.join(broadcast_if(nodes.select(F.col("node").alias("sibling")), total), sibling == F.col("sibling"), "left_semi")

    def paired(self, below: DataFrame, level: int) -> DataFrame:
        """Children whose last two items weigh enough together."""
        if not self.options.pair or self.long is not None and level == 1:
            return below
        a, b = F.element_at("node", -2), F.element_at("node", -1)
        pairs = broadcast_if(self.pairs.select(F.col("a").alias("pair_a"), F.col("b").alias("pair_b"), F.col("twu").alias("pair_twu")), self.n_pairs)
        on = (a == F.col("pair_a")) & (b == F.col("pair_b"))
        if self.long is None:
            return below.join(pairs, on & (F.col("pair_twu") >= F.col("mu1")), "left_semi")
        one, two = (broadcast_if(self.long.select(F.col("r").alias(f"r_{c}"), F.col("twu").alias(f"long_{c}")), self.dictionary.n) for c in "ab")
        bound = F.coalesce("pair_twu", F.lit(0)) + F.least(F.coalesce("long_a", F.lit(0)), F.coalesce("long_b", F.lit(0)))
        return below.join(pairs, on, "left").join(one, a == F.col("r_a"), "left").join(two, b == F.col("r_b"), "left").where(bound >= F.col("mu1")).select(*below.columns)

    def scored(self, rows: DataFrame, level: int, above: DataFrame | None) -> DataFrame:
        """One aggregate: node, mu1, iu, ru, support, residue, twu and whether the node stays."""
        o = self.options
        sums = [F.sum("iu").alias("iu"), F.sum("ru").alias("ru"), F.sum("n").alias("support"), F.sum("bound").alias("residue")]
        nodes = rows.groupBy("node", "mu1").agg(*sums, *([F.sum("tu").alias("twu")] if o.global_at_nodes else []))
        if self.late and level > 1:
            nodes = self.beside(self.paired(nodes, level - 1), above, level - 1, MOST_ROWS + 1)
        stays = F.lit(True)
        if o.look and level > 1 and o.measure == "utility":
            if o.seed == "prefix":
                nodes = nodes.withColumn("prefix", F.slice("node", 1, F.size("node") - 1)).join(above.select(F.col("node").alias("prefix"), "slack"), "prefix").withColumn("residue", F.col("residue") + F.col("slack")).drop("prefix", "slack")
            stays = F.col("residue") >= F.col("mu1")
        if o.global_at_nodes:
            stays = stays & (F.col("twu") >= F.lit(self.dictionary.lmu))
        return nodes.withColumn("stays", stays)

    def flagged(self, nodes: DataFrame) -> DataFrame:
        """Staying nodes with hui and expand."""
        measured = self.options.measure == "support"
        gain, most = (F.col("support"), F.col("support")) if measured else (F.col("iu"), F.col("iu") + F.col("ru"))
        return nodes.withColumns({"hui": gain >= F.col("mu1"), "expand": most >= F.col("mu1")})

    def joins(self, nodes: DataFrame, level: int) -> int:
        """Later siblings that expanding nodes are joined with: a counter, not needed by the search."""
        last = F.element_at("node", -1)
        if level == 1 and (not self.options.pair or self.long is not None):
            made = nodes.where("expand").agg(F.sum((self.dictionary.n - last).cast("long")))
        elif level == 1:
            made = nodes.where("expand").select(last.alias("a"), "mu1").join(self.pairs, "a").where("twu >= mu1").agg(F.count(F.lit(1)))
        elif not self.options.pair:
            siblings = Window.partitionBy(F.slice("node", 1, level - 1)).orderBy(last.desc()).rowsBetween(Window.unboundedPreceding, -1)
            made = nodes.withColumn("later", F.count(F.lit(1)).over(siblings)).where("expand").agg(F.sum("later"))
        else:
            prefix = F.slice("node", 1, level - 1)
            one, two = nodes.where("expand").select("node", "mu1", prefix.alias("p")), nodes.select(prefix.alias("q"), last.alias("y"))
            both = one.join(two, (F.col("p") == F.col("q")) & (last < F.col("y"))).select(F.concat("node", F.array("y")).alias("node"), "mu1")
            made = self.paired(both, level).agg(F.count(F.lit(1)))
        return made.first()[0] or 0

    def run(self, want_stats: bool = False) -> DataFrame:
        """node, mu1, iu, support of the itemsets found. One driver action for each level: two numbers (and counters if asked for)."""
        o, found, level = self.options, [], 1
        rows, above = written(self.first()), None
        while True:
            scored = self.scored(rows, level, above)
            children = F.count(F.lit(1)) if level > 1 else F.lit(0)
            before = scored.agg(children).first()[0] if want_stats and level > 1 else 0
            nodes = self.flagged(scored.where("stays"))
            if o.seed == "prefix":
                # the residue of a child starts from its prefix's totals: add the prefix's less the extended itemset's
                nodes = self._slack(nodes, above)
            nodes = written(nodes)
            total, expanding = nodes.agg(F.count(F.lit(1)), F.count(F.when(F.col("expand"), 1))).first()
            tried = self.stats.levels[-1]["joins"] if self.stats.levels else 0
            deeper = want_stats and level > 1
            self.stats.levels.append({"level": level, "nodes": total, "joins": self.joins(nodes, level) if want_stats else 0, "aborted": before - total if deeper else 0, "empty": tried - before if deeper else 0, "expanding": expanding})
            found.append(nodes.where("hui").select("node", "mu1", "iu", "support"))
            if not expanding or level == o.max_len:
                break
            rows = written(self.children(rows, nodes, level, total, expanding))
            above, level = nodes, level + 1
        out = found[0]
        for more in found[1:]:
            out = out.unionByName(more)
        return out

    def _slack(self, nodes: DataFrame, above: DataFrame | None) -> DataFrame:
        own = F.col("iu") + F.col("ru")
        if above is None:
            whole = F.broadcast(self.enc.agg(F.sum(F.aggregate("its", F.lit(0).cast("long"), lambda a, x: a + x["u"])).alias("whole")))  # one row
            return nodes.join(whole).withColumn("slack", F.col("whole") - own).drop("whole")
        prefix = F.slice("node", 1, F.size("node") - 1)
        totals = above.select(F.col("node").alias("prefix"), (F.col("iu") + F.col("ru")).alias("whole"))
        return nodes.withColumn("prefix", prefix).join(totals, "prefix").withColumn("slack", F.col("whole") - own).drop("prefix", "whole")


class ListJoin(Frontier):
    """The same levels, where rows below come from joining sibling lists instead of exploding tails."""

    def _row(self, rows, node, iu, ru, bound, tail):
        columns = ["tid", node.alias("node"), "mu1", iu.alias("iu"), ru.alias("ru"), bound.alias("bound"), F.lit(0).cast("long").alias("piu"), "n"]
        return rows.select(*columns, *(["tu"] if self.options.global_at_nodes else []))

    def children(self, rows: DataFrame, nodes: DataFrame, level: int, total: int, expanding: int) -> DataFrame:
        prefix, last = F.slice("node", 1, F.size("node") - 1), F.element_at("node", -1)
        live = rows.join(broadcast_if(nodes.where("expand").select("node"), expanding), "node").select("tid", prefix.alias("prefix"), last.alias("x"), "mu1", "iu", "ru", "piu", "n", *(["tu"] if self.options.global_at_nodes else []))
        # the later sibling stays if it is among the staying nodes; root slices do not limit it
        other = (self._all_items() if self.options.roots is not None and level == 1 else rows.join(nodes.select("node"), "node", "left_semi")).select(F.col("tid").alias("t"), prefix.alias("q"), last.alias("y"), F.col("iu").alias("yu"), F.col("ru").alias("yr"))
        joined = live.join(other, (F.col("tid") == F.col("t")) & (F.col("prefix") == F.col("q")) & (F.col("x") < F.col("y")))
        below = joined.select("tid", F.concat("prefix", F.array("x", "y")).alias("node"), "mu1", (F.col("iu") + F.col("yu") - F.col("piu")).alias("iu"), F.col("yr").alias("ru"), (F.col("iu") + F.col("ru")).alias("bound"), F.col("iu").alias("piu"), "n", *(["tu"] if self.options.global_at_nodes else []))
        self.late = self.n_pairs > MOST_ROWS
        return below if self.late else self.paired(below, level)

    def _all_items(self) -> DataFrame:
        return lists.item_lists(self.enc)
