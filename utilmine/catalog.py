"""Every query of the library by name, with its SQL: measures, methods, baselines, experiments and reports over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from utilmine import oracles as O  # noqa: E741
from utilmine.functions import measures as M
from utilmine.functions import ordering
from utilmine.functions import thresholds as T
from utilmine.operators import baselines as B
from utilmine.operators import pairs, post, stats
from utilmine.operators.mine import Miner
from utilmine.plans import encode, lists
from utilmine.plans.cut import cached, written
from utilmine.sources import baskets, workloads
from utilmine.sources.synthetic import quest_like
from utilmine.sources.tables import table
from utilmine.streaming import windows

Query = Callable[[SparkSession, str], DataFrame]
GLMU, BETA = 40_000, 10_000
GRID_GLMU = [(g, 10_000) for g in (40_000, 50_000, 60_000, 80_000, 100_000)]
GRID_BETA = [(40_000, b) for b in (5_000, 8_000, 10_000, 15_000, 20_000)]
PATTERN = ("key", "k", "utility", "miu", "support")
LONGEST = 13

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


def brand(s: SparkSession, d: str) -> DataFrame:
    return workloads.order_brand(s, d)


def brand_mu(s: SparkSession, d: str, glmu: int = GLMU, beta: int = BETA) -> DataFrame:
    return T.from_profit(baskets.profit_of(brand(s, d)), beta, glmu)


def brand_input(s: SparkSession, d: str, glmu: int = GLMU, beta: int = BETA) -> tuple[DataFrame, DataFrame]:
    """Lines with their baskets' utilities and thresholds, from one pass over the tables."""
    lines = cached(M.with_tu(brand(s, d).select("tid", "item", "u", "pr")))
    return lines, T.from_profit(baskets.profit_of(lines), beta, glmu)


def brand_miner(s: SparkSession, d: str, glmu: int = GLMU, beta: int = BETA) -> Miner:
    return Miner(*brand_input(s, d, glmu, beta))


def brand_huis(s: SparkSession, d: str, glmu: int = GLMU, beta: int = BETA, engine: str = "hybrid", **options) -> DataFrame:
    return brand_miner(s, d, glmu, beta).search(engine, **options)[0].select("items", *PATTERN)


def names(column: Column | str = "node") -> Column:
    return F.array_join(F.transform(column, lambda x: x.cast("string")), ",")


BRAND_LATTICE = O.lattice("order_brand", GLMU, BETA)

# measures


@query("line_utility", f"with lines as ({O.lines('order_part')}) select tid, item, qty, u from lines")
def _(s, d):
    return workloads.order_part(s, d).select("tid", "item", "qty", "u")


@query("line_utility_ready_made", f"with lines as ({O.lines('user_day_key')}) select tid, item, u from lines")
def _(s, d):
    return workloads.user_day_key(s, d).select("tid", "item", "u")


@query("basket_utility", f"with lines as ({O.lines('order_part')}) select tid, sum(u)::bigint as tu from lines group by tid")
def _(s, d):
    return M.basket_utility(workloads.order_part(s, d))


@query("item_utility_twu_support", f"{O.ranked('order_part')} select item, u, twu, support from measured")
def _(s, d):
    return M.twu_items(workloads.order_part(s, d))


def _given(lines: DataFrame) -> DataFrame:
    """All pairs of brands, and triples of consecutive ones."""
    items = lines.select("item").distinct()
    two = items.join(items.select(F.col("item").alias("b")), F.col("item") < F.col("b")).select(F.array("item", "b").alias("items"))
    three = items.where("item < 24").select(F.array("item", F.col("item") + 1, F.col("item") + 2).alias("items"))
    return two.unionByName(three).select(names("items").alias("key"), "items")


_GIVEN = "where k = 2 or (k = 3 and split_part(key, ',', 1)::int + 1 = split_part(key, ',', 2)::int and split_part(key, ',', 1)::int + 2 = split_part(key, ',', 3)::int)"


@query("twu_given_itemsets", f"{O.lattice('order_brand', 0, 0, 3)} select key, twu from sets {_GIVEN}")
def _(s, d):
    lines = brand(s, d)
    return M.twu_itemsets(lines, _given(lines))


@query("itemset_utility_given", f"{O.lattice('order_brand', 0, 0, 3)} select key, utility as u, support from sets {_GIVEN}")
def _(s, d):
    lines = brand(s, d)
    return M.itemset_utility(lines, _given(lines))


@query("itemset_miu_given", f"{O.lattice('order_brand', GLMU, BETA, 3)} select key, miu from sets {_GIVEN}")
def _(s, d):
    lines = brand(s, d)
    seen = M.support(lines, _given(lines))
    return T.miu(_given(lines).join(seen.select("key"), "key", "left_semi"), brand_mu(s, d))


@query("item_thresholds_beta", f"with lines as ({O.lines('order_brand')}) {O.thresholds(GLMU, BETA)}")
def _(s, d):
    return brand_mu(s, d)


@query("item_thresholds_beta_spread", f"with lines as ({O.lines('order_part')}) select item, greatest((100 + (item * 31) % 301) * min(pr), 2000)::bigint as mu from lines group by item")
def _(s, d):
    return T.from_profit(baskets.profit_of(workloads.order_part(s, d)), T.spread(100, 400), 2000)


@query("uniform_thresholds", f"with lines as ({O.lines('order_part')}) select distinct item, 6500::bigint as mu from lines")
def _(s, d):
    return T.uniform(workloads.order_part(s, d), 6500)


@query("least_minimum_utility", f"with lines as ({O.lines('order_brand')}), mu as ({O.thresholds(GLMU, BETA)}) select min(mu) as lmu from mu")
def _(s, d):
    return T.lmu(brand_mu(s, d))


@query("item_order", f"with lines as ({O.lines('order_brand')}), mu as ({O.thresholds(GLMU, BETA)}) select item, row_number() over (order by mu, item)::int as rank from mu")
def _(s, d):
    return ordering.rank_items(brand_mu(s, d)).select("item", "rank")


@query("promising_items", f"{O.ranked('order_part', 6500, 100)} select item, twu, mu from items")
def _(s, d):
    lines = workloads.order_part(s, d)
    return encode.Dictionary(lines, T.from_profit(baskets.profit_of(lines), 100, 6500)).items.select("item", "twu", "mu")


@query("item_utility_lists", f"{O.ranked('order_brand', GLMU, BETA)} select r as rank, tid, u as iu, ru from own")
def _(s, d):
    return lists.item_lists(brand_miner(s, d).enc).select(F.col("node")[0].alias("rank"), "tid", "iu", "ru")


@query("item_information_table", f"{O.ranked('order_brand', GLMU, BETA)} select r::varchar as key, sum(u)::bigint as iu, sum(ru)::bigint as ru, count(*) as support from own group by r")
def _(s, d):
    return lists.information_table(lists.item_lists(brand_miner(s, d).enc)).select(names().alias("key"), "iu", "ru", "support")


_PAIR_LISTS = "select a.r || ',' || b.r as key, a.tid, a.u + b.u as iu, b.ru from own a join own b on a.tid = b.tid and a.r < b.r"


@query("pair_information_table", f"{O.ranked('order_brand', GLMU, BETA)} select key, sum(iu)::bigint as iu, sum(ru)::bigint as ru, count(*) as support from ({_PAIR_LISTS}) group by key")
def _(s, d):
    made = lists.construct(lists.item_lists(brand_miner(s, d).enc))
    return lists.information_table(made).select(names().alias("key"), "iu", "ru", "support")


@query("list_construct_pairs", f"{O.ranked('order_brand', GLMU, BETA)} {_PAIR_LISTS}")
def _(s, d):
    return lists.construct(lists.item_lists(brand_miner(s, d).enc)).select(names().alias("key"), "tid", "iu", "ru")


def _pair_query(workload: str) -> None:
    sql = f"{O.ranked(workload, 0)}, {O.pairs()} select a, b, twu from pairs"

    @query(f"pair_twu_table_{workload}", sql)
    def _(s, d):
        lines = workloads.ALL[workload](s, d)
        return lists.pair_table(Miner(lines, T.uniform(lines, 0), "mu").enc)


for _w in ("order_brand", "customer_year_supplier"):
    _pair_query(_w)


@query("basket_tail_after", f"{O.ranked('toy', mu=O._TOY_MU)} select tid, coalesce(string_agg(item, ',' order by r) filter (r > 2), '') as items from own group by tid having count(*) filter (r <= 2) = 2")
def _(s, d):
    m = Miner(workloads.toy(s), workloads.toy_thresholds(s))
    both = m.enc.where(F.size(F.filter("its", lambda x: x["r"] <= 2)) == 2)
    tail = both.select("tid", F.posexplode_outer(F.transform(encode.tail_after(F.col("its"), F.lit(1)), lambda x: x["r"])).alias("p", "rank"))
    return tail.join(m.dictionary.names(), "rank", "left").groupBy("tid").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("p", "item"))), lambda x: x["item"]), ",").alias("items"))


@query("basket_minus", f"with lines as ({O.lines('order_brand')}) select tid, string_agg(item, ',' order by item) filter (item not in (3, 7)) as items from lines group by tid having count(*) filter (item in (3, 7)) = 2")
def _(s, d):
    whole = brand(s, d).groupBy("tid").agg(F.array_sort(F.collect_list("item")).alias("its"))
    gone = F.array(F.lit(3).cast("long"), F.lit(7).cast("long"))
    both = whole.where(F.size(F.array_except(gone, "its")) == 0)
    left = encode.minus(F.col("its"), gone)
    return both.select("tid", F.when(F.size(left) > 0, names(left)).alias("items"))


# methods


def _levelwise(name: str, with_tids: bool) -> None:
    @query(f"{name}_htwui_brand", f"{BRAND_LATTICE} {O.HTWUI}")
    def _(s, d):
        return B.Levelwise(*brand_input(s, d), with_tids=with_tids).named()

    @query(f"{name}_hui_brand", f"{BRAND_LATTICE} {O.HUI}")
    def _(s, d):
        run = B.Levelwise(*brand_input(s, d), with_tids=with_tids, subset_check=not with_tids)
        return run.huis().select(*PATTERN)


_levelwise("levelwise", False)
_levelwise("levelwise_tid", True)


def _mined(name: str, sql: str, **how) -> None:
    @query(name, sql)
    def _(s, d):
        return brand_huis(s, d, **how).select(*PATTERN)


for _v in ("base", "pair", "look", "both"):
    _mined(f"hui_{_v}_brand", f"{BRAND_LATTICE} {O.HUI}", engine="frontier", variant=_v)
for _e in ("lists", "subtree", "hybrid"):
    _mined(f"hui_{_e}_engine_brand", f"{BRAND_LATTICE} {O.HUI}", engine=_e)
_mined("hui_look_prefix_seed_brand", f"{BRAND_LATTICE} {O.HUI}", engine="frontier", variant="look", seed="prefix")
_mined("hui_rejoin_carry_brand", f"{BRAND_LATTICE} {O.HUI}", engine="frontier", carry="rejoin")
_mined("hui_global_at_nodes_brand", f"{BRAND_LATTICE} {O.HUI}", engine="frontier", global_at_nodes=True)


@query("htwui_brand", f"{BRAND_LATTICE} {O.HTWUI}")
def _(s, d):
    return B.enumerate_all(brand(s, d), brand_mu(s, d)).where(M.is_htwui()).select("key", "twu", "miu")


@query("hui_roots_brand", f"{BRAND_LATTICE}, first as (select s.key, arg_min(mu.item, (mu.mu, mu.item)) as root from sets s, unnest(string_split(s.key, ',')) u(i) join mu on mu.item = u.i::bigint group by s.key) select s.key, s.k, s.utility, s.miu, s.support from sets s join first using (key) where root in (3, 7, 13) and utility >= miu")
def _(s, d):
    m = brand_miner(s, d)
    return m.search("frontier", roots=m.roots([3, 7, 13]))[0].select(*PATTERN)


def _workload(name: str, workload: str, glmu: int, beta: int, max_len: int | None = None, engine: str = "hybrid", with_sql: bool = True) -> None:
    @query(name, O.huis(workload, glmu, beta, max_len) if with_sql else None)
    def _(s, d):
        lines = workloads.ALL[workload](s, d)
        return Miner(lines, T.from_profit(baskets.profit_of(lines), beta, glmu)).search(engine, max_len=max_len)[0].select(*PATTERN)


_workload("hui_order_part", "order_part", 6500, 100)
_workload("hui_customer_year_part_k3", "customer_year_part", 5000, 200, 3)
_workload("hui_order_record", "order_record", 20_000, 1000)
_workload("hui_customer_year_supplier_k3", "customer_year_supplier", 20_000, 5000, 3)
_workload("hui_user_day", "user_day_key", 20_000, 5000)


@query("hui_doc_tokens_whole_k2")
def _(s, d):
    lines = cached(workloads.doc_tokens(s, d).select("tid", "item", "u", "pr"))
    return pairs.mine_pairs(lines, T.from_profit(baskets.profit_of(lines), 30, 100))


_workload("hui_customer_year_part", "customer_year_part", 5000, 200, with_sql=False)
_workload("hui_customer_year_supplier", "customer_year_supplier", 20_000, 5000, with_sql=False)
_workload("hui_doc_tokens", "doc_tokens", 100, 30, with_sql=False)


def _uniform(variant: str) -> None:
    @query(f"uniform_{variant}_brand", O.huis("order_brand", GLMU))
    def _(s, d):
        return B.uniform(brand(s, d), GLMU, variant).select(*PATTERN)


for _v in ("base", "pair", "look"):
    _uniform(_v)


@query("enumerate_all_brand", f"{BRAND_LATTICE} {O.HUI}")
def _(s, d):
    return B.enumerated_huis(brand(s, d), brand_mu(s, d)).select(*PATTERN)


@query("naive_closure_toy", f"{O.lattice('toy', mu=O._TOY_MU)} {O.CLOSED_HUI}")
def _(s, d):
    return B.naive_closure(workloads.toy(s), workloads.toy_thresholds(s)).select(*PATTERN)


@query("frequent_pairs_brand", f"{O.lattice('order_brand', 0, 0, 2)} select key, support from sets where k = 2 and support >= 0.02 * (select count(*) from tu)")
def _(s, d):
    return B.frequent(brand(s, d), 0.02).where("k = 2").select("key", "support")


@query("frequent_multi_support_brand", f"{O.lattice('order_brand', mu='select item, (150 + 10 * (item % 7))::bigint as mu from lines group by item')} select key, support from sets where support >= miu")
def _(s, d):
    lines = brand(s, d)
    mis = lines.select("item").distinct().select("item", (150 + 10 * (F.col("item") % 7)).alias("mis"))
    return B.frequent_multi(lines, mis).select("key", "support")


_STAR = O.lattice("order_brand", GLMU, 20_000)


@query("hui_minus_uniform", f"{_STAR} select key from sets where utility >= miu and utility < {GLMU}")
def _(s, d):
    return post.diff(brand_huis(s, d, GLMU, 20_000), B.uniform(brand(s, d), GLMU, "pair"))


@query("uniform_minus_hui", f"{_STAR} select key from sets where utility < miu and utility >= {GLMU}")
def _(s, d):
    return post.diff(B.uniform(brand(s, d), GLMU, "pair"), brand_huis(s, d, GLMU, 20_000))


# experiments


def _counts_sql(grid: list[tuple[int, int]]) -> str:
    rows = " union all ".join(f"select {g}::bigint as glmu, {b}::bigint as beta" for g, b in grid)
    return f"""{O.lattice('order_brand')}, profit as (select item, min(pr) as pr from lines group by item),
most as materialized (select key, utility, twu, (select min(pr) from profit where list_contains(string_split(key, ',')::bigint[], item)) as low from sets),
grid as ({rows})
select glmu, beta, count(*) filter (utility >= greatest(beta * low, glmu)) as hui, count(*) filter (utility >= glmu) as hui_star, count(*) filter (twu >= greatest(beta * low, glmu)) as htwui from most, grid group by all"""


for _name, _grid in (("pattern_counts_by_glmu", GRID_GLMU), ("pattern_counts_by_beta", GRID_BETA)):

    @query(_name, _counts_sql(_grid))
    def _(s, d, grid=_grid):
        return stats.pattern_counts(brand(s, d), grid)


@query("pattern_counts_cube", f"{BRAND_LATTICE} select k, case when utility >= miu then 1 else 0 end as above, count(*) as n from sets where utility >= {GLMU} group by cube (1, 2)")
def _(s, d):
    star = B.uniform(brand(s, d), GLMU, "pair").select("key", "k")
    both = star.join(brand_huis(s, d).select("key", F.lit(1).alias("one")), "key", "left")
    return both.select("k", F.coalesce("one", F.lit(0)).alias("above")).cube("k", "above").agg(F.count(F.lit(1)).alias("n"))


def _visits_sql(grid: list[tuple[int, int]]) -> str:
    parts = []
    for g, b in grid:
        counts = ", ".join(f"(select count(*) from v_{v}) as n{i}" for i, v in enumerate(O.ALL_VARIANTS, 2))
        parts.append(f"(select {g}::bigint as glmu, {b}::bigint as beta, n1.n as n1, x.n2, x.n3, x.n4, x.n5 from ({O.visits('order_brand', g, b, O.ALL_VARIANTS, LONGEST)} select {counts}) x, ({O.lattice('order_brand', g, b)} select count(*) as n from sets where twu >= miu) n1)")
    return " union all ".join(parts)


for _name, _grid in (("pruning_counts_by_glmu", GRID_GLMU), ("pruning_counts_by_beta", GRID_BETA)):

    @query(_name, _visits_sql(_grid))
    def _(s, d, grid=_grid):
        return stats.pruning_counts(brand(s, d), grid)


_JOINS = " union all ".join(f"select '{v}' as variant, n as joins from j_{v}" for v in O.ALL_VARIANTS)


@query("attempted_joins", f"{O.visits('order_brand', GLMU, BETA, O.ALL_VARIANTS, LONGEST)} {_JOINS}")
def _(s, d):
    return stats.joins(brand(s, d), brand_mu(s, d))


@query("dataset_characteristics", " union all ".join(f"(with lines as ({O.lines(w)}), n as (select tid, count(*) as n from lines group by tid) select '{w}' as name, (select count(*) from n) as baskets, (select count(distinct item) from lines) as items, (select avg(n) from n) as mean_length, (select max(n) from n) as max_length)" for w in workloads.ALL))
def _(s, d):
    out = None
    for name, made in workloads.ALL.items():
        row = stats.characteristics(made(s, d)).select(F.lit(name).alias("name"), "baskets", "items", "mean_length", "max_length")
        out = row if out is None else out.unionByName(row)
    return out


# reports


@query("hui_topn", f"{BRAND_LATTICE} {O.HUI} order by utility desc, key limit 10")
def _(s, d):
    return post.topn(brand_huis(s, d), 10).select(*PATTERN)


@query("hui_topn_per_k", f"{BRAND_LATTICE} {O.HUI} qualify row_number() over (partition by k order by utility desc, key) <= 3")
def _(s, d):
    return post.topn(brand_huis(s, d), 3, per_k=True).select(*PATTERN)


@query("hui_containing_item", f"{BRAND_LATTICE} {O.HUI} and list_contains(string_split(key, ','), '7')")
def _(s, d):
    return post.containing(brand_huis(s, d), F.lit(7).cast("long")).select(*PATTERN)


@query("hui_maximal", f"{BRAND_LATTICE}, h as materialized (select *, string_split(key, ',') as l from sets where utility >= miu) select key, k, utility, miu, support from h where not exists (select 1 from h g where g.k > h.k and list_has_all(g.l, h.l))")
def _(s, d):
    return post.maximal(brand_huis(s, d)).select(*PATTERN)


@query("rare_item_report", f"{BRAND_LATTICE}, low as (select item, mu from mu where mu < (select quantile_cont(mu, 0.5) from mu)) select key, k, utility, count(*) as rare_items, min(low.mu) as least_mu from sets, low where utility >= miu and list_contains(string_split(key, ','), low.item::varchar) group by all")
def _(s, d):
    return post.rare_items(brand_huis(s, d), brand_mu(s, d), 0.5)


@query("cumulative_utility_share", f"{BRAND_LATTICE} select key, utility, sum(utility) over (order by utility desc, key rows unbounded preceding)::bigint as running, (select sum(u)::bigint from lines) as total from sets where utility >= miu")
def _(s, d):
    return post.share(brand_huis(s, d), brand(s, d).agg(F.sum("u").alias("total")))


def _brand_lines_by(s: SparkSession, d: str) -> DataFrame:
    orders, customer = table(s, d, "orders").select("o_orderkey", "o_custkey"), table(s, d, "customer").select("c_custkey", "c_mktsegment", "c_nationkey")
    nation = table(s, d, "nation").select("n_nationkey", "n_regionkey", "n_name").join(table(s, d, "region").select("r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    owners = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    return brand(s, d).join(owners, F.col("tid") == F.col("o_orderkey"))


_OWNED = f"with lines as ({O.lines('order_brand')}) select {{}}, sum(u)::bigint as u, count(*) as n from lines join orders on tid = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by {{}}"


@query("utility_by_segment_rollup", _OWNED.format("c_mktsegment as segment, item", "rollup (c_mktsegment, item)"))
def _(s, d):
    return post.utility_rollup(_brand_lines_by(s, d).withColumnRenamed("c_mktsegment", "segment"), ["segment", "item"])


@query("utility_by_region_cube", _OWNED.format("r_name as region, c_mktsegment as segment", "cube (r_name, c_mktsegment)"))
def _(s, d):
    return post.utility_cube(_brand_lines_by(s, d).withColumnRenamed("r_name", "region").withColumnRenamed("c_mktsegment", "segment"), ["region", "segment"])


@query("customers_of_pairs", f"with lines as ({O.lines('order_brand')}) select a.item || ',' || b.item as key, count(distinct o_custkey) as customers from lines a join lines b on a.tid = b.tid and a.item < b.item join orders on a.tid = o_orderkey group by 1")
def _(s, d):
    lines = brand(s, d).join(table(s, d, "orders").select(F.col("o_orderkey").alias("tid"), F.col("o_custkey").alias("cust")), "tid")
    return post.customers_of(lines, _given(brand(s, d)).where(F.size("items") == 2))


_ASOF_SQL = """with sold as (select l_orderkey as tid, l_partkey as item, sum(l_quantity::bigint)::bigint as qty, min(o_orderdate) as ts from lineitem join orders on l_orderkey = o_orderkey group by 1, 2),
prices as (select p_partkey as item, p_size + y - 1994 as pr, make_timestamp(y, 1, 1, 0, 0, 0) as valid_from from part, range(1994, 2002) r(y))
select year(ts)::int as year, sum(qty * pr)::bigint as u, count(*) as n from sold asof join prices on sold.item = prices.item and ts >= valid_from group by 1"""


@query("price_asof_utility", _ASOF_SQL)
def _(s, d):
    rows = table(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity").join(table(s, d, "orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    lines = baskets.from_lines(rows, "l_orderkey", "l_partkey", "l_quantity", ts="o_orderdate")
    years = table(s, d, "part").select("p_partkey", "p_size", F.explode(F.sequence(F.lit(1994), F.lit(2001))).alias("y"))
    prices = years.select(F.col("p_partkey").alias("item"), (F.col("p_size") + F.col("y") - 1994).cast("long").alias("pr"), F.make_timestamp("y", F.lit(1), F.lit(1), F.lit(0), F.lit(0), F.lit(0)).alias("valid_from"))
    return M.asof_profit(lines, prices).groupBy(F.year("ts").alias("year")).agg(F.sum("u").alias("u"), F.count(F.lit(1)).alias("n"))


# the running examples


@query("toy_huis", O.toy_huis())
def _(s, d):
    return Miner(workloads.toy(s), workloads.toy_thresholds(s)).search()[0].select(*PATTERN)


@query("shop_pairs", f"{O.lattice('shop', 150)} {O.HUI}")
def _(s, d):
    lines = workloads.shop(s)
    return Miner(lines, T.uniform(lines, 150)).search("subtree")[0].select(*PATTERN)


@query("toy_eucs", f"{O.ranked('toy', mu=O._TOY_MU)}, {O.pairs()} select least(x.item, y.item) || greatest(x.item, y.item) as pair, p.twu from pairs p join items x on p.a = x.rank join items y on p.b = y.rank")
def _(s, d):
    m = Miner(workloads.toy(s), workloads.toy_thresholds(s))
    one, two = (m.dictionary.items.select(F.col("rank").alias(r), F.col("item").alias(f"i{r}")) for r in "ab")
    return lists.pair_table(m.enc).join(one, "a").join(two, "b").select(F.concat(F.least("ia", "ib"), F.greatest("ia", "ib")).alias("pair"), "twu")


@query("toy_information_table", f"{O.ranked('toy', mu=O._TOY_MU)} select item, sum(own.u)::bigint as iu, sum(own.ru)::bigint as ru from own group by item")
def _(s, d):
    m = Miner(workloads.toy(s), workloads.toy_thresholds(s))
    table_ = lists.information_table(lists.item_lists(m.enc)).withColumn("rank", F.col("node")[0])
    return table_.join(m.dictionary.names(), "rank").select("item", "iu", "ru")


@query("toy_search_counters", "select * from (values ('base', 22::bigint, 20::bigint), ('pair', 21, 16), ('look', 16, 20), ('both', 16, 16)) v(variant, nodes, joins)")
def _(s, d):
    counts = stats.search_counts(workloads.toy(s), workloads.toy_thresholds(s))
    return s.createDataFrame([(v, c["nodes"], c["joins"]) for v, c in counts.items()], "variant string, nodes long, joins long")


# streams

_EVENT_LINES = "select user_id as user, ts, json_extract_string(props, '$.k')::bigint as item, round(value * 100)::bigint as u from events"


@query("stream_basket_windows", f"select date_trunc('day', ts) as start, user, sum(u)::bigint as tu, count(*) as n from ({_EVENT_LINES}) group by all")
def _(s, d):
    baskets_ = windows.window_baskets(windows.event_stream(s, d), "1 day")
    return windows.run_to_table(baskets_.select("start", "user", "tu", F.size("its").cast("long").alias("n")), "complete")


@query("stream_item_twu", f"with e as materialized ({_EVENT_LINES}), b as (select date_trunc('day', ts) as start, user, sum(u)::bigint as tu from e group by all), l as (select distinct date_trunc('day', ts) as start, user, item from e) select start, item, sum(tu)::bigint as twu, count(*) as support from l join b using (start, user) group by all")
def _(s, d):
    return windows.run_to_table(windows.window_baskets(windows.event_stream(s, d), "1 day"), "complete", windows.item_twu)


@query("stream_session_baskets", f"with e as ({_EVENT_LINES}), g as (select *, case when ts - lag(ts) over w <= interval 6 hour - interval 1 microsecond then 0 else 1 end as new from e window w as (partition by user order by ts)), n as (select *, sum(new) over (partition by user order by ts, item, u rows unbounded preceding) as number from g) select user, min(ts) as start, sum(u)::bigint as tu, count(*) as n from n group by user, number")
def _(s, d):
    made = windows.window_baskets(windows.event_stream(s, d), gap="6 hours")
    return windows.run_to_table(made.select("user", "start", "tu", F.size("its").cast("long").alias("n")), "complete")


_WEEK = "time_bucket(interval 7 day, ts, timestamp '1970-01-01')"


def _stream_huis_sql() -> str:
    return f"""with recursive e as materialized (select {_WEEK} as start, user as tid, item, sum(u)::bigint as u from ({_EVENT_LINES}) group by all),
sub(start, tid, last, key, k, u) as (select start, tid, item, item::varchar, 1, u from e union all select s.start, s.tid, e.item, s.key || ',' || e.item, s.k + 1, s.u + e.u from sub s join e on s.start = e.start and s.tid = e.tid and e.item > s.last and s.k < 3)
select start, key, k, sum(u)::bigint as utility, 100000::bigint as miu, count(*) as support from sub group by start, key, k having sum(u) >= 100000"""


def _stream_huis(s: SparkSession, d: str, **options) -> DataFrame:
    made = windows.window_baskets(windows.event_stream(s, d), "7 days")
    items = s.range(100).select(F.col("id").alias("item"))
    # the stream's table holds baskets, not patterns, whose number may be a power of a basket's length
    return windows.mine_windows(windows.run_to_table(made, "complete"), T.uniform(items, 100_000), engine="hybrid", **options)


@query("stream_window_huis", _stream_huis_sql())
def _(s, d):
    return _stream_huis(s, d, max_len=3)


@query("stream_window_huis_full")
def _(s, d):
    return _stream_huis(s, d)


# measurements, without SQL


@query("search_stats_runtime")
def _(s, d):
    return stats.runtimes(brand(s, d), list(dict.fromkeys([(GLMU, BETA), *GRID_GLMU, *GRID_BETA])))


@query("memory_profile")
def _(s, d):
    rows = []
    for name, run in {"one_phase": lambda: brand_huis(s, d), "level_wise": lambda: B.Levelwise(*brand_input(s, d), with_tids=True).huis()}.items():
        run().count()
        rows.append((name, *stats.memory(s).values()))
    return s.createDataFrame(rows, "method string, heap_mb double, python_mb double")


def _nested(lines: DataFrame, parts: int = 4) -> dict[str, DataFrame]:
    """Growing shares of the baskets, each within the next, up to all of them. The lines are written: each share would read and join the tables again, twice."""
    lines = written(lines)
    share = F.pmod(F.xxhash64("tid"), F.lit(parts))
    return {f"{i}/{parts}": lines.where(share < i) for i in range(1, parts)} | {f"{parts}/{parts}": lines}


SCALED = {"order_part": (6500, 100), "customer_year_supplier": (20_000, 5000), "order_brand": (GLMU, BETA)}
GENERATED = (100_000, 200_000, 300_000, 400_000, 500_000)


@query("scalability_runs")
def _(s, d):
    """The tables' workloads in nested shares, and generated baskets (4,000 items, mean length 10) of five sizes."""
    return _scaled(s, d).unionByName(stats.scalability({f"generated {n}": quest_like(s, n) for n in GENERATED}, 100_000, 1000))


def _scaled(s: SparkSession, d: str) -> DataFrame:
    out = None
    for w, (glmu, beta) in SCALED.items():
        own = stats.scalability({f"{w} {n}": lines for n, lines in _nested(workloads.ALL[w](s, d)).items()}, glmu, beta)
        out = own if out is None else out.unionByName(own)
    return out
