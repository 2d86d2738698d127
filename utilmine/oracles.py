"""SQL for DuckDB that gives the rows of the catalogue's queries from the same tables, by exhaustive enumeration of sub-baskets."""

from __future__ import annotations

from utilmine.sources.workloads import SHOP_BASKETS, TOY_BASKETS, TOY_MU, TOY_PROFIT

_SOLD = "select {t} as tid, {i} as item, sum(l_quantity::bigint)::bigint as qty, min({p})::bigint as pr from lineitem {j} group by 1, 2"
_YEAR = "join orders on l_orderkey = o_orderkey"
_PART = "join part on l_partkey = p_partkey"
_BRAND = "regexp_extract(p_brand, '([0-9]+)', 1)::bigint"

#: Lines (tid, item, qty, pr) of each workload.
_BASE = {
    "order_part": _SOLD.format(t="l_orderkey", i="l_partkey", p="p_size", j=_PART),
    "customer_year_part": _SOLD.format(t="o_custkey * 10000 + year(o_orderdate)", i="l_partkey", p="p_size", j=f"{_YEAR} {_PART}"),
    "customer_year_supplier": _SOLD.format(t="o_custkey * 10000 + year(o_orderdate)", i="l_suppkey", p="1 + l_suppkey % 10", j=_YEAR),
    "order_brand": _SOLD.format(t="l_orderkey", i=_BRAND, p=f"1 + (7 * {_BRAND}) % 10", j=_PART),
    "doc_tokens": "select doc_id as tid, t as item, count(*) as qty, length(t)::bigint as pr from (select doc_id, unnest(regexp_extract_all(lower(text), '[a-zéèàêçïü]+')) as t from documents) group by 1, 2, 4",
    "order_record": """select tid, id as item, 1 + (tid * 7 + id * 13) % 5 as qty, 1 + (7 * id) % 10 as pr from
      (select tid, dense_rank() over (order by name) as id from (select o_orderkey as tid, unnest(['st=' || o_orderstatus, 'pri=' || o_orderpriority, 'seg=' || c_mktsegment, 'nat=' || c_nationkey, 'yr=' || year(o_orderdate), 'mon=' || month(o_orderdate),
       'tp=' || least(9, floor(o_totalprice / 50000)::bigint), 'bal=' || case when c_acctbal < 0 then 'neg' when c_acctbal < 5000 then 'mid' else 'hi' end]) as name from orders join customer on o_custkey = c_custkey))""",
    "toy": "select * from (values " + ", ".join(f"({t}, '{x[0]}', {x[1:]}, {TOY_PROFIT[x[0]]})" for t, line in TOY_BASKETS.items() for x in line.split()) + ") v(tid, item, qty, pr)",
}
_READY = {
    "user_day_key": "select user_id * 100 + day(ts) as tid, json_extract_string(props, '$.k')::bigint as item, count(*) as qty, sum(round(value * 100)::bigint)::bigint as u, 1 + json_extract_string(props, '$.k')::bigint % 10 as pr from events group by 1, 2, 5",
    "shop": "select tid, item, 1::bigint as qty, u::bigint as u, 1::bigint as pr from (values " + ", ".join(f"({t}, '{i}', {u})" for t, line in SHOP_BASKETS.items() for i, u in line.items()) + ") v(tid, item, u)",
}


def lines(workload: str) -> str:
    """CTE body: tid, item, qty, pr, u."""
    if workload in _READY:
        return f"select tid, item, qty, pr, u from ({_READY[workload]})"
    return f"select tid, item, qty, pr, (qty * pr)::bigint as u from ({_BASE[workload]})"


def thresholds(glmu: int, beta: int = 0) -> str:
    return f"select item, greatest({beta} * min(pr), {glmu})::bigint as mu from lines group by item"


def _start(workload: str, mu: str) -> str:
    return f"with recursive lines as materialized ({lines(workload)}), mu as materialized ({mu}), tu as materialized (select tid, sum(u)::bigint as tu from lines group by tid)"


def lattice(workload: str, glmu: int = 0, beta: int = 0, max_len: int | None = None, mu: str | None = None) -> str:
    """CTEs lines, mu, tu and sets(key, k, utility, miu, support, twu) of all itemsets in some basket."""
    cap = f" and s.k < {max_len}" if max_len else ""
    return f"""{_start(workload, mu or thresholds(glmu, beta))},
priced as materialized (select tid, item, u, mu from lines join mu using (item)),
sub(tid, last, key, k, u, miu) as (
  select tid, item, item::varchar, 1, u, mu from priced
  union all
  select s.tid, p.item, s.key || ',' || p.item, s.k + 1, s.u + p.u, least(s.miu, p.mu) from sub s join priced p on s.tid = p.tid and p.item > s.last{cap}),
sets as materialized (select key, k, sum(u)::bigint as utility, min(miu) as miu, count(*) as support, sum(tu)::bigint as twu from sub join tu using (tid) group by key, k)"""


HUI = "select key, k, utility, miu, support from sets where utility >= miu"
#: Those that are left if a set goes as soon as one of its subsets misses its own threshold by weight.
CLOSED_HUI = """select key, k, utility, miu, support from sets s where utility >= miu
and not exists (select 1 from sets p where p.twu < p.miu and list_has_all(string_split(s.key, ','), string_split(p.key, ',')))"""
HTWUI = "select key, twu, miu from sets where twu >= miu"


def huis(workload: str, glmu: int, beta: int = 0, max_len: int | None = None) -> str:
    return f"{lattice(workload, glmu, beta, max_len)}\n{HUI}"


_TOY_MU = "select * from (values " + ", ".join(f"('{i}', {m}::bigint)" for i, m in TOY_MU.items()) + ") v(item, mu)"


def toy_huis() -> str:
    return f"{lattice('toy', mu=_TOY_MU)}\n{HUI}"


def ranked(workload: str, glmu: int = 0, beta: int = 0, mu: str | None = None) -> str:
    """CTEs lines, mu, tu, items (promising, with rank), own(tid, item, r, u, ru, mu, tu): baskets in the order of thresholds with what remains after each item."""
    return f"""{_start(workload, mu or thresholds(glmu, beta))},
lmu as (select min(mu) as lmu from mu),
measured as materialized (select item, sum(u)::bigint as u, sum(tu)::bigint as twu, count(*) as support from lines join tu using (tid) group by item),
items as materialized (select item, mu, measured.u, twu, support, row_number() over (order by mu, item)::int as rank from measured join mu using (item), lmu where twu >= lmu),
own as materialized (select tid, item, rank as r, lines.u, mu, tu, coalesce(sum(lines.u) over (partition by tid order by rank desc rows between unbounded preceding and 1 preceding), 0)::bigint as ru from lines join items using (item) join tu using (tid))"""


def pairs() -> str:
    return "pairs as materialized (select a.r as a, b.r as b, sum(a.tu)::bigint as twu from own a join own b on a.tid = b.tid and a.r < b.r group by 1, 2)"


def visits(workload: str, glmu: int, beta: int, variants: dict[str, tuple[bool, bool]], longest: int, mu: str | None = None) -> str:
    """CTEs as in ranked, facts of every itemset in threshold order, and for each variant (pair, look) v_<name>(node, k, ...) of visited itemsets and j_<name>(n), joins by length."""
    out = f"""{ranked(workload, glmu, beta, mu)}, {pairs()},
occ(tid, node, last, iu, ru, bound, mu1) as (
  select tid, [r], r, u, ru, 0::bigint, mu from own
  union all
  select o.tid, list_append(o.node, x.r), x.r, o.iu + x.u, x.ru, o.iu + o.ru, o.mu1 from occ o join own x on o.tid = x.tid and x.r > o.last),
facts as materialized (select node, len(node) as k, node[-1] as last, node[:-2] as prefix, list_append(node[:-3], node[-1]) as sibling, sum(iu)::bigint as iu, sum(ru)::bigint as ru, sum(bound)::bigint as residue, min(mu1) as mu1 from occ group by node)"""
    for name, (pair, look) in variants.items():
        out += f",\nv_{name}_1 as materialized (select * from facts where k = 1)"
        for k in range(2, longest + 1):
            test = " and f.residue >= f.mu1" if look else ""
            join = " join pairs q on q.a = p.last and q.b = f.last and q.twu >= f.mu1" if pair else ""
            out += f",\nv_{name}_{k} as materialized (select f.* from facts f join v_{name}_{k - 1} p on p.node = f.prefix and p.iu + p.ru >= p.mu1 join v_{name}_{k - 1} s on s.node = f.sibling{join} where f.k = {k}{test})"
        every = " union all ".join(f"select * from v_{name}_{k}" for k in range(1, longest + 1))
        out += f",\nv_{name} as materialized ({every})"
        join = " join pairs q on q.a = x.last and q.b = y.last and q.twu >= x.mu1" if pair else ""
        out += f",\nj_{name} as materialized (select count(*) as n from v_{name} x join v_{name} y on x.k = y.k and x.prefix = y.prefix and x.last < y.last{join} where x.iu + x.ru >= x.mu1)"
    return out


ALL_VARIANTS = {"base": (False, False), "pair": (True, False), "look": (False, True), "both": (True, True)}
