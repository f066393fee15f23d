"""DuckDB SQL that answers mining queries from first principles: recursion over transactions for the
itemsets, bit masks for the splits, and the query itself as a condition. Normal forms play no part."""

from __future__ import annotations

from fractions import Fraction

from rulelattice.plans.algebra import Expr, to_sql
from rulelattice.sources.views import VIEWS


def pairs(view: str) -> str:
    return f"pairs as materialized ({VIEWS[view].sql}), total as (select count(distinct tid) as n from pairs)"


def need(minsup: int | Fraction) -> str:
    """The minimal support as a scalar expression."""
    return str(minsup) if isinstance(minsup, int) else f"(select greatest(1, (({minsup.numerator} * n + {minsup.denominator - 1}) // {minsup.denominator})) from total)"


def sets_cte(view: str, minsup: int | Fraction) -> str:
    """``sets(items, k, support)``: all itemsets that reach the minimal support."""
    p = need(minsup)
    return f"""{pairs(view)}, p as (select {p} as p),
good as materialized (select tid, item from pairs where item in (select item from pairs group by item having count(*) >= (select p from p))),
occ as (
  select tid, item as last, [item] as items, count(*) over (partition by item) as support from good
  union all
  select o.tid, g.item, list_append(o.items, g.item), count(*) over (partition by o.items, g.item) from occ o join good g on g.tid = o.tid and g.item > o.last where o.support >= (select p from p)
),
sets as materialized (select distinct items, len(items) as k, support from occ where support >= (select p from p))"""


def rules_cte(view: str, minsup: int | Fraction) -> str:
    """Adds ``rules(body_items, head_items, support, body_support)`` of all splits."""
    pick = lambda bit: f"list_filter(items, lambda x, i: ((m >> (i - 1)) & 1) = {bit})"
    return f"""{sets_cte(view, minsup)},
split as (select items, support, unnest(range(1, (1 << k) - 1)) as m from sets where k > 1),
sides as (select {pick(1)} as body_items, {pick(0)} as head_items, support from split),
rules as materialized (select s.*, b.support as body_support from sides s join sets b on b.items = s.body_items)"""


def itemsets(view: str, minsup: int | Fraction, where: str = "true") -> str:
    return f"with recursive {sets_cte(view, minsup)} select array_to_string(items, '|') as itemset, k::int as k, support from sets where {where}"


RULE_COLUMNS = "array_to_string(body_items, '|') as body, array_to_string(head_items, '|') as head, support, body_support, support::double / body_support as confidence"


def rules(view: str, minsup: int | Fraction, where: str) -> str:
    return f"with recursive {rules_cte(view, minsup)} select {RULE_COLUMNS} from rules where {where}"


def query_rules(view: str, minsup: int | Fraction, query: Expr) -> str:
    return rules(view, minsup, to_sql(query))


def contains(pos: list[str] = (), neg: list[str] = ()) -> str:
    return " and ".join([*[f"list_contains(items, '{i}')" for i in pos], *[f"not list_contains(items, '{i}')" for i in neg]]) or "true"


def _listed(items: list[str]) -> str:
    return "[" + ", ".join(f"'{i}'" for i in sorted(items)) + "]::varchar[]"


def candidates_cte(pos: list[str] = (), neg: list[str] = (), name: str = "cand") -> str:
    """Adds ``cand(items, level)`` to ``sets``: what a level-wise search under a set query has to count.

    That is the required items, every frequent item beside them, and each larger rest all of whose parts are
    frequent with them; a level is the size of the rest.
    """
    start = f"select {_listed(pos)} as items, 0 as level union all " if pos else ""
    alive = f" and exists (select 1 from {name}_rest where len(r) = 0)" if pos else ""
    return f"""{name}_rest as materialized (select list_filter(items, lambda x: not list_contains({_listed(pos)}, x)) as r from sets where {contains(pos, neg)}),
{name}_join as (select list_append(a.r, b.r[-1]) as c from {name}_rest a join {name}_rest b on len(a.r) = len(b.r) and list_slice(a.r, 1, len(a.r) - 1) = list_slice(b.r, 1, len(b.r) - 1) and a.r[-1] < b.r[-1] where len(a.r) > 0),
{name}_part as (select c, unnest(range(1, len(c) + 1)) as i from {name}_join),
{name}_whole as (select c from {name}_part join {name}_rest on r = list_concat(list_slice(c, 1, i - 1), list_slice(c, i + 1, len(c))) group by c having count(*) = len(c)),
{name} as materialized ({start}select list_sort(list_append({_listed(pos)}, items[1])) as items, 1 as level from sets where k = 1 and not list_contains({_listed([*pos, *neg])}, items[1]){alive}
  union all select list_sort(list_concat({_listed(pos)}, c)), len(c) from {name}_whole)"""


def pattern_counts(view: str, minsup: int | Fraction, queries: list[Expr], minconf: Fraction) -> str:
    """One row a query: itemsets that some split into body and head makes acceptable, rules, and the totals."""
    pick = lambda bit: f"list_filter(items, lambda x, i: ((m >> (i - 1)) & 1) = {bit})"
    confident = f"support * {minconf.denominator} >= body_support * {minconf.numerator}"
    each = " union all ".join(f"select {i}::int as query, count(distinct items) filter (where {to_sql(q)}) as sets, count(*) filter (where proper and {confident} and {to_sql(q)}) as rules from splits" for i, q in enumerate(queries, 1))
    return f"""with recursive {sets_cte(view, minsup)},
masks as (select items, k, support, unnest(range(0, 1 << k)) as m from sets),
sides as (select items, support, m > 0 and m < (1 << k) - 1 as proper, {pick(1)} as body_items, {pick(0)} as head_items from masks),
splits as materialized (select s.*, coalesce(b.support, 0) as body_support from sides s left join sets b on b.items = s.body_items),
counted as ({each}), all_ as (select count(distinct items) as all_sets, count(*) filter (where proper and {confident}) as all_rules from splits)
select '{view}' as view, query, sets, all_sets, rules, all_rules from counted, all_"""
