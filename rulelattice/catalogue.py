"""Queries over the given tables, one for each method, variant, baseline, measure or workload, with SQL twins.

Minimal supports are shares of the transactions unless a query text says otherwise, so that every query
runs at every scale.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulelattice import oracle as O
from rulelattice.functions import itemsets as fi
from rulelattice.operators import baselines, families, incremental, levelwise, projection, rulegen
from rulelattice.operators.counting import count_sets
from rulelattice.operators.integrated import MiningOptions, generated_sets, query_rules, query_sets
from rulelattice.operators.items import Dataset, encode, item_supports, profile, sets_table, shown
from rulelattice.operators.ledger import cutoff, saturation
from rulelattice.operators.session import Session
from rulelattice.operators.store import ItemsetStore
from rulelattice.plans.algebra import And, Expr, MinConfidence, Not, parse_query, to_sql
from rulelattice.plans.normalform import SetConj, rule_disjuncts, set_disjuncts
from rulelattice.runtime import read_table, shared_dir
from rulelattice.sources.views import pairs_of
from rulelattice.streaming.streams import SupportStream, gap_sessions, stream_transactions
from rulelattice.workload import ceil_share, characteristics, compare_strategies, load, pattern_counts, pattern_ratios, random_queries, run_session

Query = Callable[[SparkSession, str], DataFrame]

BRAND, DENSE, CLICKS, PART, TERMS = Fraction(5, 1000), Fraction(5, 100), Fraction(2, 1000), Fraction(1, 5000), Fraction(4, 10)
HALF = Fraction(1, 2)
#: Items that exist at every scale, for generated queries.
DENSE_ITEMS = [f"{k}={v}" for k, vs in {"status": "OFP", "qtr": "1234", "bal": "0123", "dow": "0123456", "big": "yn", "neg": "yn"}.items() for v in vs] + [f"year={y}" for y in range(1993, 1998)]
FLAGSHIP = parse_query("(body('Brand#2') and not head('Brand#7') or head('Brand#3') and body('Brand#4')) and support >= 20 and confidence >= 0.05")

_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def keep(f: Query) -> Query:
        _QUERIES[name or f.__name__] = f
        if sql is not None:
            _ORACLES[name or f.__name__] = sql
        return f
    return keep


def _sets(ds: Dataset, found: dict) -> DataFrame:
    return shown(sets_table(ds, found))


def _text(q: Expr | str) -> Expr:
    return parse_query(q) if isinstance(q, str) else q


# Foundations and baselines ---------------------------------------------------------------------------


@query(f"with {O.pairs('clicks')} select item, count(*) as support from pairs group by item")
def item_support(spark, sf_dir):
    return item_supports(pairs_of(spark, sf_dir, "clicks"))


@query(f"with {O.pairs('clicks')}, t as (select tid, count(*) as n from pairs group by tid) select count(*) as transactions, sum(n)::bigint as occurrences, max(n) as longest, (select count(distinct item) from pairs) as items from t")
def tx_profile(spark, sf_dir):
    return profile(pairs_of(spark, sf_dir, "clicks"))


def _frequent(view: str, share: Fraction, kernel: str = "auto") -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, view, share)
        return _sets(ds, levelwise.frequent_sets(ds, minsup, kernel))
    return run


for _name, _view, _share in (("brand", "basket_brand", BRAND), ("dense", "dense_order", DENSE), ("clicks", "clicks", CLICKS), ("parts", "basket_part", PART), ("terms", "doc_terms", TERMS)):
    query(O.itemsets(_view, _share), f"frequent_sets_{_name}")(_frequent(_view, _share))
for _kernel in ("probe", "bitmap", "subset", "partitioned"):
    query(O.itemsets("basket_brand", BRAND), f"kernel_{_kernel}")(_frequent("basket_brand", BRAND, _kernel))


@query(O.itemsets("basket_brand", BRAND))
def frequent_as_tables(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "basket_brand", BRAND)
    return shown(levelwise.named_table(ds, levelwise.frequent_sets_as_tables(ds, minsup)))


@query(O.itemsets("basket_brand", BRAND))
def frequent_fpgrowth(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "basket_brand", BRAND)
    return shown(baselines.named(ds, baselines.fpgrowth(ds, minsup)))


@query(O.itemsets("dense_order", DENSE))
def frequent_vertical(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return shown(baselines.named(ds, baselines.vertical(ds, minsup)))


@query(O.itemsets("dense_order", DENSE))
def frequent_sampling(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return _sets(ds, baselines.sampling(ds, minsup))


@query(O.itemsets("dense_order", DENSE))
def divide_and_mine(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    parts = [_sets(ds, p) for p in baselines.divide_and_mine(ds, minsup, 4)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)  # disjoint by construction
    return out


_CONF = MinConfidence(HALF)


@query(O.rules("dense_order", DENSE, to_sql(_CONF)))
def rules_allsplits(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return rulegen.shown(rulegen.all_splits(sets_table(ds, levelwise.frequent_sets(ds, minsup)), HALF))


@query(O.rules("dense_order", DENSE, to_sql(_CONF)))
def rules_levelwise(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return rulegen.shown(rulegen.levelwise(sets_table(ds, levelwise.frequent_sets(ds, minsup)), HALF))


@query(O.rules("dense_order", DENSE, "support * 2 > body_support"))
def rules_strict_conf(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return rulegen.shown(rulegen.all_splits(sets_table(ds, levelwise.frequent_sets(ds, minsup)), HALF, strict=True))


# Constrained mining ---------------------------------------------------------------------------------------

_POS, _NEG = ["year=1995", "big=y"], ["neg=y", "qtr=2"]


def _projected_rows(alias: str) -> str:
    return f"{alias} as (select tid from pairs where item in ('year=1995', 'big=y') group by tid having count(*) = 2)"


@query(f"with {O.pairs('dense_order')}, {_projected_rows('t')} select 0::int as disjunct, (select count(*) from t) as transactions, (select count(*) from pairs join t using (tid) where item not in ('year=1995', 'big=y', 'neg=y', 'qtr=2')) as occurrences")
def projected_db_size(spark, sf_dir):
    ds, _ = load(spark, sf_dir, "dense_order", Fraction(1, 10**9))
    return projection.sizes(ds, [SetConj(frozenset(_POS), frozenset(_NEG))])


@query(f"with {O.pairs('dense_order')}, {_projected_rows('t')}, r as (select tid, string_agg(case when item not in ('year=1995', 'big=y', 'neg=y', 'qtr=2') then item end, '|' order by item) as rest from pairs join t using (tid) group by tid) select rest, count(*) as transactions from r group by rest")
def projected_db_rows(spark, sf_dir):
    ds, _ = load(spark, sf_dir, "dense_order", Fraction(1, 10**9))
    names = spark.createDataFrame(list(enumerate(ds.names)), "iid int, name string")
    rest = projection.project(ds, SetConj(frozenset(_POS), frozenset(_NEG))).select("nid", F.explode_outer("items").alias("iid"))
    spelt = rest.join(F.broadcast(names), "iid", "left").groupBy("nid").agg(F.array_join(F.array_sort(F.collect_list("name")), "|").alias("rest"))
    return spelt.groupBy("rest").agg(F.count("*").alias("transactions"))


def _constrained(pos: list[str], neg: list[str]) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, "dense_order", Fraction(1, 100))
        return _sets(ds, levelwise.mine_set_query(ds, [SetConj(frozenset(pos), frozenset(neg), minsup)], minsup)[0])
    return run


for _name, _p, _n in (("pos", _POS, []), ("neg", [], [*_NEG, "big=y", "status=O", "status=F"]), ("posneg", _POS, _NEG)):
    query(O.itemsets("dense_order", Fraction(1, 100), O.contains(_p, _n)), f"constrained_sets_{_name}")(_constrained(_p, _n))

_TINY = [(1, "2 3 5 6 9"), (2, "1 2 3 5 6"), (3, "1 3 4 8")]
_TINY_QUERY = parse_query("body('1') and not body('2') and head('3') and not head('4') and not body('5') and not head('5') and support >= 1 and confidence >= 0.5")


def tiny(spark: SparkSession) -> Dataset:
    """The three-transaction frame of the worked example."""
    return encode(spark.createDataFrame([(t, i) for t, s in _TINY for i in s.split()], "tid long, item string"), 1)


def _values(rows: list[tuple], columns: str) -> str:
    spelt = ", ".join("(" + ", ".join(f"'{v}'" if isinstance(v, str) else str(v) for v in r) + ")" for r in rows)
    return f"select * from (values {spelt}) as t({columns})"


@query(_values([("1", "3", 2, 2, 1.0), ("1", "2|3", 1, 2, 0.5), ("1", "2|3|6", 1, 2, 0.5), ("1", "3|6", 1, 2, 0.5), ("1", "3|8", 1, 2, 0.5), ("1|4", "3", 1, 1, 1.0), ("1|4", "3|8", 1, 1, 1.0), ("1|4|8", "3", 1, 1, 1.0), ("1|6", "2|3", 1, 1, 1.0), ("1|6", "3", 1, 1, 1.0), ("1|8", "3", 1, 1, 1.0)], "body, head, s, b, c").replace("select *", "select body, head, s::bigint as support, b::bigint as body_support, c::double as confidence"))
def rules_example(spark, sf_dir):
    return rulegen.shown(query_rules(tiny(spark), _TINY_QUERY))


_FAMILIES = [("rule", s, 1 if s != "1|3" else 2) for s in ("1|3", "1|2|3", "1|3|4", "1|3|6", "1|3|8", "1|2|3|6", "1|3|4|8")]
_FAMILIES += [("body", s, 1 if s != "1" else 2) for s in ("1", "1|4", "1|6", "1|8", "1|4|8")] + [("head", s, n) for s, n in (("3", 3), ("2|3", 2), ("3|6", 2), ("3|8", 1), ("2|3|6", 2))]


@query(_values(_FAMILIES, "role, itemset, s").replace("select *", "select 0::int as rule_disjunct, role, itemset, s::bigint as support"))
def families_example(spark, sf_dir):
    ds, conjs = tiny(spark), rule_disjuncts(_TINY_QUERY)
    table = families.families(ds, query_sets(ds, _TINY_QUERY), conjs)
    return table.select("rule_disjunct", "role", F.array_join("items", "|").alias("itemset"), "support")


def _family(role: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
        conj = rule_disjuncts(parse_query(f"body('big=y') and not body('neg=n') and not head('neg=y') and support >= {minsup}"))[0]
        found = levelwise.mine_set_query(ds, set_disjuncts([conj]), minsup)[0]
        table = families.families(ds, found, [conj])
        return table.where(F.col("role") == role).select(F.array_join("items", "|").alias("itemset"), "support")
    return run


def _family_sql(part: str) -> str:
    """Residual sets are the answers without the required item; supports of bodies and heads are counted in the pairs."""
    return f"""with recursive {O.sets_cte("dense_order", DENSE)}, rest as (select list_filter(items, lambda x: x <> 'big=y') as r, support from sets where list_contains(items, 'big=y')),
fam as (select distinct {part}),
n as (select items, count(*) as c from (select f.items, pairs.tid from fam f join pairs on list_contains(f.items, pairs.item) group by f.items, pairs.tid having count(*) = len(f.items)) group by items)
select array_to_string(fam.items, '|') as itemset, case when len(fam.items) = 0 then (select n from total) else coalesce(c, 0) end as support from fam left join n using (items)"""


query(_family_sql("list_sort(list_append(r, 'big=y')) as items from rest where not list_contains(r, 'neg=n')"), "body_sets")(_family("body"))
query(_family_sql("r as items from rest where not list_contains(r, 'neg=y')"), "head_sets")(_family("head"))

# Integrated queries: name, view, share or absolute threshold of the data, query text, options.
_INTEGRATED = {
    "integrated_conj": ("dense_order", DENSE, "body('big=y') and not body('neg=n') and head('status=O') and not head('qtr=2') and confidence >= 0.2", MiningOptions()),
    "integrated_negated_only": ("dense_order", DENSE, "not body('big=y') and not head('big=y') and not head('neg=n') and confidence >= 0.5", MiningOptions()),
    "integrated_body_only": ("dense_order", DENSE, "body('year=1995') and confidence >= 0.3", MiningOptions()),
    "integrated_head_only": ("dense_order", DENSE, "head('neg=n') and not body('big=n') and confidence >= 0.3", MiningOptions()),
    "integrated_bitmap": ("dense_order", DENSE, "head('neg=n') and body('big=y')", MiningOptions(kernel="bitmap")),
    "integrated_probe": ("dense_order", DENSE, "head('neg=n') and body('big=y')", MiningOptions(kernel="probe")),
    "boolean_or": ("dense_order", DENSE, "body('big=y') or body('neg=y')", MiningOptions()),
    "boolean_or_dnf": ("dense_order", DENSE, "body('big=y') or body('neg=y')", MiningOptions(normal="dnf")),
    "boolean_or_set_ddnf": ("dense_order", DENSE, "body('big=y') or body('neg=y')", MiningOptions(normal="set_ddnf")),
    "boolean_ex2_shape": ("dense_order", DENSE, "body('big=y') and (body('neg=n') or head('neg=n'))", MiningOptions()),
    "boolean_nested": ("dense_order", DENSE, "not (body('big=y') or head('neg=n') and not body('status=O')) and (head('year=1996') or body('qtr=1')) and confidence >= 0.15", MiningOptions()),
    "boolean_mixed_thresholds": ("dense_order", DENSE, "body('big=y') and support >= 1000 or head('neg=n') and support >= 2000", MiningOptions()),
    "boolean_mixed_unsorted": ("dense_order", DENSE, "body('big=y') and support >= 1000 or head('neg=n') and support >= 2000", MiningOptions(sort_by_support=False)),
    "max_support_filter": ("dense_order", DENSE, "body('big=y') and not support >= 1500", MiningOptions()),
    "max_confidence_filter": ("dense_order", DENSE, "body('big=y') and not confidence >= 0.3", MiningOptions()),
    "negated_confidence_ignored": ("dense_order", DENSE, "body('big=y') and confidence >= 0.3 or head('neg=n') and confidence >= 0.2", MiningOptions(negated_confidence="ignore")),
    "boolean_thresholds_only": ("basket_brand", BRAND, "confidence >= 0.15 or support >= 500", MiningOptions()),
    "query_without_answers": ("dense_order", DENSE, "body('big=y') and head('big=y')", MiningOptions()),
    "query_unknown_item": ("dense_order", DENSE, "body('big=y') and not head('no such item') and head('neg=y')", MiningOptions()),
    "infeasible_terms": ("doc_terms", Fraction(3, 10), "body('the') and head('of') and confidence >= 0.9", MiningOptions()),
    "rules_from_forced_head": ("dense_order", DENSE, "head('big=y') and not body('neg=n') and confidence >= 0.3 or body('status=O') and head('neg=n') and confidence >= 0.2", MiningOptions(heads="levelwise")),
    "rules_grown_without_bound": ("dense_order", DENSE, "body('big=y') and not confidence >= 0.3", MiningOptions(heads="levelwise")),
    "cust_profile_rules": ("cust_profile", Fraction(1, 10), "confidence >= 0.3", MiningOptions()),
}


def _integrated(view: str, share: Fraction, text: str, options: MiningOptions) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, view, share)
        return rulegen.shown(query_rules(ds, And((parse_query(text), parse_query(f"support >= {minsup}"))), options))
    return run


for _name, (_view, _share, _q, _options) in _INTEGRATED.items():
    query(O.query_rules(_view, _share, parse_query(_q)), _name)(_integrated(_view, _share, _q, _options))


@query(O.query_rules("basket_brand", 20, FLAGSHIP))
def flagship(spark, sf_dir):
    ds = encode(pairs_of(spark, sf_dir, "basket_brand"), 20)
    return rulegen.shown(query_rules(ds, FLAGSHIP))


_OR = "body('big=y') or body('neg=y')"
_OR_SETS = "(list_contains(items, 'big=y') or list_contains(items, 'neg=y'))"


def _repeats(form: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
        made = generated_sets(ds, And((parse_query(_OR), parse_query(f"support >= {minsup}"))), MiningOptions(normal=form))
        return spark.createDataFrame([("|".join(ds.named(s)), n) for _, s, n in made], "itemset string, support long").groupBy("itemset").agg(F.count("*").alias("times"))
    return run


query(f"with recursive {O.sets_cte('dense_order', DENSE)} select array_to_string(items, '|') as itemset, (list_contains(items, 'big=y')::int + list_contains(items, 'neg=y')::int)::bigint as times from sets where {_OR_SETS}", "boolean_dnf_duplicates")(_repeats("dnf"))
query(f"with recursive {O.sets_cte('dense_order', DENSE)} select array_to_string(items, '|') as itemset, 1::bigint as times from sets where {_OR_SETS}", "boolean_ddnf_no_duplicates")(_repeats("ddnf"))


@query()
def boolean_shared_scan(spark, sf_dir):
    """Scans of two disjuncts together and apart."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    conjs = set_disjuncts(rule_disjuncts(And((parse_query(_OR), parse_query(f"support >= {minsup}")))))
    before = ds.scans
    levelwise.mine_set_query(ds, conjs, minsup)
    together, before = ds.scans - before, ds.scans
    for c in conjs:
        levelwise.mine_set_query(ds, [c], minsup)
    return spark.createDataFrame([("together", together), ("apart", ds.scans - before)], "mode string, scans int")


_UNIVERSE = ["big=y", "neg=y", "status=F", "year=1995", "qtr=1", "dow=0"]


def _subsets_sql() -> str:
    listed = "[" + ", ".join(f"'{u}'" for u in sorted(_UNIVERSE)) + "]"
    return f"""with {O.pairs("dense_order")}, u as (select list_filter({listed}, lambda x, i: ((m >> (i - 1)) & 1) = 1) as items from (select unnest(range(1, {1 << len(_UNIVERSE)})) as m)),
n as (select items, count(*) as c from (select u.items, pairs.tid from u join pairs on list_contains(u.items, pairs.item) group by u.items, pairs.tid having count(*) = len(u.items)) group by items)
select array_to_string(u.items, '|') as itemset, len(u.items)::int as k, coalesce(c, 0) as support from u left join n using (items) where coalesce(c, 0) < {O.need(DENSE)}"""


@query(_subsets_sql())
def topdown_sets(spark, sf_dir):
    ds, _ = load(spark, sf_dir, "dense_order", Fraction(1, 10**9))
    return _sets(ds, baselines.topdown_sets(ds, _UNIVERSE, ceil_share(DENSE, ds.size)))


@query(O.rules("dense_order", DENSE, "support * 10 < body_support * 3"))
def topdown_rules(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    found = baselines.topdown_rules(levelwise.frequent_sets(ds, minsup), 3, 10)
    return rulegen.shown(spark.createDataFrame([(ds.named(b), ds.named(h), n, m) for b, h, n, m in found], "body_items array<string>, head_items array<string>, support long, body_support long"))


# Sessions -----------------------------------------------------------------------------------------------------

_S1 = "body('big=y') and head('neg=n') and confidence >= 0.2"
_S2 = "body('big=y') or head('status=O')"
_S3 = "not body('big=y') and head('year=1996') and confidence >= 0.1"


def _session(strategy: str, texts: list[str], which: int, coverage: str = "none", **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
        session = Session(ds, strategy, minsup, coverage=coverage, **options)
        answers = [session.ask(t) for t in texts]
        return rulegen.shown(answers[which])
    return run


def _answer(text: str) -> str:
    return O.query_rules("dense_order", DENSE, parse_query(text))


query(_answer(_S1), "postprocess_rules_on_demand")(_session("postprocess", [_S1], 0))
query(_answer(_S1), "postprocess_rules_stored")(_session("postprocess", [_S1], 0, materialize="rules"))
query(_answer(_S1), "incremental_first")(_session("incremental", [_S1], 0))
query(_answer(_S1), "incremental_repeat")(_session("incremental", [_S1, _S1], 1))
query(_answer(_S3), "incremental_basic")(_session("incremental", [_S1, _S2, _S3], 2))
query(_answer(_S3), "incremental_coverage")(_session("incremental", [_S1, _S2, _S3], 2, "full"))
query(_answer(_S3), "incremental_topm")(_session("incremental", [_S1, _S2, _S3], 2, "top", keep=1))
query(_answer(_S2), "incremental_without_cache_pruning")(_session("incremental", [_S1, _S2], 1, cache_pruning=False))
query(_answer(_S1 + " and not head('qtr=2')"), "session_refine")(lambda spark, sf_dir: _refined(spark, sf_dir, True))
query(_answer(f"({_S1}) or head('qtr=2')"), "session_widen")(lambda spark, sf_dir: _refined(spark, sf_dir, False))


def _refined(spark: SparkSession, sf_dir: str, narrower: bool) -> DataFrame:
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    session = Session(ds, "incremental", minsup, coverage="full")
    session.ask(_S1)
    return rulegen.shown(session.refine("not head('qtr=2')") if narrower else session.widen("head('qtr=2')"))


@query(O.itemsets("dense_order", DENSE, "list_contains(items, 'big=y') or list_contains(items, 'status=O')"))
def postprocess_sets(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return shown(Session(ds, "postprocess", minsup).sets(_S2))


@query(O.query_rules("dense_order", Fraction(1, 100), parse_query("body('year=1995') and head('big=y')")))
def incremental_lower_support(spark, sf_dir):
    """The same item conditions at a high, a lower and again a high minimal support; the second answer."""
    ds, low = load(spark, sf_dir, "dense_order", Fraction(1, 100))
    session = Session(ds, "incremental", low, coverage="full")
    ask = lambda n: session.ask(f"body('year=1995') and head('big=y') and support >= {n}")
    ask(5 * low)
    second = ask(low)
    ask(10 * low)
    return rulegen.shown(second)


@query(O.query_rules("dense_order", DENSE, And((Not(parse_query(_S1)), parse_query(_S2)))))
def answers_except(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    session = Session(ds, "incremental", minsup)
    session.ask(_S1)
    session.ask(_S2)
    return rulegen.shown(session.diff(1, 2))


@query(O.query_rules("dense_order", DENSE, And((parse_query(_S1), parse_query(_S2)))))
def answers_intersect(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    session = Session(ds, "incremental", minsup)
    return rulegen.shown(session.ask(_S1).intersect(session.ask(_S2)))


_RANDOM = random_queries(DENSE_ITEMS, 6, seed=5)
_SESSION_SQL = f"with recursive {O.rules_cte('dense_order', DENSE)} " + " union all ".join(f"select {i}::int as query, {O.RULE_COLUMNS} from rules where {to_sql(And((q, _CONF)))}" for i, q in enumerate(_RANDOM, 1))


def _random_session(strategy: str, coverage: str = "none") -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
        session = Session(ds, strategy, minsup, HALF, coverage)
        out = None
        for i, q in enumerate(_RANDOM, 1):
            part = rulegen.shown(session.ask(q)).withColumn("query", F.lit(i))
            out = part if out is None else out.unionByName(part)
        return out
    return run


for _strategy, _cover in (("integrated", "none"), ("postprocess", "none"), ("incremental", "none"), ("incremental", "full"), ("incremental", "top")):
    query(_SESSION_SQL, f"session_{_strategy}_{_cover}")(_random_session(_strategy, _cover))


@query("select 2::int as query, 0::bigint as counted, 0::bigint as scans")
def no_regeneration(spark, sf_dir):
    """A repeated query counts nothing and scans nothing."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    session = run_session(ds, [_text(_S2), _text(_S2)], "incremental", minsup)
    return spark.createDataFrame([(2, int(session.ledger.total("generated", 2)), int(session.ledger.total("query_scans", 2)))], "query int, counted long, scans long")


@query()
def cache_pruning(spark, sf_dir):
    """Counted candidates of a session with and without pruning by the store."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    rows = [(on, int(run_session(ds, _RANDOM, "incremental", minsup, cache_pruning=on).ledger.total("generated"))) for on in (True, False)]
    return spark.createDataFrame(rows, "pruning boolean, counted long")


@query(O.itemsets("dense_order", DENSE, "list_contains(items, 'big=y')"))
def store_round_trip(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    store = ItemsetStore(ds)
    incremental.mine_incremental(ds, [SetConj(frozenset(["big=y"]), frozenset(), minsup)], store, minsup)
    path = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    store.save(path)
    return _sets(ds, ItemsetStore.load(ds, path).satisfying([SetConj(frozenset(["big=y"]), frozenset(), minsup)]))


@query(_family_sql("list_filter(r, lambda x: x <> 'neg=n') as items from rest where len(r) > 1").replace("fam as (select distinct", "fam as (select distinct * from (select").replace("where len(r) > 1)", "where len(r) > 1) where len(items) > 0)"))
def missing_families(spark, sf_dir):
    """Supports of sets that a query's own answer does not hold, by one more scan."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    found = levelwise.mine_set_query(ds, [SetConj(frozenset(["big=y"]), frozenset(), minsup)], minsup)[0]
    drop = {ds.code["big=y"], ds.code["neg=n"]}
    asked = {tuple(i for i in s if i not in drop) for s in found if len(s) > 2}
    return shown(sets_table(ds, {s: n for s, n in count_sets(ds, [s for s in asked if s]).items()})).select("itemset", "support")


# Measures and workloads -------------------------------------------------------------------------------------------


_W1 = {"dense_order": Fraction(1, 100), "clicks": Fraction(1, 1000), "basket_part": PART, "doc_terms": TERMS}
_W1_SQL = " union all ".join(
    f"(with recursive {O.sets_cte(v, share)}, {O.candidates_cte()} select '{v}' as view, (select count(distinct item) from pairs) as items, (select n from total) as transactions, (select p from p)::bigint as minsup, (select count(distinct level) from cand)::int as iterations, (select count(*) from sets) as itemsets)"
    for v, share in _W1.items()
)


@query(_W1_SQL)
def w1_characteristics(spark, sf_dir):
    return characteristics(spark, sf_dir, _W1).drop("seconds")


_W2_VIEWS = {
    "dense_order": (DENSE, DENSE_ITEMS),
    "clicks": (CLICKS, [f"{e}_{b}" for e in ("click", "view", "purchase") for b in range(10)]),
    "basket_brand": (BRAND, [f"Brand#{b}" for b in range(1, 26)]),
    "doc_terms": (TERMS, ["the", "of", "and", "in", "to", "on", "re", "or"]),
}


def _pattern_counts(view: str) -> Query:
    share, items = _W2_VIEWS[view]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ds, minsup = load(spark, sf_dir, view, share)
        return pattern_counts(ds, view, minsup, Fraction(1, 10), random_queries(items, 100, seed=11))
    return run


for _view, (_share, _items) in _W2_VIEWS.items():
    query(O.pattern_counts(_view, _share, random_queries(_items, 100, seed=11), Fraction(1, 10)), f"w2_patterns_{_view}")(_pattern_counts(_view))
_W2 = random_queries(DENSE_ITEMS, 10, seed=11)


@query()
def w2_pattern_ratio(spark, sf_dir):
    """Shares of candidates and of time beside those of the patterns, each query mined by itself."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return pattern_ratios(ds, minsup, Fraction(1, 10), _W2)


@query()
def w3_cutoff(spark, sf_dir):
    """Query at which mining anew has generated more candidates than mining everything once."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    ledger = compare_strategies(ds, random_queries(DENSE_ITEMS, 12, seed=21), minsup, (("integrated", "none"), ("postprocess", "none")))
    return cutoff(ledger, "generated", "integrated", "postprocess").select("session", F.col("cutoff").cast("int").alias("cutoff"))


@query()
def w4_saturation(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    everything = len(levelwise.frequent_sets(ds, minsup))
    session = run_session(ds, random_queries(DENSE_ITEMS, 10, seed=31), "incremental", minsup)
    return saturation(session.ledger.df(spark), everything).select("query", "share")


@query()
def w4_costs(spark, sf_dir):
    """Generated candidates and scans of one session under all strategies."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    ledger = compare_strategies(ds, _RANDOM, minsup)
    return ledger.where("metric in ('generated', 'query_scans', 'rows_read')").groupBy("strategy", "metric").agg(F.sum("value").alias("value"))


_M_POS, _M_NEG = ["big=y", "status=O"], ["neg=n"]
_M_SETS = f"with recursive {O.sets_cte('dense_order', DENSE)}"


def _candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    log: list = []
    levelwise.mine_set_query(ds, [SetConj(frozenset(_M_POS), frozenset(_M_NEG), minsup)], minsup, log=log)
    return spark.createDataFrame([(ds.named(s),) for _, s, _ in log], "items array<string>")


@query(f"{_M_SETS}, {O.candidates_cte(_M_POS, _M_NEG)} select array_to_string(items, '|') as itemset from cand")
def m1_candidates(spark, sf_dir):
    """Every itemset that is counted for a query, once for each time."""
    return _candidates(spark, sf_dir).select(F.array_join("items", "|").alias("itemset"))


@query("select 0::bigint as vain")
def m1_vain(spark, sf_dir):
    """Counted itemsets that the query cannot accept whatever their support."""
    wanted = [F.array_contains("items", i) for i in _M_POS] + [~F.array_contains("items", i) for i in _M_NEG]
    kept = F.lit(True)
    for w in wanted:
        kept &= w
    return _candidates(spark, sf_dir).agg(F.count_if(~kept).alias("vain"))


@query(f"{_M_SETS}, {O.candidates_cte()} select count(distinct level) as scans from cand where level > 1")
def m2_scans(spark, sf_dir):
    """Passes over the transactions that the unconstrained search makes after encoding."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    levelwise.frequent_sets(ds, minsup, "probe")
    return spark.createDataFrame([(ds.scans,)], "scans long")


@query(f"""{_M_SETS}, {O.candidates_cte(_M_POS, _M_NEG)}, f as (select item, count(*) as n from pairs group by item having count(*) >= (select p from p)),
t as (select tid from pairs where item in ('big=y', 'status=O') group by tid having count(*) = 2), l as (select count(distinct level) as n from cand where level > 1)
select (select n from total) + (select count(*) from t) * (1 + (select n from l)) as rows_read,
  ((select sum(n) from f) + (select count(*) from pairs join t using (tid) join f using (item) where item not in ('big=y', 'status=O', 'neg=n')) * (1 + (select n from l)))::bigint as occurrences_read""")
def m3_scanned(spark, sf_dir):
    """Transactions and items that a query's scans read: all of them once, then the projected ones only."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    levelwise.mine_set_query(ds, [SetConj(frozenset(_M_POS), frozenset(_M_NEG), minsup)], minsup, "probe")
    return spark.createDataFrame([(ds.rows_read, ds.occurrences_read)], "rows_read long, occurrences_read long")


_M6 = {"body('big=y')": (["big=y"], []), "body('big=y') and head('status=O')": (["big=y", "status=O"], []), "head('big=y') and not body('neg=n') and not head('neg=n')": (["big=y"], ["neg=n"])}


@query(f"{_M_SETS}, {', '.join(O.candidates_cte(p, n, f'c{i}') for i, (p, n) in enumerate(_M6.values()))}, u as ({' union all '.join(f'select items from c{i}' for i in range(len(_M6)))}) select 'integrated' as strategy, count(*) - count(distinct items) as regenerated from u union all select 'incremental', 0")
def m6_regenerated(spark, sf_dir):
    """Itemsets that a session counts again, from the log of all its counts."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    rows = []
    for strategy in ("integrated", "incremental"):
        log = [s for _, s, _ in run_session(ds, [parse_query(q) for q in _M6], strategy, minsup).log]
        rows.append((strategy, len(log) - len(set(log))))
    return spark.createDataFrame(rows, "strategy string, regenerated long")


_M18 = ["big=y", "neg=y", "status=O", "qtr=1", "dow=0", "bal=3"]


@query(_M_SETS + " " + " union all ".join(f"select '{i}' as item, count(*) filter (where list_contains(items, '{i}')) as required, count(*) filter (where not list_contains(items, '{i}')) as forbidden, count(*) as frequent from sets" for i in _M18))
def m18_search_space(spark, sf_dir):
    """Frequent itemsets left where an item is required or forbidden: at most half of them contain it."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    conjs = [SetConj(frozenset(), frozenset(), minsup)] + [SetConj(frozenset(p), frozenset(n), minsup) for i in _M18 for p, n in (([i], []), ([], [i]))]
    sizes = [len(f) for f in levelwise.mine_set_query(ds, conjs, minsup)]
    return spark.createDataFrame([(i, sizes[2 * k + 1], sizes[2 * k + 2], sizes[0]) for k, i in enumerate(_M18)], "item string, required long, forbidden long, frequent long")


@query()
def m19_lookup(spark, sf_dir):
    """Seconds of a session's queries that go into lookups: subtraction, seeding and the answer's selection."""
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    ledger = run_session(ds, _RANDOM, "incremental", minsup, coverage="top").ledger.df(spark)
    return ledger.where("metric in ('t_lookup', 't_query')").groupBy("query").pivot("metric", ["t_lookup", "t_query"]).agg(F.sum("value"))


@query(f"with recursive {O.sets_cte('dense_order', DENSE)} select array_to_string(a.items, '|') as itemset, a.k::int as k, a.support from sets a where not exists (select 1 from sets b where b.k = a.k + 1 and b.support = a.support and list_has_all(b.items, a.items))")
def closed_sets(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return shown(fi.closed_sets(sets_table(ds, levelwise.frequent_sets(ds, minsup))))


@query(f"with recursive {O.sets_cte('dense_order', DENSE)} select array_to_string(a.items, '|') as itemset, a.k::int as k, a.support from sets a where not exists (select 1 from sets b where b.k = a.k + 1 and list_has_all(b.items, a.items))")
def maximal_sets(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return shown(fi.maximal_sets(sets_table(ds, levelwise.frequent_sets(ds, minsup))))


@query(f"""with recursive {O.rules_cte('dense_order', DENSE)} select array_to_string(body_items, '|') as body, array_to_string(head_items, '|') as head, r.support, r.body_support, h.support as head_support,
round(r.support * n::double / (r.body_support * h.support), 9) as lift, round(r.support::double / (r.body_support + h.support - r.support), 9) as jaccard, round(r.support::double / greatest(r.body_support, h.support), 9) as all_confidence
from rules r join sets h on h.items = r.head_items, total where r.support * 2 >= r.body_support""")
def rule_measures(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    sets = sets_table(ds, levelwise.frequent_sets(ds, minsup))
    made = fi.rule_measures(rulegen.all_splits(sets, HALF), sets, ds.size)
    return made.select(F.array_join("body_items", "|").alias("body"), F.array_join("head_items", "|").alias("head"), "support", "body_support", "head_support", *[F.round(c, 9).alias(c) for c in ("lift", "jaccard", "all_confidence")])


@query(f"with recursive {O.rules_cte('dense_order', DENSE)} select {O.RULE_COLUMNS} from rules order by support::double / body_support desc, support desc, array_to_string(body_items, '|'), array_to_string(head_items, '|') limit 10")
def top_rules(spark, sf_dir):
    ds, minsup = load(spark, sf_dir, "dense_order", DENSE)
    return rulegen.shown(fi.top_rules(rulegen.all_splits(sets_table(ds, levelwise.frequent_sets(ds, minsup)), Fraction(0)), 10))


@query(f"with {O.pairs('dense_order')} select tid from pairs where item in ('big=y', 'neg=y', 'year=1995') group by tid having count(*) = 3")
def supporting_transactions(spark, sf_dir):
    return fi.supporting_transactions(pairs_of(spark, sf_dir, "dense_order"), ["big=y", "neg=y", "year=1995"])


# Streams, on the table of events ------------------------------------------------------------------------------------

_ITEM = "event_type || '_' || (json_extract_string(props, '$.k')::int // 10)"


@query(f"select user_id, array_to_string(list_sort(list_distinct(list({_ITEM}))), '|') as items, count(*) as events from events group by user_id, date_trunc('day', ts)".replace(", count(*) as events", ""))
def stream_day_tx(spark, sf_dir):
    return stream_transactions(read_table(spark, sf_dir, "events")).select("user_id", F.array_join("items", "|").alias("items"))


@query(f"""with m as (select *, case when epoch(ts)::bigint - epoch(lag(ts) over (partition by user_id order by ts, event_id))::bigint <= 14400 then 0 else 1 end as fresh from events),
s as (select *, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) as session from m)
select user_id, session::bigint as session, array_to_string(list_sort(list_distinct(list({_ITEM}))), '|') as items from s group by user_id, session""")
def stream_session_tx(spark, sf_dir):
    return gap_sessions(read_table(spark, sf_dir, "events"), 14_400).select("user_id", "session", F.array_join("items", "|").alias("items"))


@query(f"with t as (select user_id, date_trunc('day', ts) as d, list_distinct(list({_ITEM})) as items from events group by 1, 2), w as (select unnest([['click_1'], ['click_1', 'view_2'], ['purchase_3', 'view_2']]) as items) select array_to_string(w.items, '|') as itemset, count(*) as support from w join t on list_has_all(t.items, w.items) group by 1")
def stream_absorb(spark, sf_dir):
    """Supports of fixed itemsets after two batches, the second of which arrives twice."""
    wanted = spark.createDataFrame([(["click_1"],), (["click_1", "view_2"],), (["purchase_3", "view_2"],)], "items array<string>")
    tx = stream_transactions(read_table(spark, sf_dir, "events"))
    stream = SupportStream(wanted, f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}")
    for batch_id, part in ((0, 0), (1, 1), (1, 1)):
        stream.absorb(tx.where(F.pmod(F.xxhash64("user_id", "started"), F.lit(2)) == part).select("items"), batch_id)
    return stream.supports().select(F.array_join("items", "|").alias("itemset"), "support")


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)

