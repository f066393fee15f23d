"""Random queries and the experiment workloads, with their costs in a ledger."""

from __future__ import annotations

import random
import time
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulelattice.operators.integrated import query_rules, query_sets, with_session_bounds
from rulelattice.operators.items import Dataset, encode, sets_table
from rulelattice.operators.ledger import Ledger, cumulative, cutoff, proportionality
from rulelattice.operators.levelwise import frequent_sets, mine_set_query
from rulelattice.operators.rulegen import all_splits
from rulelattice.operators.session import Session
from rulelattice.plans.algebra import And, Expr, InBody, InHead, Not, Or, to_rule_predicate, to_text
from rulelattice.plans.normalform import rule_disjuncts, set_disjuncts
from rulelattice.sources.views import pairs_of


def random_queries(items: list[str], n: int, max_atoms: int = 3, seed: int = 1, p_not: float = 0.3, p_or: float = 0.4) -> list[Expr]:
    """Queries with one to ``max_atoms`` item conditions, a pure function of the seed."""
    rng = random.Random(seed)
    out = []
    for _ in range(n):
        parts: list[Expr] = []
        for _ in range(rng.randint(1, max_atoms)):
            atom: Expr = (InBody if rng.random() < 0.5 else InHead)(rng.choice(items))
            parts.append(Not(atom) if rng.random() < p_not else atom)
        while len(parts) > 1:
            at = rng.randrange(len(parts) - 1)
            parts[at : at + 2] = [(Or if rng.random() < p_or else And)((parts[at], parts[at + 1]))]
        out.append(parts[0])
    return out


def ceil_share(share: Fraction, n: int) -> int:
    return max(1, -(-share.numerator * n // share.denominator))


def load(spark: SparkSession, sf_dir: str, view: str, share: Fraction) -> tuple[Dataset, int]:
    """A view encoded for a relative minimal support, and that support as a count."""
    # Three jobs read the pairs; a spilled copy spares the joins and the shuffle behind them.
    pairs = pairs_of(spark, sf_dir, view).where("tid is not null and item is not null").select("tid", "item").distinct().persist()
    try:
        minsup = ceil_share(share, pairs.select("tid").distinct().count())
        return encode(pairs, minsup, distinct=True), minsup
    finally:
        pairs.unpersist()


def characteristics(spark: SparkSession, sf_dir: str, wanted: dict[str, Fraction]) -> DataFrame:
    """One row a data set: items, transactions, minimal support, iterations, itemsets, seconds."""
    rows = []
    for view, share in wanted.items():
        ds, minsup = load(spark, sf_dir, view, share)
        ledger, began = Ledger(), time.time()
        found = frequent_sets(ds, minsup, ledger=ledger)
        items = pairs_of(spark, sf_dir, view).select(F.count_distinct("item")).first()[0]
        rows.append((view, items, ds.size, minsup, int(ledger.total("iterations")), len(found), time.time() - began))
        ds.release()
    return spark.createDataFrame(rows, "view string, items long, transactions long, minsup long, iterations int, itemsets long, seconds double")


def pattern_ratios(ds: Dataset, minsup: int, minconf: Fraction, queries: list[Expr], with_rules: bool = False) -> DataFrame:
    """For each query: its share of all itemsets (and rules), of generated candidates and of the time."""
    full, began = Ledger(), time.time()
    everything = frequent_sets(ds, minsup, ledger=full)
    base, all_generated = time.time() - began, full.total("generated")
    all_rules = query_rules(ds, with_session_bounds(And(()), minsup, minconf)).count() if with_rules else 0
    rows = []
    for i, q in enumerate(queries, 1):
        bounded, ledger, began = with_session_bounds(q, minsup, minconf), Ledger(), time.time()
        found = query_sets(ds, bounded, ledger=ledger)
        spent = time.time() - began
        rules = query_rules(ds, bounded).count() if with_rules else 0
        rows.append((i, to_text(q), len(found), len(everything), len(found) / max(1, len(everything)), rules / all_rules if all_rules else None, ledger.total("generated") / max(1.0, all_generated), spent / base))
    return ds.spark.createDataFrame(rows, "query int, query_text string, sets long, all_sets long, set_ratio double, rule_ratio double, candidate_ratio double, time_ratio double")


def pattern_counts(ds: Dataset, view: str, minsup: int, minconf: Fraction, queries: list[Expr]) -> DataFrame:
    """For each query its itemsets and rules, beside those of no query. All queries are mined in shared scans."""
    disjuncts = [set_disjuncts(rule_disjuncts(with_session_bounds(q, minsup, None))) for q in queries]
    found = mine_set_query(ds, [c for cs in disjuncts for c in cs], minsup)
    sizes, at = [], 0
    for cs in disjuncts:
        sizes.append(sum(map(len, found[at : at + len(cs)])))  # a query's disjuncts exclude each other
        at += len(cs)
    everything = sets_table(ds, frequent_sets(ds, minsup))
    rules = all_splits(everything, minconf).agg(F.count("*").alias("all_rules"), *[F.count_if(to_rule_predicate(q)).alias(f"q{i}") for i, q in enumerate(queries)]).first()
    total = everything.count()
    rows = [(view, i, n, total, rules[f"q{i - 1}"], rules["all_rules"]) for i, n in enumerate(sizes, 1)]
    return ds.spark.createDataFrame(rows, "view string, query int, sets long, all_sets long, rules long, all_rules long")


def run_session(ds: Dataset, queries: list[Expr], strategy: str, minsup: int, minconf: Fraction | None = None, coverage: str = "none", keep: int = 2, cache_pruning: bool = True) -> Session:
    """Answers all queries (itemsets only) under one strategy; costs are in the session's ledger."""
    session = Session(ds, strategy, minsup, minconf, coverage, keep, cache_pruning=cache_pruning)
    for q in queries:
        found = session.sets(q)
        if strategy == "postprocess":
            began = time.time()
            found.count()
            session.ledger.record(t_query=time.time() - began)
    return session


def nonempty(ds: Dataset, queries: list[Expr], minsup: int, n: int) -> list[Expr]:
    """The first ``n`` queries whose answer has an itemset."""
    out = []
    for q in queries:
        if len(out) == n:
            break
        if query_sets(ds, with_session_bounds(q, minsup, None)):
            out.append(q)
    return out


STRATEGIES = (("integrated", "none"), ("postprocess", "none"), ("incremental", "none"), ("incremental", "full"), ("incremental", "top"))


def compare_strategies(ds: Dataset, queries: list[Expr], minsup: int, strategies=STRATEGIES) -> DataFrame:
    """Ledger of one session under several strategies."""
    rows = [r for s, c in strategies for r in run_session(ds, queries, s, minsup, coverage=c).ledger.rows]
    from rulelattice.operators.ledger import SHAPE

    return ds.spark.createDataFrame(rows, SHAPE)


def session_report(ledger: DataFrame, metric: str = "generated") -> tuple[DataFrame, DataFrame]:
    """Running totals, and the query at which mining anew has cost more than mining everything."""
    return cumulative(ledger, metric), cutoff(ledger, metric, "integrated", "postprocess")


def slope(points: DataFrame) -> DataFrame:
    return proportionality(points, "set_ratio", "candidate_ratio")
