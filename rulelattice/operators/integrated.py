"""Integrated querying: the query's conditions steer the search itself."""

from __future__ import annotations

import time
from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import DataFrame

from rulelattice.operators.candidates import Itemset
from rulelattice.operators.items import Dataset, sets_table
from rulelattice.operators.ledger import Ledger
from rulelattice.operators.levelwise import mine_set_query
from rulelattice.operators.rulegen import rules_of
from rulelattice.plans.algebra import And, Expr, MinConfidence, MinSupport
from rulelattice.plans.normalform import rule_disjuncts, set_disjuncts


@dataclass(frozen=True)
class MiningOptions:
    kernel: str = "auto"
    #: ``ddnf``: rule and set query disjoint; ``set_ddnf``: the set query only; ``dnf``: neither.
    normal: str = "ddnf"
    sort_by_support: bool = True
    negated_confidence: str = "filter"
    strict_confidence: bool = False
    allow_empty: bool = False
    #: With ``dnf`` forms: keep itemsets and rules that several disjuncts produce.
    keep_duplicates: bool = False
    #: ``auto``, ``splits`` or ``levelwise``: how rules are made from itemsets.
    heads: str = "auto"


def with_session_bounds(query: Expr, minsup: int, minconf: Fraction | None) -> Expr:
    return And((query, MinSupport(minsup), *([MinConfidence(minconf)] if minconf is not None else [])))


def query_sets(ds: Dataset, query: Expr, options: MiningOptions = MiningOptions(), ledger: Ledger | None = None, log: list | None = None) -> dict[Itemset, int]:
    """Itemsets that the query accepts."""
    rules = rule_disjuncts(query, options.normal, options.sort_by_support)
    parts = mine_set_query(ds, set_disjuncts(rules, options.normal, options.sort_by_support), 1, options.kernel, ledger, log=log)
    return {s: n for p in parts for s, n in p.items()}


def generated_sets(ds: Dataset, query: Expr, options: MiningOptions, ledger: Ledger | None = None) -> list[tuple[int, Itemset, int]]:
    """(disjunct, itemset, support) with repeats, to see what a normal form does twice."""
    rules = rule_disjuncts(query, options.normal, options.sort_by_support)
    parts = mine_set_query(ds, set_disjuncts(rules, options.normal, options.sort_by_support), 1, options.kernel, ledger)
    return [(i, s, n) for i, p in enumerate(parts) for s, n in p.items()]


def query_rules(ds: Dataset, query: Expr, options: MiningOptions = MiningOptions(), ledger: Ledger | None = None) -> DataFrame:
    """Rules that the query accepts, as (body_items, head_items, support, body_support)."""
    ledger = ledger or Ledger()
    rules = rule_disjuncts(query, options.normal, options.sort_by_support)
    sets = query_sets(ds, query, options, ledger)
    began, before = time.time(), ds.scans
    found = rules_of(ds, sets_table(ds, sets), rules, kernel=options.kernel, allow_empty=options.allow_empty, strict=options.strict_confidence, negated_confidence=options.negated_confidence, heads=options.heads)
    ledger.record(extra_scans=ds.scans - before, t_rules=time.time() - began)
    if options.normal != "ddnf" and not options.keep_duplicates:
        found = found.dropDuplicates(["body_items", "head_items"])
    return found
