"""The three roles of a residual itemset: rule-set, body-set and head-set of each rule disjunct."""

from __future__ import annotations

from pyspark.sql import DataFrame

from rulelattice.operators.candidates import Itemset
from rulelattice.operators.counting import count_sets
from rulelattice.operators.items import Dataset
from rulelattice.plans.normalform import RuleConj, to_set_conj


def _coded(ds: Dataset, items: frozenset) -> set[int]:
    return {ds.code[i] for i in items if i in ds.code}


def body_set(ds: Dataset, rest: Itemset, conj: RuleConj) -> Itemset | None:
    """The body that a residual set gives; none if it holds an item barred from bodies."""
    return None if set(rest) & _coded(ds, conj.body_out) else tuple(sorted({*rest, *_coded(ds, conj.body_in)}))


def head_set(ds: Dataset, rest: Itemset, conj: RuleConj) -> Itemset | None:
    return None if set(rest) & _coded(ds, conj.head_out) else tuple(sorted({*rest, *_coded(ds, conj.head_in)}))


def families(ds: Dataset, sets: dict[Itemset, int], conjs: list[RuleConj], count_heads: bool = True, kernel: str = "auto") -> DataFrame:
    """(rule_disjunct, role, items, support). Residual sets belong to the disjunct's own rule-sets;
    bodies and heads that ``sets`` does not hold are counted in one scan for all disjuncts."""
    roles: list[tuple[int, str, Itemset]] = []
    for r, conj in enumerate(conjs):
        asked = to_set_conj(conj)
        pos = _coded(ds, asked.pos)
        for s, n in sets.items():
            if not asked.allows([ds.names[i] for i in s], n):
                continue
            rest = tuple(i for i in s if i not in pos)
            roles.append((r, "rule", s))
            roles += [(r, role, made) for role, made in (("body", body_set(ds, rest, conj)), ("head", head_set(ds, rest, conj))) if made is not None and (role == "body" or count_heads)]
    roles = list(dict.fromkeys(roles))
    counted = count_sets(ds, [s for _, _, s in roles if s not in sets], kernel) | sets
    return ds.spark.createDataFrame([(r, role, ds.named(s), counted[s]) for r, role, s in roles], "rule_disjunct int, role string, items array<string>, support long")


def audit(ds: Dataset, table: DataFrame) -> DataFrame:
    """Sets that have a role in no disjunct's rules; the method generates none."""
    return table.groupBy("items").pivot("role", ["rule", "body", "head"]).count().where("rule is null and body is null and head is null")
