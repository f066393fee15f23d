"""Candidate itemsets from frequent ones: locally on the driver, and as tables beyond its bound."""

from __future__ import annotations

from collections.abc import Iterable
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Itemset = tuple[int, ...]


def joined(frequent: Iterable[Itemset]) -> list[Itemset]:
    """Unions of two frequent sets of one size that differ in the last item, all of whose parts are frequent."""
    known = set(frequent)
    by_prefix: dict[Itemset, list[int]] = {}
    for s in sorted(known):
        by_prefix.setdefault(s[:-1], []).append(s[-1])
    out = []
    for prefix, lasts in by_prefix.items():
        for a, b in combinations(lasts, 2):
            made = (*prefix, a, b)
            if all(made[:i] + made[i + 1 :] in known for i in range(len(made) - 2)):
                out.append(made)
    return out


def join_step(frequent: DataFrame) -> DataFrame:
    """The same as a table: pairs with a common prefix. ``frequent`` has sorted code arrays ``items``."""
    n = F.size("items")
    halves = frequent.select(F.slice("items", 1, n - 1).alias("prefix"), F.element_at("items", -1).alias("last"))
    other = halves.select(F.col("prefix").alias("prefix2"), F.col("last").alias("last2"))
    pairs = halves.join(other, (F.col("prefix") == F.col("prefix2")) & (F.col("last") < F.col("last2")))
    return pairs.select(F.concat("prefix", F.array("last", "last2")).alias("items"))


def prune_step(candidates: DataFrame, frequent: DataFrame) -> DataFrame:
    """Candidates all of whose subsets that lack one item are frequent."""
    n = F.size("items")
    parts = candidates.select("items", F.explode(F.transform(F.sequence(F.lit(1), n), lambda i: F.concat(F.slice("items", 1, i - 1), F.slice("items", i + 1, n)))).alias("part"))
    met = parts.join(frequent.select(F.col("items").alias("part")), "part", "left_semi")
    return met.groupBy("items").agg(F.count("*").alias("met")).where(F.col("met") == n).select("items")
