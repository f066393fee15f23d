"""Store of counted itemsets and the formula of what it covers."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from rulelattice.operators.candidates import Itemset
from rulelattice.operators.items import Dataset, sets_table
from rulelattice.plans.normalform import SetConj, disjoint, size_of, subtract, to_set_predicate
from rulelattice.runtime import LOCAL_CANDIDATES


class StoreMismatch(ValueError):
    """A store belongs to other data."""


@dataclass
class ItemsetStore:
    """Exact supports of all itemsets counted so far, frequent or not; whether one is frequent is a
    matter of each query's threshold."""

    ds: Dataset
    supports: dict[Itemset, int] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.supports = {(i,): n for i, n in enumerate(self.ds.supports)} | self.supports

    def append(self, counted: dict[Itemset, int]) -> dict[Itemset, int]:
        """Adds sets and returns the new ones."""
        new = {s: n for s, n in counted.items() if s and s not in self.supports}
        self.supports |= new
        if len(self.supports) > 20 * LOCAL_CANDIDATES:
            raise ValueError("the session's store outgrew the driver's bound; use a post-processing session")
        return new

    def satisfying(self, conjs: list[SetConj]) -> dict[Itemset, int]:
        return {s: n for s, n in self.supports.items() if any(c.allows(self.ds.named(s), n) for c in conjs)}

    def fingerprint(self) -> str:
        return f"{self.ds.size}:{len(self.ds.names)}:{sum(self.ds.supports)}"

    def save(self, path: str) -> None:
        """Parquet by size of the sets, so that a lookup by size reads its folder only."""
        from pyspark.sql import functions as F

        sets_table(self.ds, self.supports).withColumn("fingerprint", F.lit(self.fingerprint())).write.mode("overwrite").partitionBy("k").parquet(path)

    @staticmethod
    def load(ds: Dataset, path: str) -> ItemsetStore:
        rows = ds.spark.read.parquet(path).select("items", "support", "fingerprint").collect()
        made = ItemsetStore(ds)
        if rows and rows[0]["fingerprint"] != made.fingerprint():
            raise StoreMismatch(path)
        made.supports |= {tuple(sorted(ds.code[i] for i in r["items"])): r["support"] for r in rows}
        return made


def lookup(table: DataFrame, conjs: list[SetConj]) -> DataFrame:
    """Stored sets that a set query accepts, as a filter on the stored table."""
    return table.where(to_set_predicate(conjs))


@dataclass
class Coverage:
    """Disjuncts whose answers are in the store, each with the number of stored sets that satisfy it."""

    entries: list[tuple[SetConj, int]] = field(default_factory=list)

    def chosen(self, mode: str, keep: int, heuristic: str = "cached_count") -> list[SetConj]:
        if mode == "none":
            return []
        if mode == "full":
            return [c for c, _ in self.entries]
        key = {"cached_count": lambda e: -e[1], "literal_count": lambda e: len(e[0].literals()), "sup_lo": lambda e: e[0].sup_lo}[heuristic]
        return [c for c, _ in sorted(self.entries, key=key)[:keep]]

    def remainder(self, conjs: list[SetConj], mode: str, keep: int, heuristic: str = "cached_count") -> list[SetConj]:
        """What of a disjoint set query is not known to be stored, as disjoint conjunctions."""
        parts = list(conjs)
        for covered in self.chosen(mode, keep, heuristic):
            parts = [x for p in parts for x in subtract(p, covered)]
        return parts

    def add(self, conjs: list[SetConj], store: ItemsetStore, new: dict[Itemset, int]) -> None:
        named = [(self_names, n) for s, n in new.items() for self_names in [store.ds.named(s)]]
        bumped = [(c, k + sum(c.allows(s, n) for s, n in named)) for c, k in self.entries]
        added = [(c, len(store.satisfying([c]))) for c in conjs]
        kept = [(c, k) for c, k in bumped if not any(a.covers(c) for a, _ in added)]
        self.entries = kept + [a for a in added if not any(c.covers(a[0]) for c, _ in kept)]

    def size(self) -> tuple[int, int]:
        return size_of([c for c, _ in self.entries])


def disjoint_query(conjs: list[SetConj]) -> list[SetConj]:
    return disjoint(conjs)
