"""Projected databases: the transactions that hold all required items, without required and forbidden ones."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.operators.candidates import Itemset
from rulelattice.operators.counting import count_sets
from rulelattice.operators.items import Dataset
from rulelattice.plans.normalform import SetConj
from rulelattice.runtime import cut


def _codes(items: list[int]) -> Column:
    return F.array(*map(F.lit, items)).cast("array<int>")


def _rest(ds: Dataset, conj: SetConj) -> Column | None:
    """What a transaction leaves under a disjunct; null where it lacks a required item."""
    if any(p not in ds.code for p in conj.pos):
        return None
    gone = [ds.code[i] for i in sorted(conj.pos | conj.neg) if i in ds.code]
    rest = F.array_except("items", _codes(gone)) if gone else F.col("items")
    for p in sorted(conj.pos):
        rest = F.when(F.array_contains("items", ds.code[p]), rest)
    return rest


def project(ds: Dataset, conj: SetConj) -> DataFrame:
    """(nid, items) of one disjunct; transactions that become empty stay."""
    rest = _rest(ds, conj)
    if rest is None:
        return ds.tx.limit(0)
    return ds.tx.select("nid", rest.alias("items")).where("items is not null")


def project_all(ds: Dataset, conjs: list[SetConj]) -> DataFrame:
    """(disjunct, nid, items) of all disjuncts in one pass, without a shuffle."""
    offers = [F.struct(F.lit(i).alias("disjunct"), r.alias("items")) for i, c in enumerate(conjs) if (r := _rest(ds, c)) is not None]
    if not offers:
        return ds.tx.limit(0).select(F.lit(0).alias("disjunct"), "nid", "items")
    held = F.filter(F.array(*offers), lambda o: o["items"].isNotNull())
    return ds.tx.select("nid", F.explode(held).alias("o")).select("o.disjunct", "nid", "o.items")


def sizes(ds: Dataset, conjs: list[SetConj]) -> DataFrame:
    """Rows and item occurrences of each projected database."""
    return project_all(ds, conjs).groupBy("disjunct").agg(F.count("*").alias("transactions"), F.sum(F.size("items")).alias("occurrences"))


class ProjectedCounts:
    """Counts residual sets on the projected databases of several disjuncts, made in one pass over the data.

    Every disjunct's items get codes of their own, so that the transactions that the disjuncts leave form one
    data set, on which any kernel counts. Disjuncts without required items leave every transaction; theirs
    are counted on the data as they are. The pass is made at the first count that needs it.
    """

    def __init__(self, ds: Dataset, frames: list[tuple[Itemset, Iterable[int]]]) -> None:
        """``frames``: required codes and codes that may stand beside them, of each disjunct."""
        self.ds, self.frames = ds, [(pos, sorted(beside)) for pos, beside in frames]
        self.held: Dataset | None = None
        self.sizes: dict[int, int] = {}
        self.offset: dict[int, int] = {}

    def _offer(self, d: int, width: int, offset: int) -> Column:
        """What a transaction leaves for a disjunct, in the disjunct's codes; null where it lacks a required item.

        Codes rank items by support, so those below ``width`` are allowed but for the few barred ones.
        """
        pos, beside = self.frames[d]
        gone = sorted(set(range(width)) - set(beside))
        rest = F.array_except("items", _codes(gone)) if gone else F.col("items")
        coded = F.transform(F.filter(rest, lambda x: x < width), lambda x: x + offset)
        for p in pos:
            coded = F.when(F.array_contains("items", p), coded)
        return F.struct(F.lit(d).alias("disjunct"), coded.alias("items"))

    def _made(self) -> Dataset:
        if self.held is not None:
            return self.held
        offers, total = [], 0
        for d, (pos, beside) in enumerate(self.frames):
            if pos:
                width = beside[-1] + 1 if beside else 0
                offers.append(self._offer(d, width, total))
                self.offset[d] = total
                total += width
        held = F.filter(F.array(*offers), lambda o: o["items"].isNotNull())
        rows = cut(self.ds.tx.select("nid", F.explode(held).alias("o")).select("o.disjunct", "o.items", F.monotonically_increasing_id().alias("nid")))
        self.ds.scanned(self.ds.size, self.ds.occurrences)
        got = rows.select("disjunct", F.explode(F.concat(F.array(F.lit(-1)), "items")).alias("iid")).groupBy("disjunct", "iid").agg(F.count("*").alias("n")).collect()  # a row for each allowed item
        supports = [0] * total
        for r in got:
            if r["iid"] < 0:
                self.sizes[r["disjunct"]] = r["n"]
            else:
                supports[r["iid"]] = r["n"]
        self.held = Dataset(self.ds.spark, rows.drop("disjunct"), [str(i) for i in range(total)], supports, sum(self.sizes.values()), 1)
        self.held.scanned(self.held.size, self.held.occurrences)
        self._handed_on()
        return self.held

    def _handed_on(self) -> None:
        """Adds what was read here to the data set's own counters."""
        for c in ("scans", "rows_read", "occurrences_read"):
            setattr(self.ds, c, getattr(self.ds, c) + getattr(self.held, c))
            setattr(self.held, c, 0)

    def count(self, asked: Iterable[tuple[int, Itemset]], kernel: str = "auto") -> dict[Itemset, int]:
        """Supports by whole set of (disjunct, rest) pairs; a whole set asked for twice is counted once."""
        whole = lambda d, rest: tuple(sorted((*self.frames[d][0], *rest)))
        first = {}
        for d, rest in asked:
            first.setdefault(whole(d, rest), (d, rest))
        known = {w: self.ds.size if not w else self.ds.supports[w[0]] for w in first if len(w) < 2}
        plain = [w for w, (d, _) in first.items() if w not in known and not self.frames[d][0]]
        known |= count_sets(self.ds, plain, kernel) if plain else {}
        rest_of = {w: x for w, x in first.items() if w not in known}
        if rest_of:
            held = self._made()
            coded = {w: tuple(sorted(c + self.offset[d] for c in rest)) for w, (d, rest) in rest_of.items()}
            found = count_sets(held, [c for c in coded.values() if c], kernel)
            self._handed_on()
            known |= {w: found[c] if c else self.sizes.get(rest_of[w][0], 0) for w, c in coded.items()}
        return known
