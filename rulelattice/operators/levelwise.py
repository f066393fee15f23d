"""Level-wise search for frequent itemsets, unconstrained and under a set query.

All disjuncts of a set query advance together: each level counts the candidates of every disjunct in
one scan. A disjunct's search starts at its required items, so it saves as many levels, and never
offers a forbidden item. The rests are counted in the projected databases: transactions without the
required items leave at the first scan, and required, forbidden and too rare items are stripped.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulelattice.operators.candidates import Itemset, join_step, joined, prune_step
from rulelattice.operators.counting import pair_counts
from rulelattice.operators.items import Dataset
from rulelattice.operators.ledger import Ledger
from rulelattice.operators.projection import ProjectedCounts
from rulelattice.plans.normalform import SetConj
from rulelattice.runtime import LOCAL_CANDIDATES, cut


#: Pairs from which the second level is counted without listing them.
MANY_PAIRS = 100_000


class TooManyCandidates(ValueError):
    """A level has more candidates than allowed; add constraints or raise the minimal support."""


@dataclass
class Branch:
    """State of one disjunct: required codes, allowed codes, thresholds and the frequent rests so far."""

    conj: SetConj
    pos: Itemset
    allowed: list[int]
    need: int
    alive: bool = True
    level: list[Itemset] = field(default_factory=list)

    def whole(self, rest: Itemset) -> Itemset:
        return tuple(sorted((*self.pos, *rest)))


def branch_of(ds: Dataset, conj: SetConj, minsup: int) -> Branch:
    need = max(conj.sup_lo, minsup)
    if need < ds.min_support:
        raise ValueError(f"the data are encoded for supports of {ds.min_support} or more, the query asks for {need}")
    known = all(p in ds.code for p in conj.pos)
    pos = tuple(sorted(ds.code[p] for p in conj.pos)) if known else ()
    alive = known and all(ds.supports[p] >= need for p in pos) and (conj.sup_hi is None or conj.sup_hi > need)
    barred = {ds.code[i] for i in conj.neg if i in ds.code} | set(pos)
    allowed = [i for i in range(len(ds.names)) if ds.supports[i] >= need and i not in barred] if alive else []
    return Branch(conj, pos, allowed, need, alive)


def mine_set_query(ds: Dataset, conjs: list[SetConj], minsup: int = 1, kernel: str = "auto", ledger: Ledger | None = None, max_k: int | None = None, max_candidates: int = LOCAL_CANDIDATES, log: list | None = None) -> list[dict[Itemset, int]]:
    """Frequent itemsets of each disjunct with their supports.

    ``log`` gets (disjunct, itemset, support) of every candidate that is counted; of pairs that are counted
    without a list of candidates, of the frequent ones.
    """
    ledger = ledger or Ledger()
    branches = [branch_of(ds, c, minsup) for c in conjs]
    found: list[dict[Itemset, int]] = [{} for _ in branches]
    counts_of = ProjectedCounts(ds, [(b.pos, b.allowed) for b in branches])
    before, began, level = (ds.scans, ds.rows_read, ds.occurrences_read), time.time(), 0
    offers: list[list[Itemset]] = [[()] if b.alive and b.pos else [(i,) for i in b.allowed] if b.alive else [] for b in branches]
    while any(offers):
        wanted = list(dict.fromkeys(b.whole(r) for b, rs in zip(branches, offers, strict=True) for r in rs))
        if len(wanted) > max_candidates:
            raise TooManyCandidates(f"{len(wanted)} candidates at level {level}")
        counts = counts_of.count(((at, r) for at, rs in enumerate(offers) for r in rs), kernel)
        if log is not None:
            log += [(at, b.whole(r), counts[b.whole(r)]) for at, (b, rs) in enumerate(zip(branches, offers, strict=True)) for r in rs]
        deeper = 0
        for at, (b, rests) in enumerate(zip(branches, offers, strict=True)):
            good = [r for r in rests if counts[b.whole(r)] >= b.need]
            found[at].update((b.whole(r), counts[b.whole(r)]) for r in good)
            if rests:
                ledger.record(k=level, disjunct=at, generated=len(rests), infrequent=len(rests) - len(good), frequent=len(good))
            if not good or max_k is not None and len(b.whole(good[0])) >= max_k:
                offers[at] = []
            elif not b.pos and len(good[0]) == 1 and len(good) * (len(good) - 1) // 2 > MANY_PAIRS:
                pairs = _many_pairs(ds, b, max_candidates)
                deeper = 1
                if log is not None:
                    log += [(at, s, n) for s, n in pairs.items()]
                found[at].update(pairs)
                ledger.record(k=level + 1, disjunct=at, generated=len(good) * (len(good) - 1) // 2, frequent=len(pairs))
                offers[at] = [] if max_k == 2 else joined(pairs)
            elif good == [()]:
                offers[at] = [(i,) for i in b.allowed]
            else:
                offers[at] = joined(good)
        level += 1 + deeper
    ledger.record(scans=ds.scans - before[0], rows_read=ds.rows_read - before[1], occurrences_read=ds.occurrences_read - before[2], iterations=level, t_sets=time.time() - began)
    return [{s: n for s, n in f.items() if b.conj.sup_hi is None or n < b.conj.sup_hi} for b, f in zip(branches, found, strict=True)]


def _many_pairs(ds: Dataset, b: Branch, most: int) -> dict[Itemset, int]:
    """Frequent pairs of a disjunct without required items; at most ``most`` come to the driver."""
    ds.scanned(ds.size, ds.occurrences)
    barred = any(i in ds.code for i in b.conj.neg)
    rows = pair_counts(ds, b.need, b.allowed if barred else None).limit(most + 1).collect()
    if len(rows) > most:
        raise TooManyCandidates(f"over {most} frequent pairs")
    return {(r["a"], r["b"]): int(r["support"]) for r in rows}


def frequent_sets(ds: Dataset, minsup: int, kernel: str = "auto", ledger: Ledger | None = None, max_k: int | None = None, max_candidates: int = LOCAL_CANDIDATES) -> dict[Itemset, int]:
    """All frequent itemsets: the unconstrained search."""
    return mine_set_query(ds, [SetConj(sup_lo=minsup)], minsup, kernel, ledger, max_k, max_candidates)[0]


def frequent_sets_as_tables(ds: Dataset, minsup: int, max_k: int | None = None) -> DataFrame:
    """(items array<int>, k, support) with candidates that stay tables from level to level.

    For answers beyond the driver's bound: join, prune and count are joins, each level is a checkpoint.
    """
    singles = ds.spark.createDataFrame([([i], n) for i, n in enumerate(ds.supports) if n >= minsup], "items array<int>, support long")
    done = [singles.withColumn("k", F.lit(1))]
    if max_k == 1:
        return done[0]
    # Pairs are counted as they occur: all single items have one prefix, so a join would offer every pair.
    ds.scanned(ds.size, ds.occurrences)
    level, k = cut(pair_counts(ds, minsup).select(F.array("a", "b").alias("items"), "support")), 2
    done.append(level.withColumn("k", F.lit(2)))
    while max_k is None or k < max_k:
        offered = prune_step(join_step(level.select("items")), level.select("items"))
        listed = offered.withColumn("probe", F.element_at("items", -1)).withColumn("key", F.array_join(F.transform("items", lambda i: i.cast("string")), ","))
        offered_tx = ds.tx.where(F.size("items") > k).select(F.col("items").alias("t"), F.explode("items").alias("probe"))
        met = offered_tx.join(listed, "probe").where(F.size(F.array_except("items", "t")) == 0)
        counted = met.groupBy("key").agg(F.count("*").alias("support")).where(F.col("support") >= minsup)
        level = cut(counted.select(F.transform(F.split("key", ","), lambda x: x.cast("int")).alias("items"), "support"))
        ds.scanned(ds.size, ds.occurrences)
        k += 1
        if level.isEmpty():
            break
        done.append(level.withColumn("k", F.lit(k)))
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    return out


def named_table(ds: Dataset, coded: DataFrame) -> DataFrame:
    """Code arrays as sorted name arrays, by a join with the dictionary."""
    names = ds.spark.createDataFrame(list(enumerate(ds.names)), "iid int, name string")
    keyed = coded.withColumn("key", F.array_join(F.transform("items", lambda i: i.cast("string")), ","))
    each = keyed.select("key", "k", "support", F.explode("items").alias("iid")).join(F.broadcast(names), "iid")
    return each.groupBy("key", "k", "support").agg(F.sort_array(F.collect_list("name")).alias("items")).select("items", "k", "support")


def level_one_supports_closed(ds: Dataset, sets: dict[Itemset, int]) -> bool:
    """Whether no itemset is more frequent than one of its parts, and every part is there."""
    return all(len(s) < 2 or all(sets.get(s[:i] + s[i + 1 :], -1) >= n for i in range(len(s))) for s, n in sets.items())
