"""Incremental mining: every set query starts from what earlier queries counted."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from rulelattice.operators.candidates import Itemset, joined
from rulelattice.operators.items import Dataset
from rulelattice.operators.ledger import Ledger
from rulelattice.operators.levelwise import Branch, branch_of
from rulelattice.operators.projection import ProjectedCounts
from rulelattice.operators.store import ItemsetStore
from rulelattice.plans.normalform import SetConj


@dataclass
class Search:
    branch: Branch
    #: Rests whose whole set is known or certain to be frequent.
    frequent: set[Itemset] = field(default_factory=set)
    #: Whole sets that are certain to be frequent but not counted yet.
    pending: set[Itemset] = field(default_factory=set)

    def seed(self, store: ItemsetStore) -> None:
        """Stored frequent sets of the disjunct, closed downwards."""
        b = self.branch
        pos, allowed = set(b.pos), set(b.allowed)
        layer = set()
        for s, n in store.supports.items():
            if n >= b.need and pos <= set(s):
                rest = tuple(i for i in s if i not in pos)
                if allowed.issuperset(rest):
                    layer.add(rest)
        while layer:
            self.frequent |= layer
            layer = {r[:i] + r[i + 1 :] for r in layer for i in range(len(r))} - self.frequent
        if not pos:
            self.frequent.discard(())
        self.pending = {w for r in self.frequent if (w := b.whole(r)) and w not in store.supports}

    def offers(self) -> list[Itemset]:
        """Rests of any size that the frequent ones lead to."""
        b = self.branch
        if b.pos and () not in self.frequent:
            return [()]
        out = [(i,) for i in b.allowed if (i,) not in self.frequent]
        by_size: dict[int, list[Itemset]] = {}
        for r in self.frequent:
            if r:
                by_size.setdefault(len(r), []).append(r)
        return out + [c for level in by_size.values() for c in joined(level) if c not in self.frequent]


def certainly_infrequent(whole: Itemset, store: ItemsetStore, need: int) -> bool:
    """Whether the store holds a part of the set, possibly one without required items, that is too rare."""
    return any(store.supports.get(whole[:i] + whole[i + 1 :], need) < need for i in range(len(whole)) if len(whole) > 1)


def mine_incremental(ds: Dataset, conjs: list[SetConj], store: ItemsetStore, minsup: int = 1, cache_pruning: bool = True, kernel: str = "auto", ledger: Ledger | None = None, log: list | None = None) -> dict[Itemset, int]:
    """Counts what the disjuncts still need, all in shared scans with candidates of mixed sizes; returns the new sets."""
    ledger = ledger or Ledger()
    searches = [Search(branch_of(ds, SetConj(c.pos, c.neg, c.sup_lo), minsup)) for c in conjs]
    searches = [s for s in searches if s.branch.alive]
    began = time.time()
    for s in searches:
        s.seed(store)
    ledger.record(t_seed=time.time() - began)
    counts_of = ProjectedCounts(ds, [(s.branch.pos, s.branch.allowed) for s in searches])
    new: dict[Itemset, int] = {}
    before, rounds, pruned = (ds.scans, ds.rows_read, ds.occurrences_read), 0, 0
    while True:
        wanted: dict[Itemset, tuple[int, Itemset]] = {}
        for at, s in enumerate(searches):
            while True:
                moved = False
                open_ = []
                for rest in s.offers():
                    whole = s.branch.whole(rest)
                    n = store.supports.get(whole)
                    if n is not None:
                        if n >= s.branch.need:
                            s.frequent.add(rest)
                            moved = True
                    elif cache_pruning and certainly_infrequent(whole, store, s.branch.need):
                        pruned += 1
                    else:
                        open_.append(whole)
                if not moved:
                    break
            pos = set(s.branch.pos)
            for w in (*sorted(s.pending), *open_):
                wanted.setdefault(w, (at, tuple(i for i in w if i not in pos)))
        wanted = {w: x for w, x in wanted.items() if w not in store.supports}
        if not wanted:
            break
        counted = counts_of.count(wanted.values(), kernel)
        rounds += 1
        ledger.record(k=rounds, generated=len(wanted))
        if log is not None:
            log += [(at, w, counted[w]) for w, (at, _) in wanted.items()]
        new |= store.append(counted)
        for s in searches:
            s.pending = {w for w in s.pending if w not in store.supports}
    ledger.record(scans=ds.scans - before[0], rows_read=ds.rows_read - before[1], occurrences_read=ds.occurrences_read - before[2], iterations=rounds, pruned_by_cache=pruned)
    return new
