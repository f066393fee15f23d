"""Sessions of rule queries under three strategies.

``integrated`` mines every query anew; ``postprocess`` mines everything once and looks answers up;
``incremental`` counts only what earlier queries have not, and may subtract from a query what earlier
answers cover (``coverage``: ``none``, ``full`` or ``top``, the last with the ``keep`` broadest ones).
"""

from __future__ import annotations

import time
import uuid
from dataclasses import dataclass, field
from fractions import Fraction

from pyspark.sql import DataFrame

from rulelattice.operators.candidates import Itemset
from rulelattice.operators.incremental import mine_incremental
from rulelattice.operators.integrated import MiningOptions, query_sets, with_session_bounds
from rulelattice.operators.items import Dataset, sets_table
from rulelattice.operators.ledger import Ledger
from rulelattice.operators.levelwise import TooManyCandidates, frequent_sets, frequent_sets_as_tables, named_table
from rulelattice.operators.rulegen import all_splits, rules_of
from rulelattice.operators.store import Coverage, ItemsetStore, lookup
from rulelattice.plans.algebra import And, Expr, Or, parse_query, to_rule_predicate, to_text
from rulelattice.plans.normalform import SetConj, disjoint, rule_disjuncts, set_disjuncts, size_of, to_set_conj
from rulelattice.runtime import LOCAL_CANDIDATES, shared_dir


class BelowThreshold(ValueError):
    """A post-processing session cannot answer below the support it was mined at."""


@dataclass
class Session:
    ds: Dataset
    strategy: str = "integrated"
    minsup: int = 1
    minconf: Fraction | None = None
    coverage: str = "none"
    keep: int = 2
    heuristic: str = "cached_count"
    cache_pruning: bool = True
    materialize: str = "sets"
    #: Most candidates of a level that the driver holds while everything is mined; beyond it they stay tables.
    most_local: int = LOCAL_CANDIDATES
    options: MiningOptions = MiningOptions()
    name: str = "session"
    ledger: Ledger = field(default_factory=Ledger)
    asked: list[Expr] = field(default_factory=list)
    #: (disjunct, itemset, support) of every candidate counted for itemsets, repeats included.
    log: list = field(default_factory=list)

    def __post_init__(self) -> None:
        self.ledger.session = self.name
        self.ledger.strategy = self.strategy if self.coverage == "none" else f"{self.strategy}_{self.coverage}"
        self.store = ItemsetStore(self.ds)
        self.covered = Coverage()
        self.table: DataFrame | None = None
        if self.strategy == "postprocess":
            self._mine_everything()

    def _mine_everything(self) -> None:
        began = time.time()
        path = f"{shared_dir(self.ds.spark)}/store-{uuid.uuid4().hex}"
        try:
            sets = sets_table(self.ds, frequent_sets(self.ds, self.minsup, self.options.kernel, self.ledger, max_candidates=self.most_local))
        except TooManyCandidates:
            # More than the driver may hold: candidates and answers stay tables.
            sets = named_table(self.ds, frequent_sets_as_tables(self.ds, self.minsup))
        sets.write.partitionBy("k").parquet(path)
        self.table = self.ds.spark.read.parquet(path).select("items", "k", "support")
        if self.materialize == "rules":
            all_splits(self.table, self.minconf or Fraction(0)).write.parquet(path + "-rules")
            self.rules_table = self.ds.spark.read.parquet(path + "-rules")
        self.ledger.record(t_mining=time.time() - began, stored=self.table.count())

    def _parsed(self, query: Expr | str) -> Expr:
        query = parse_query(query) if isinstance(query, str) else query
        return with_session_bounds(query, self.minsup, self.minconf)

    def _answer_sets(self, query: Expr) -> dict[Itemset, int] | DataFrame:
        rules = rule_disjuncts(query, "ddnf", self.options.sort_by_support)
        wanted = set_disjuncts(rules, "ddnf", self.options.sort_by_support)
        if self.strategy == "integrated":
            return query_sets(self.ds, query, self.options, self.ledger, self.log)
        if self.strategy == "postprocess":
            if wanted and min(c.sup_lo for c in wanted) < self.minsup:
                raise BelowThreshold(f"the store holds supports of {self.minsup} or more")
            return lookup(self.table, wanted)
        began = time.time()
        rest = self.covered.remainder(wanted, self.coverage, self.keep, self.heuristic)
        looked = time.time() - began
        new = mine_incremental(self.ds, rest, self.store, self.minsup, self.cache_pruning, self.options.kernel, self.ledger, self.log)
        seeded, again = self.ledger.total("t_seed", self.ledger.query), time.time()
        answer = self.store.satisfying(wanted)
        looked += seeded + time.time() - again
        self.covered.add(wanted, self.store, new)
        d, n = self.covered.size()
        stored = sum(s >= self.minsup for s in self.store.supports.values())
        self.ledger.record(t_lookup=looked, reused=len(answer) - sum(s in new for s in answer), needed=len(answer), mined_disjuncts=size_of(rest)[0], mined_literals=size_of(rest)[1], coverage_disjuncts=d, coverage_literals=n, stored=len(self.store.supports), stored_frequent=stored)
        return answer

    def sets(self, query: Expr | str) -> DataFrame:
        """Itemsets of the answer."""
        self.ledger.query += 1
        bounded, began, before = self._parsed(query), time.time(), self.ds.scans
        self.asked.append(bounded)
        found = self._answer_sets(bounded)
        out = found if isinstance(found, DataFrame) else sets_table(self.ds, found)
        self.ledger.record(query_scans=self.ds.scans - before, t_query=time.time() - began)
        return out

    def ask(self, query: Expr | str) -> DataFrame:
        """Rules of the answer, as (body_items, head_items, support, body_support)."""
        sets = self.sets(query)
        bounded = self.asked[-1]
        if self.strategy == "postprocess" and self.materialize == "rules":
            return self.rules_table.where(to_rule_predicate(bounded))
        known, remember = self.table, None
        if self.strategy == "incremental":
            known, remember = sets_table(self.ds, self.store.supports), {}
        rules = rules_of(self.ds, sets, rule_disjuncts(bounded, "ddnf", self.options.sort_by_support), known, self.options.kernel, self.options.allow_empty, self.options.strict_confidence, remember=remember, heads=self.options.heads)
        if remember:
            self.store.append(remember)
        self.answers = [*getattr(self, "answers", []), rules]
        rules.createOrReplaceTempView(f"answer_{len(self.asked)}")
        return rules

    def refine(self, extra: Expr | str) -> DataFrame:
        """The last query with a further condition."""
        extra = parse_query(extra) if isinstance(extra, str) else extra
        return self.ask(And((self.asked[-1], extra)))

    def widen(self, extra: Expr | str) -> DataFrame:
        """The last query or another one."""
        extra = parse_query(extra) if isinstance(extra, str) else extra
        return self.ask(Or((self.asked[-1], extra)))

    def history(self) -> list[str]:
        return [to_text(q) for q in self.asked]

    def diff(self, a: int, b: int) -> DataFrame:
        """Rules of answer ``b`` that answer ``a`` has not (counted from 1)."""
        return self.answers[b - 1].exceptAll(self.answers[a - 1])

    def explain(self, query: Expr | str) -> dict:
        """Both normal forms, expected sizes of the projected databases, covered and remaining part."""
        bounded = self._parsed(query)
        rules = rule_disjuncts(bounded)
        sets = set_disjuncts(rules)
        bound = lambda c: min((self.ds.supports[self.ds.code[i]] if i in self.ds.code else 0 for i in c.pos), default=self.ds.size)
        return {"rule_disjuncts": rules, "set_disjuncts": sets, "most_projected": [bound(c) for c in sets], "remaining": self.covered.remainder(sets, self.coverage, self.keep)}

    def close(self) -> None:
        self.ds.release()


def advise(all_frequent_feasible: bool, expected_queries: int, cutoff: int) -> str:
    """Post-processing where everything can be mined and the session outlasts the cut-off; else incremental."""
    return "postprocess" if all_frequent_feasible and expected_queries > cutoff else "incremental"


def set_query_of(query: Expr) -> list[SetConj]:
    return disjoint([to_set_conj(c) for c in rule_disjuncts(query)])
