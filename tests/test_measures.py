"""Counting on projected databases, real measures, heads grown under a query, and sessions beyond the driver."""

from fractions import Fraction
from itertools import combinations

import pytest

from rulelattice.operators import levelwise, rulegen
from rulelattice.operators.integrated import MiningOptions, query_rules
from rulelattice.operators.items import encode, sets_table
from rulelattice.operators.session import Session
from rulelattice.plans.algebra import parse_query
from rulelattice.plans.normalform import SetConj, rule_disjuncts


def dataset(spark, rows):
    return encode(spark.createDataFrame([(t, i) for t, row in enumerate(rows) for i in row], "tid long, item string"))


ROWS = [set("abcd"), set("abc"), set("abd"), set("bcd"), set("ae"), set("abce"), set("ce"), set("b")]


@pytest.mark.parametrize("kernel", ["probe", "bitmap", "subset", "partitioned"])
def test_disjuncts_are_counted_on_what_they_leave(spark, kernel):
    ds = dataset(spark, ROWS)
    conjs = [SetConj(frozenset("a"), frozenset("e"), 1), SetConj(frozenset("bc"), frozenset(), 1), SetConj(frozenset("b"), frozenset("a"), 2), SetConj(frozenset(), frozenset("b"), 1)]
    found = levelwise.mine_set_query(ds, conjs, 1, kernel)
    for c, f in zip(conjs, found, strict=True):
        want = {}
        for n in range(1, 6):
            for s in combinations("abcde", n):
                k = sum(set(s) <= r for r in ROWS)
                if c.pos <= set(s) and not c.neg & set(s) and k >= c.sup_lo:
                    want[s] = k
        assert {tuple(ds.named(s)): n for s, n in f.items()} == want


def test_scans_after_the_first_read_projected_rows_only(spark):
    ds = dataset(spark, ROWS)
    levelwise.mine_set_query(ds, [SetConj(frozenset("ab"), frozenset("e"), 1)], 1, "probe")
    left = [r - set("abe") for r in ROWS if set("ab") <= r]
    # The whole data once, then the projected rows: for single items, and for the one pair.
    assert ds.rows_read == len(ROWS) + 2 * len(left)
    assert ds.occurrences_read == sum(map(len, ROWS)) + 2 * sum(map(len, left))


def test_bodies_are_counted_on_transactions_that_hold_their_items(spark):
    ds = dataset(spark, ROWS)
    wanted = spark.createDataFrame([(["a", "b"],), (["a", "c"],), (["b", "c"],), (["a"],)], "items array<string>")
    known = spark.createDataFrame([], "items array<string>, support long")
    got = {tuple(r["items"]): r["support"] for r in rulegen.missing_supports(ds, wanted, known, "probe", required=[frozenset("a")]).collect()}
    assert got == {s: sum(set(s) <= r for r in ROWS) for s in [("a", "b"), ("a", "c"), ("b", "c"), ("a",)]}


@pytest.mark.parametrize("text", ["body('a') and confidence >= 0.5", "head('b') and not body('c') and confidence >= 0.4", "not head('a') or body('e')", "head('a') and head('b') and not confidence >= 0.9", "body('a') and head('a')"])
def test_grown_heads_give_all_rules(spark, text):
    ds = dataset(spark, ROWS)
    q = parse_query(f"({text}) and support >= 1")
    rows = lambda o: sorted((tuple(r["body_items"]), tuple(r["head_items"]), r["support"], r["body_support"]) for r in query_rules(ds, q, o).collect())
    assert rows(MiningOptions(heads="levelwise")) == rows(MiningOptions(heads="splits"))


def test_heads_shrink_as_their_parts_do(spark):
    """A head is confident only if every part of it is, with the other items in the body."""
    ds = dataset(spark, ROWS)
    sets = sets_table(ds, levelwise.frequent_sets(ds, 1))
    share = Fraction(1, 2)
    rules = {(tuple(r["body_items"]), tuple(r["head_items"])) for r in rulegen.all_splits(sets, share).collect()}
    for body, head in rules:
        for i in head:
            if len(head) > 1:
                assert (tuple(sorted((*body, i))), tuple(x for x in head if x != i)) in rules


def test_an_itemset_with_35_free_items(spark):
    items = [f"i{k:02d}" for k in range(36)]
    rows = [set(items)] * 5 + [set(items) - {i} for i in items for _ in range(5)]
    ds = dataset(spark, rows)
    sets = spark.createDataFrame([(items, 36, 5)], "items array<string>, k int, support long")
    got = rulegen.rules_of(ds, sets, rule_disjuncts(parse_query("not head('i00') and confidence >= 0.5")), kernel="probe").collect()
    assert sorted(tuple(r["head_items"]) for r in got) == [(i,) for i in items[1:]] and {r["body_support"] for r in got} == {10}
    with pytest.raises(ValueError):
        rulegen.rules_of(ds, sets, rule_disjuncts(parse_query("confidence >= 0.5")), heads="splits")


def test_postprocessing_beyond_the_driver(spark):
    ds = dataset(spark, ROWS)
    rows = lambda s: sorted((tuple(r["body_items"]), tuple(r["head_items"]), r["support"], r["body_support"]) for r in s.ask("body('a') and confidence >= 0.3").collect())
    want = rows(Session(ds, "integrated", 1))
    assert rows(Session(ds, "postprocess", 1, most_local=3)) == rows(Session(ds, "postprocess", 1)) == want


def test_log_shows_what_a_session_counts_again(spark):
    for strategy in ("integrated", "incremental"):
        session = Session(dataset(spark, ROWS), strategy, 1)
        for q in ("body('a')", "body('a') and head('b')"):
            session.sets(q)
        again = len(session.log) - len({s for _, s, _ in session.log})
        assert again > 0 if strategy == "integrated" else again == 0
