"""Mining and sessions against exponential brute force."""

import random
from fractions import Fraction
from itertools import combinations

import pytest

from rulelattice import catalogue
from rulelattice.operators import baselines, levelwise, projection, rulegen
from rulelattice.operators.counting import count_sets
from rulelattice.operators.integrated import MiningOptions, query_rules
from rulelattice.operators.items import encode, sets_table
from rulelattice.operators.session import BelowThreshold, Session, advise
from rulelattice.plans.algebra import holds, parse_query
from rulelattice.plans.normalform import SetConj, rule_disjuncts, set_disjuncts
from rulelattice.workload import random_queries

ITEMS = "abcdef"


def database(seed: int, n: int = 24) -> list[str]:
    rng = random.Random(seed)
    return ["".join(i for i in ITEMS if rng.random() < 0.55) for _ in range(n)]


def dataset(spark, rows, min_support=1):
    pairs = [(t, i) for t, r in enumerate(rows) for i in [*r, *r[:1]]]  # a repeated pair must not count twice
    return encode(spark.createDataFrame(pairs + [(None, "a"), (1, None)], "tid long, item string"), min_support)


def supports(rows):
    return {frozenset(s): n for k in range(1, len(ITEMS) + 1) for s in combinations(ITEMS, k) if (n := sum(set(s) <= set(r) for r in rows))}


def rules(rows, query, minsup):
    sup = supports(rows)
    out = set()
    for s, n in sup.items():
        if n >= minsup:
            for k in range(1, len(s)):
                for b in combinations(sorted(s), k):
                    body, head = frozenset(b), s - frozenset(b)
                    if holds(query, body, head, n, sup[body]):
                        out.add(("|".join(sorted(body)), "|".join(sorted(head)), n, sup[body]))
    return out


def shown(df):
    rows = [tuple(r)[:4] for r in rulegen.shown(df).collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


@pytest.mark.parametrize("kernel", ["probe", "bitmap", "subset", "partitioned"])
def test_kernels_count_alike(spark, kernel):
    rows = database(1)
    ds = dataset(spark, rows)
    asked = [tuple(sorted(ds.code[i] for i in s)) for s in ("ab", "acd", "bf", "def", "a")]
    want = {s: sum(set(ds.named(s)) <= set(r) for r in rows) for s in asked}
    assert count_sets(ds, asked, kernel) == want


def test_miners_agree(spark):
    rows = database(2)
    ds = dataset(spark, rows)
    found = levelwise.frequent_sets(ds, 5)
    want = {s: n for s, n in supports(rows).items() if n >= 5}
    named = lambda d: {frozenset(ds.named(s)): n for s, n in d.items()}
    table = lambda df: {frozenset(r["items"]): r["support"] for r in df.collect()}
    assert named(found) == want
    assert levelwise.level_one_supports_closed(ds, found)
    assert named({s: n for p in baselines.divide_and_mine(ds, 5, 3) for s, n in p.items()}) == want
    assert named(baselines.sampling(ds, 5)) == want
    for df in (levelwise.frequent_sets_as_tables(ds, 5), baselines.vertical(ds, 5), baselines.fpgrowth(ds, 5)):
        assert table(levelwise.named_table(ds, df)) == want
    sets = sets_table(ds, found)
    assert shown(rulegen.all_splits(sets, Fraction(3, 5))) == shown(rulegen.levelwise(sets, Fraction(3, 5))) == rules(rows, parse_query("confidence >= 0.6"), 5)


def test_projected_database(spark):
    ds = catalogue.tiny(spark)
    conj = SetConj(frozenset("13"), frozenset("5"))
    rest = {tuple(sorted(ds.names[i] for i in r["items"])) for r in projection.project(ds, conj).collect()}
    assert rest == {("2", "6"), ("4", "8")}
    assert projection.sizes(ds, [conj]).first()["transactions"] == 2
    found = levelwise.mine_set_query(ds, [conj])[0]
    assert {"".join(i for i in ds.named(s) if i not in "13") for s in found} == {"", "2", "4", "6", "8", "26", "48"}


def test_worked_example(spark):
    assert catalogue.queries()["rules_example"](spark, "").count() == 11
    strict = query_rules(catalogue.tiny(spark), catalogue._TINY_QUERY, MiningOptions(strict_confidence=True))
    assert strict.count() == 7


@pytest.mark.parametrize("seed", [3, 4])
def test_strategies_agree_in_a_random_session(spark, seed):
    rows = database(seed)
    ds = dataset(spark, rows)
    queries = random_queries(list(ITEMS), 5, seed=seed)
    sessions = {(s, c): Session(ds, s, 4, coverage=c, keep=1) for s, c in (("integrated", "none"), ("postprocess", "none"), ("incremental", "none"), ("incremental", "full"), ("incremental", "top"))}
    for q in queries:
        want = rules(rows, q, 4)
        for key, session in sessions.items():
            assert shown(session.ask(q)) == want, key
    for key, session in sessions.items():
        assert session.ledger.total("regenerated") == 0, key
    again = sessions["incremental", "none"]
    again.ask(queries[0])
    assert again.ledger.total("query_scans", 6) == 0


def test_moving_thresholds(spark):
    rows = database(6)
    ds = dataset(spark, rows)
    for coverage in ("none", "full", "top"):
        session = Session(ds, "incremental", 1, coverage=coverage)
        for n in (9, 4, 12, 6):
            text = f"body('a') and not head('c') and support >= {n}"
            assert shown(session.ask(text)) == rules(rows, parse_query(text), n)


@pytest.mark.parametrize("text", ["body('a') and head('a')", "head('zz')", "not body('zz') and confidence >= 0.7", "true", "false", "support >= 8", "not support >= 8", "not confidence >= 0.6", "body('a') and body('b') and body('c') and head('d') and head('e') and head('f')"])
@pytest.mark.parametrize("normal", ["ddnf", "dnf", "set_ddnf"])
def test_edge_queries(spark, text, normal):
    rows = database(7)
    ds = dataset(spark, rows)
    q = parse_query(text)
    assert shown(query_rules(ds, q, MiningOptions(normal=normal))) == rules(rows, q, 1)


def test_empty_data(spark):
    ds = dataset(spark, [])
    assert query_rules(ds, parse_query("body('a')")).count() == 0
    assert levelwise.frequent_sets(ds, 1) == {}


def test_bounds_are_checked(spark):
    ds = dataset(spark, database(8), 3)
    with pytest.raises(ValueError):
        levelwise.frequent_sets(ds, 2)
    with pytest.raises(levelwise.TooManyCandidates):
        levelwise.frequent_sets(ds, 3, max_candidates=2)
    with pytest.raises(BelowThreshold):
        Session(ds, "postprocess", 6).options and Session(ds, "postprocess", 6)._answer_sets(parse_query("support >= 4"))
    assert advise(True, 50, 8) == "postprocess" and advise(False, 50, 8) == "incremental"


def test_constraints_shrink_the_search(spark):
    ds = dataset(spark, database(9))
    sizes = []
    for text in ("true", "body('a')", "body('a') and head('b')"):
        from rulelattice.operators.ledger import Ledger

        ledger = Ledger()
        levelwise.mine_set_query(ds, set_disjuncts(rule_disjuncts(parse_query(text))), 3, ledger=ledger)
        sizes.append(ledger.total("generated"))
    assert sizes[0] > sizes[1] > sizes[2]


def test_bitmap_plan_keeps_bitmaps_in_place(spark):
    from rulelattice.operators.counting import bitmap_counts, candidate_table

    ds = dataset(spark, database(10))
    plan = bitmap_counts(ds, candidate_table(ds, [(0, 1), (1, 2)]))._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert plan.count("Exchange hashpartitioning") == 1 and "Python" not in plan
