"""Findings of round 3."""

import random
from datetime import datetime, timedelta

import duckdb
import pytest

from rulelattice import catalogue

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, props string"
START = datetime(2024, 3, 10)


def both(spark, path, rows, name="stream_session_tx"):
    """The rows of a query on given events, by Spark and by its SQL."""
    spark.createDataFrame(rows, EVENTS).write.parquet(f"{path}/events.parquet")
    got = catalogue.queries()[name](spark, str(path))
    con = duckdb.connect()
    con.sql(f"create view events as select * from '{path}/events.parquet/*.parquet'")
    want = con.sql(catalogue.oracle_sql()[name])
    order = lambda rs: sorted(rs, key=repr)
    return order(map(tuple, got.select(*want.columns).collect())), order(want.fetchall())


@pytest.mark.parametrize("zone", ["UTC", "America/New_York"])
def test_sessions_end_at_the_gaps_of_their_sql(spark, tmp_path, zone):
    # Gaps around four hours, of which some cross the hour that the zone skips; parts of seconds around the half.
    rng, rows = random.Random(5), []
    for user in range(20):
        at = START - timedelta(days=3) + timedelta(hours=user)
        for _ in range(150):
            at = (at + timedelta(seconds=rng.choice([900, 10_799, 14_399, 14_400, 14_401]))).replace(microsecond=rng.choice([0, 1, 499_999, 500_000, 500_001, 999_999]))
            rows.append((len(rows), at, user, rng.choice(["click", "view"]), f'{{"k": {rng.randrange(100)}}}'))
    old = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", zone)
    try:
        got, want = both(spark, tmp_path, rows)
    finally:
        spark.conf.set("spark.sql.session.timeZone", old)
    assert got == want


def test_gaps_are_of_seconds_rounded_half_to_even(spark, tmp_path):
    def pair(user, first, second):
        return [(10 * user, START + timedelta(microseconds=first), user, "click", '{"k": 1}'), (10 * user + 1, START + timedelta(hours=4, microseconds=second), user, "view", '{"k": 2}')]

    # 0 to 0.6 is rounded up to one second too many, 0 to 0.5 is not, 1 to 1.5 is; 0.6 to 1.4 is none.
    rows = [*pair(1, 0, 600_000), *pair(2, 0, 500_000), *pair(3, 1_000_000, 1_500_000), *pair(4, 600_000, 1_400_000)]
    got, want = both(spark, tmp_path, rows)
    sessions = {u: sum(r[0] == u for r in got) for u in (1, 2, 3, 4)}
    assert got == want and sessions == {1: 2, 2: 1, 3: 2, 4: 1}


@pytest.mark.parametrize("name", ["stream_session_tx", "stream_day_tx"])
def test_events_with_missing_or_odd_values(spark, tmp_path, name):
    props = ['{"k": 87}', '{"k": -5}', '{"k": -15}', '{"k": 19.5}', '{"k": "30"}', '{"k": 1e2}', '{"k": null}', "{}", None]
    rows = [(n, START + timedelta(hours=n), u, kind, p) for u in (1, None) for n, (kind, p) in enumerate((k, p) for k in ("click", None) for p in props)]
    rows += [(99, START, 2, "click", "{}")]
    got, want = both(spark, tmp_path, rows, name)
    assert got == want


def test_events_without_time_are_last(spark, tmp_path):
    rows = [(1, None, 1, "click", '{"k": 1}'), (None, START, 1, "view", '{"k": 2}'), (2, START, 1, "error", '{"k": 3}'), (3, None, 1, "view", '{"k": 4}'), (None, None, 1, "view", '{"k": 55}')]
    got, want = both(spark, tmp_path, rows)
    assert got == want and [r[1] for r in got] == [1, 2, 3, 4]
