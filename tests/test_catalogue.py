"""A choice of catalogue queries against their SQL at the smallest scale, and the driver's contract."""

import importlib.util

import duckdb
import pytest

import __spark_entry__ as entry
from rulelattice import catalogue

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHOSEN = ["item_support", "frequent_sets_brand", "flagship", "boolean_nested", "incremental_coverage", "stream_session_tx", "stream_absorb", "projected_db_rows", "topdown_sets", "frequent_sampling"]


@pytest.fixture(scope="module")
def con():
    made = duckdb.connect()
    for t in TABLES:
        made.sql(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    return made


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_its_sql(spark, con, name):
    got = catalogue.queries()[name](spark, DIR)
    want = con.sql(catalogue.oracle_sql()[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = lambda rs, cs: sorted(tuple(repr(r[cs.index(c)]) for c in columns) for r in rs)
    assert rows(got.collect(), got.columns) == rows(want.fetchall(), want.columns)


def test_entry_has_rows_and_names_are_complete(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_library_does_not_import_the_training_data_part():
    import subprocess
    import sys

    code = "import sys; import rulelattice.catalogue; assert not any(m.startswith('rulelattice.llm') for m in sys.modules)"
    assert subprocess.run([sys.executable, "-c", code]).returncode == 0
    assert importlib.util.find_spec("rulelattice.catalogue")


def test_event_stream_runs(spark, tmp_path):
    from rulelattice.streaming.streams import SupportStream, stream_transactions

    events = spark.read.parquet(f"{DIR}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    tx = stream_transactions(spark.readStream.schema(events.schema).parquet(str(tmp_path / "in")))
    wanted = spark.createDataFrame([(["click_1"],), (["view_2"],)], "items array<string>")
    stream = SupportStream(wanted, str(tmp_path / "out"))
    stream.start(tx.select("items"), str(tmp_path / "cp")).awaitTermination(120)
    got = {tuple(r["items"]): r["support"] for r in stream.supports().collect()}
    table = {tuple(r["items"]) for r in stream_transactions(events).select("items").collect()}
    assert got and all(any(set(k) <= set(t) for t in table) for k in got)


def test_readers(spark, tmp_path):
    from rulelattice.sources import readers

    (tmp_path / "b.txt").write_text("1 2 3\n2 3\n\n")
    assert readers.from_text(spark, str(tmp_path / "b.txt")).select("tid").distinct().count() == 2
    df = spark.createDataFrame([(1, "x", None), (2, None, "y")], "id long, a string, b string")
    assert {tuple(r) for r in readers.from_columns(df, "id", ["a", "b"]).collect()} == {(1, "a=x"), (2, "b=y")}
    assert readers.synthetic_baskets(spark, 50, items=40).select("tid").distinct().count() == 50
    readers.write_answers(spark.createDataFrame([(["a", "b"],)], "items array<string>"), str(tmp_path / "o"), "csv")
    assert spark.read.csv(str(tmp_path / "o")).first()[0] == "a|b"
