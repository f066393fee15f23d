"""Columns of the input that are named like an operator's own, and headers that differ in case only."""

import pytest
from pyspark.sql import functions as F

from rulelattice.llm import exact_dedup, langid, packing, quality_rules, secret_scan, sentence_spans, simhash, suffix_dedup, warc

CLASHING = ["_id", "_n", "_norm", "_sha", "_h", "_keep_n", "_keep_id", "_size", "_th", "_rid", "_times", "_ref_lang", "_ref_words", "_gone", "_r", "_lang", "_s", "fp", "root", "least", "kept", "size", "cluster", "bin_id", "n_spans", "n_removed", "own0", "p", "with.dot"]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet").where("doc_id < 60")


@pytest.fixture(scope="module")
def clashing(docs):
    return docs.select("*", *[F.lit(f"of {c}").alias(c) for c in CLASHING])


def rows(df, columns):
    return sorted(map(repr, df.select(*columns).collect()))


PASSING = {
    "keep_good": quality_rules.keep_good,
    "drop_copies": exact_dedup.drop_copies,
    "one_of_each": simhash.one_of_each,
    "mask": secret_scan.mask,
    "drop_repeats": sentence_spans.drop_repeats,
}


@pytest.mark.parametrize("name", sorted(PASSING))
def test_clashing_columns_pass_through(docs, clashing, name):
    plain, got = PASSING[name](docs), PASSING[name](clashing)
    assert rows(got, plain.columns) == rows(plain, plain.columns)
    handed_on = [c for c in CLASHING if c not in plain.columns]
    assert set(got.columns) == {*docs.columns, *CLASHING, *plain.columns}
    values = [F.col(f"`{c}`") == f"of {c}" for c in handed_on]
    assert got.where(~F.forall(F.array(*values), lambda x: x)).isEmpty()


REPORTING = {
    "remove_later_copies": lambda d: suffix_dedup.remove_later_copies(d, kept_text=False),
    "pack_documents": packing.pack_documents,
    "duplicate_classes": exact_dedup.duplicate_classes,
    "judge": quality_rules.judge,
    "scan": secret_scan.scan,
    "near_duplicates": simhash.near_duplicates,
    "predict": lambda d: langid.predict(d, langid.Model([], None, None, 1.0, 1.0)),
}


@pytest.mark.parametrize("name", sorted(REPORTING))
def test_clashing_columns_leave_reports_alone(docs, clashing, name):
    plain, got = REPORTING[name](docs), REPORTING[name](clashing)
    assert got.columns == plain.columns and rows(got, plain.columns) == rows(plain, plain.columns)


def test_header_names_that_differ_in_case_only(spark):
    records = [
        (1, "response", "http://a.org/x", 10, "e", None, {"ETag": "e", "etag": "f", "Server": "s"}, "d1"),
        (2, "revisit", "http://a.org/x", 20, "e", None, {"Date": "1", "DATE": "2", "Server": "t"}, None),
        (3, "revisit", "http://a.org/x", 30, "e", None, {}, None),
        (4, "revisit", "http://a.org/x", 40, "e", None, None, None),
    ]
    got = {r["record_id"]: r["headers"] for r in warc.resolve_revisits(spark.createDataFrame(records, warc.RECORD)).collect()}
    assert got == {2: {"etag": "f", "server": "s", "date": "1"}, 3: {"etag": "f", "server": "s"}, 4: {"etag": "f", "server": "s"}}
