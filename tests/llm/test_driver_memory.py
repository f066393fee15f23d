"""What the driver holds while components are found, over many rounds."""

from rulelattice.llm.components import components


def test_size_guesses_do_not_grow_with_rounds(spark):
    # A path whose numbers are shuffled takes several rounds.
    n = 257
    got = components(spark.range(n - 1).selectExpr("id * 100 % 257 as a", "(id + 1) * 100 % 257 as b"))
    assert {(r["node"], r["root"]) for r in got.collect()} == {(x, 0) for x in range(n)}
    assert got._jdf.queryExecution().optimizedPlan().stats().sizeInBytes() < 1 << 200
