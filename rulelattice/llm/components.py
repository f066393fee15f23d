"""Connected components of a link table, by alternating large-star and small-star steps.

Every step is a pair of joins over the links; nothing is gathered in one place. Each round is cut
into the checkpoint folder, and the rounds (logarithmic in the links' number in practice) end when a
round leaves the links as they were.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import cut_afresh


def _renewed(node: Column) -> Column:
    """The same number as a new expression: keeps adaptive execution free to split a hot node's links."""
    return F.shiftleft(node, 0)


def _large_star(links: DataFrame) -> DataFrame:
    both = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")).select(_renewed(F.col("a")).alias("k"), "m")
    return both.where("b > a").join(least, F.col("a") == F.col("k")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(links: DataFrame) -> DataFrame:
    down = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m")).select(_renewed(F.col("a")).alias("k"), "m")
    moved = down.join(least, F.col("a") == F.col("k")).select(F.explode(F.array(F.struct(F.col("a").alias("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("x"))
    return moved.select("x.a", "x.b").where("a <> b").distinct()


def _print_of(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first())


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root) for every node that has a link to another; root is its component's smallest node.

    ``links`` has two long columns a and b. Links of a node to itself, repeated ones and ones with a
    null are ignored; without links the result is empty.
    """
    now = cut_afresh(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    seen = _print_of(now)
    for _ in range(most_rounds):
        if not seen[0]:
            break
        now = cut_afresh(_small_star(_large_star(now)))
        got = _print_of(now)
        if got == seen:
            break
        seen = got
    else:
        raise RuntimeError(f"links did not settle in {most_rounds} rounds")
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots)
