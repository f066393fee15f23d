"""Cost ledger: one row per measure, and what is derived from it."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SHAPE = "session string, query int, strategy string, disjunct int, k int, metric string, value double"


@dataclass
class Ledger:
    session: str = ""
    strategy: str = ""
    query: int = 0
    rows: list[tuple] = field(default_factory=list)

    def record(self, disjunct: int = -1, k: int = -1, **metrics: float) -> None:
        self.rows += [(self.session, self.query, self.strategy, disjunct, k, m, float(v)) for m, v in metrics.items()]

    def total(self, metric: str, query: int | None = None) -> float:
        return sum(r[6] for r in self.rows if r[5] == metric and (query is None or r[1] == query))

    def df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SHAPE)


def cumulative(ledger: DataFrame, metric: str) -> DataFrame:
    """Running total of a measure by strategy and query."""
    spent = ledger.where(F.col("metric") == metric).groupBy("session", "strategy", "query").agg(F.sum("value").alias("value"))
    # A strategy that spends nothing on a query still has its total there.
    queries, strategies = ledger.select("session", "query").distinct(), ledger.select("session", "strategy").distinct()
    each = queries.join(strategies, "session").join(spent, ["session", "strategy", "query"], "left").fillna(0.0, ["value"])
    w = Window.partitionBy("session", "strategy").orderBy("query").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return each.withColumn("total", F.sum("value").over(w))


def cutoff(ledger: DataFrame, metric: str, a: str, b: str) -> DataFrame:
    """First query after which strategy ``a`` has cost more than ``b``; null if it never has."""
    totals = cumulative(ledger, metric)
    left = totals.where(F.col("strategy") == a).select("session", "query", F.col("total").alias("a_total"))
    right = totals.where(F.col("strategy") == b).select("session", "query", F.col("total").alias("b_total"))
    met = left.join(right, ["session", "query"])
    return met.groupBy("session").agg(F.min(F.when(F.col("a_total") > F.col("b_total"), F.col("query"))).alias("cutoff"))


def saturation(ledger: DataFrame, all_frequent: int) -> DataFrame:
    """Share of all frequent itemsets that the store holds after each query."""
    return ledger.where("metric = 'stored_frequent'").select("session", "strategy", "query", (F.col("value") / all_frequent).alias("share"))


def proportionality(points: DataFrame, x: str, y: str) -> DataFrame:
    """Slope through the origin, and the usual regression as a check."""
    return points.agg((F.sum(F.col(x) * F.col(y)) / F.sum(F.col(x) * F.col(x))).alias("factor"), F.regr_slope(y, x).alias("slope"), F.regr_r2(y, x).alias("r2"))


def report(ledger: DataFrame) -> DataFrame:
    """Sums by strategy and measure with totals over both (grouping sets)."""
    return ledger.cube("strategy", "metric").agg(F.sum("value").alias("value"))


def pivoted(ledger: DataFrame, metric: str) -> DataFrame:
    """One row a query, one column a strategy: the shape of a session plot."""
    return ledger.where(F.col("metric") == metric).groupBy("query").pivot("strategy").agg(F.sum("value"))
