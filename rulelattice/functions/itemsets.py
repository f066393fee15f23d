"""Set algebra on sorted arrays of items, and measures of rules and of sets of itemsets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def is_subset(small: Column, large: Column) -> Column:
    return F.size(F.array_except(small, large)) == 0


def minus(a: Column, b: Column) -> Column:
    return F.array_sort(F.array_except(a, b))


def plus(a: Column, b: Column) -> Column:
    return F.array_sort(F.array_union(a, b))


def drop_one(items: Column) -> Column:
    """All subsets that lack one item."""
    return F.transform(items, lambda x: F.filter(items, lambda y: y != x))


def set_key(items: Column) -> Column:
    return F.array_join(items, "|")


def rule_measures(rules: DataFrame, sets: DataFrame, n: int) -> DataFrame:
    """Adds head support, lift, leverage, conviction, Jaccard, cosine and all-confidence."""
    heads = sets.select(F.col("items").alias("head_items"), F.col("support").alias("head_support"))
    both = rules.join(heads, "head_items")
    s, b, h = F.col("support"), F.col("body_support"), F.col("head_support")
    return both.select(
        "body_items", "head_items", "support", "body_support", "head_support", (s / b).alias("confidence"), (s * n / (b * h)).alias("lift"), ((s * n - b * h) / (F.lit(n) * n)).alias("leverage"),
        F.when(b > s, (b * (n - h)) / (F.lit(n) * (b - s))).alias("conviction"), (s / (b + h - s)).alias("jaccard"), (s / F.sqrt(b * h.cast("double"))).alias("cosine"), (s / F.greatest(b, h)).alias("all_confidence"),
    )


def _larger(sets: DataFrame) -> DataFrame:
    """Each set that lacks one item of a given set, with the larger one's support."""
    return sets.where(F.size("items") > 1).select(F.explode(drop_one(F.col("items"))).alias("items"), F.col("support").alias("larger"))


def closed_sets(sets: DataFrame) -> DataFrame:
    """Itemsets without a larger one of the same support."""
    same = _larger(sets).withColumnRenamed("larger", "support").distinct()
    return sets.join(same, ["items", "support"], "left_anti").select(*sets.columns)


def maximal_sets(sets: DataFrame) -> DataFrame:
    """Itemsets without a larger frequent one."""
    return sets.join(_larger(sets).select("items").distinct(), "items", "left_anti").select(*sets.columns)


def top_rules(rules: DataFrame, k: int, per: str | None = None) -> DataFrame:
    """The k rules of the highest confidence (then support, then text), overall or for each body or head."""
    keyed = rules.withColumn("_b", F.array_join("body_items", "|")).withColumn("_h", F.array_join("head_items", "|")).withColumn("_c", F.col("support") / F.col("body_support"))
    order = [F.desc("_c"), F.desc("support"), "_b", "_h"]
    if per is None:
        return keyed.orderBy(*order).limit(k).drop("_b", "_h", "_c")
    w = Window.partitionBy(f"{per}_items").orderBy(*order)
    return keyed.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= k).drop("_b", "_h", "_c", "_n")


def top_itemsets(sets: DataFrame, k: int) -> DataFrame:
    return sets.withColumn("_t", F.array_join("items", "|")).orderBy(F.desc("support"), "_t").limit(k).drop("_t")


def supporting_transactions(pairs: DataFrame, items: list[str]) -> DataFrame:
    """Transactions that hold all given items."""
    met = pairs.where(F.col("item").isin(items)).select("tid", "item").distinct().groupBy("tid").agg(F.count("*").alias("n"))
    return met.where(F.col("n") == len(set(items))).select("tid")


def confidence_spread(rules: DataFrame) -> DataFrame:
    """Rank measures of the rules' confidence by size of head."""
    w = Window.partitionBy(F.size("head_items")).orderBy((F.col("support") / F.col("body_support")))
    return rules.withColumn("percent_rank", F.percent_rank().over(w)).withColumn("cume_dist", F.cume_dist().over(w)).withColumn("quartile", F.ntile(4).over(w))


def same_answers(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
