"""Transactions from tables, arrays, attribute columns, text, CSV and JSON; sinks for answers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def from_pairs(df: DataFrame, tid: str, item: str) -> DataFrame:
    """(tid, item) without nulls."""
    return df.select(F.col(tid).alias("tid"), F.col(item).cast("string").alias("item")).where("tid is not null and item is not null")


def from_arrays(df: DataFrame, tid: str, items: str) -> DataFrame:
    return from_pairs(df.select(F.col(tid).alias("_t"), F.explode(F.array_distinct(F.col(items))).alias("_i")), "_t", "_i")


def from_columns(df: DataFrame, tid: str, columns: list[str]) -> DataFrame:
    """``column=value`` items; a null attribute gives none."""
    cells: list[Column] = [F.when(F.col(c).isNotNull(), F.concat(F.lit(f"{c}="), F.col(c).cast("string"))) for c in columns]
    return from_pairs(df.select(F.col(tid).alias("_t"), F.explode(F.array_compact(F.array(*cells))).alias("_i")), "_t", "_i")


def from_text(spark: SparkSession, path: str, separator: str = " ") -> DataFrame:
    """One transaction a line; the tid is a hash of file and position within the task's split."""
    lines = spark.read.text(path).select(F.xxhash64(F.input_file_name(), F.monotonically_increasing_id()).alias("tid"), F.split("value", separator).alias("items"))
    return from_arrays(lines, "tid", "items").where("item <> ''")


def from_csv(spark: SparkSession, path: str, schema: str, tid: str, item: str) -> DataFrame:
    return from_pairs(spark.read.schema(schema).csv(path, header=True), tid, item)


def from_json(spark: SparkSession, path: str, schema: str, tid: str, items: str) -> DataFrame:
    return from_arrays(spark.read.schema(schema).json(path), tid, items)


def write_answers(df: DataFrame, path: str, kind: str = "parquet") -> None:
    """Parquet, JSON or CSV; arrays are joined to strings for CSV."""
    if kind == "csv":
        df = df.select(*[F.array_join(c, "|").alias(c) if t.startswith("array") else F.col(c) for c, t in df.dtypes])
    df.write.mode("overwrite").format(kind).save(path)


def synthetic_baskets(spark: SparkSession, n: int, items: int = 1000, length: int = 40, patterns: int = 200, pattern_length: int = 10, seed: int = 1) -> DataFrame:
    """(tid, item): each transaction takes whole patterns of items, chosen by seeded hashes, and some noise."""
    chosen = max(1, length // pattern_length)
    pick = lambda *c: F.pmod(F.xxhash64(F.lit(seed), *c), F.lit(patterns))
    base = spark.range(n).select(F.col("id").alias("tid"), F.explode(F.sequence(F.lit(0), F.lit(chosen - 1))).alias("p"))
    # Squaring the uniform number favours low pattern numbers, so some patterns are frequent.
    pattern = F.floor(F.pow(pick("tid", "p") / F.lit(float(patterns)), 2) * patterns)
    within = base.withColumn("pattern", pattern).select("tid", "pattern", F.explode(F.sequence(F.lit(0), F.lit(pattern_length - 1))).alias("i"))
    kept = within.where(F.pmod(F.xxhash64(F.lit(seed + 1), "tid", "pattern", "i"), F.lit(10)) < 8)
    item = F.pmod(F.xxhash64(F.lit(seed + 2), "pattern", "i"), F.lit(items))
    return kept.select("tid", F.concat(F.lit("item"), item.cast("string")).alias("item"))
