"""Encoding of (tid, item) pairs: a dictionary of frequent items and transactions as sorted code arrays."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulelattice.runtime import cut

#: Most frequent items that a dictionary may hold; their number is at most occurrences / minimal support.
MOST_ITEMS = 500_000


class TooManyItems(ValueError):
    """The minimal support leaves more items than the dictionary's bound."""


@dataclass
class Dataset:
    """Encoded transactions. Codes rank items by falling support, ties by name."""

    spark: SparkSession
    tx: DataFrame  # nid long, items array<int>; transactions without frequent items stay, empty
    names: list[str]
    supports: list[int]
    size: int
    min_support: int
    scans: int = 0
    rows_read: int = 0
    occurrences_read: int = 0
    _bitmaps: DataFrame | None = field(default=None, repr=False)

    def __post_init__(self) -> None:
        self.code = {n: i for i, n in enumerate(self.names)}

    @property
    def occurrences(self) -> int:
        return sum(self.supports)

    def scanned(self, rows: int, occurrences: int) -> None:
        """Notes a pass over so many transactions and items in them."""
        self.scans += 1
        self.rows_read += rows
        self.occurrences_read += occurrences

    @property
    def bitmaps(self) -> DataFrame:
        """(block, iid, bm): one bitmap of 32 768 transactions for each item, dealt by block."""
        if self._bitmaps is None:
            nid = F.col("nid") + 1
            each = self.tx.select(F.bitmap_bucket_number(nid).alias("block"), F.bitmap_bit_position(nid).alias("at"), F.explode("items").alias("iid"))
            parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
            self.scanned(self.size, self.occurrences)
            made = each.groupBy("block", "iid").agg(F.bitmap_construct_agg("at").alias("bm"))
            # Without adaptive execution a checkpoint knows its partitioning by block, so that no later
            # grouping by block moves a bitmap.
            adaptive = self.spark.conf.get("spark.sql.adaptive.enabled")
            self.spark.conf.set("spark.sql.adaptive.enabled", "false")
            try:
                self._bitmaps = cut(made.repartition(parts, "block"))
            finally:
                self.spark.conf.set("spark.sql.adaptive.enabled", adaptive)
        return self._bitmaps

    def release(self) -> None:
        self._bitmaps = None

    def named(self, codes: tuple[int, ...]) -> list[str]:
        return sorted(self.names[i] for i in codes)


def item_supports(pairs: DataFrame) -> DataFrame:
    """(item, support) over distinct pairs."""
    return pairs.where("tid is not null and item is not null").select("tid", "item").distinct().groupBy("item").agg(F.count("*").alias("support"))


def encode(pairs: DataFrame, min_support: int = 1, distinct: bool = False) -> Dataset:
    """Two scans of the pairs: one for the dictionary, one for the transactions.

    ``distinct``: the pairs are known to be distinct and without nulls.
    """
    spark = pairs.sparkSession
    clean = pairs if distinct else pairs.where("tid is not null and item is not null").select("tid", "item").distinct()
    known = clean.groupBy("item").agg(F.count("*").alias("support")).where(F.col("support") >= min_support)
    rows = known.orderBy(F.desc("support"), "item").limit(MOST_ITEMS + 1).collect()
    if len(rows) > MOST_ITEMS:
        raise TooManyItems(f"over {MOST_ITEMS} items with support {min_support} or more")
    names, supports = [r["item"] for r in rows], [r["support"] for r in rows]
    codes = spark.createDataFrame([(n, i) for i, n in enumerate(names)], "item string, iid int")
    coded = clean.join(F.broadcast(codes), "item", "left")  # at most MOST_ITEMS rows
    tx = cut(coded.groupBy("tid").agg(F.sort_array(F.collect_list("iid")).alias("items")).select(F.monotonically_increasing_id().alias("nid"), "items"))
    return Dataset(spark, tx, names, supports, tx.count(), min_support)


def sets_table(ds: Dataset, sets: dict[tuple[int, ...], int]) -> DataFrame:
    """(items array<string>, k, support) of itemsets by code; names sorted."""
    import pandas as pd

    shape = "items array<string>, k int, support long"
    if not sets:
        return ds.spark.createDataFrame([], shape)
    rows = [(ds.named(s), len(s), n) for s, n in sets.items()]
    return ds.spark.createDataFrame(pd.DataFrame(rows, columns=["items", "k", "support"]), shape)


def shown(sets: DataFrame) -> DataFrame:
    """Itemsets in output form: names joined with ``|``."""
    return sets.select(F.array_join("items", "|").alias("itemset"), F.col("k").cast("int").alias("k"), F.col("support").cast("long").alias("support"))


def profile(pairs: DataFrame) -> DataFrame:
    """One row: transactions, items, mean and largest transaction."""
    per = pairs.where("tid is not null and item is not null").select("tid", "item").distinct()
    by_tid = per.groupBy("tid").agg(F.count("*").alias("n"))
    items = per.select("item").distinct().agg(F.count("*").alias("items"))
    sizes = by_tid.agg(F.count("*").alias("transactions"), F.sum("n").alias("occurrences"), F.max("n").alias("longest"))
    return sizes.crossJoin(items)  # one row each
