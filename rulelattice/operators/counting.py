"""Counting kernels: supports of listed itemsets in one scan.

``probe`` looks candidates up by their rarest item; ``bitmap`` intersects vertical bitmaps block by
block, without a shuffle of them; ``subset`` enumerates the pairs or triples of short transactions;
``partitioned`` is the probe by a shuffled join, for candidate lists that are too large to broadcast.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulelattice.operators.items import Dataset
from rulelattice.runtime import BROADCAST_BYTES

Itemset = tuple[int, ...]
#: Share of a block's transactions that an item must fill on average for bitmaps to pay.
DENSE = 1 / 64


def candidate_table(ds: Dataset, sets: list[Itemset]) -> DataFrame:
    """(cid, k, items, probe); codes ascend with rarity, so the last item is the rarest."""
    rows = pd.DataFrame({"cid": range(len(sets)), "k": [len(s) for s in sets], "items": [list(s) for s in sets], "probe": [s[-1] for s in sets]})
    return ds.spark.createDataFrame(rows, "cid long, k int, items array<int>, probe int")


def _probe(tx: DataFrame, candidates: DataFrame) -> DataFrame:
    offered = tx.where(F.size("items") > 0).select(F.col("items").alias("t"), F.explode("items").alias("probe"))
    found = offered.join(candidates, "probe").where(F.size(F.array_except("items", "t")) == 0)
    return found.groupBy("cid").agg(F.count("*").alias("support"))


def probe_counts(ds: Dataset, candidates: DataFrame, broadcast: bool = True) -> DataFrame:
    return _probe(ds.tx, F.broadcast(candidates) if broadcast else candidates.hint("merge"))


def bitmap_counts(ds: Dataset, candidates: DataFrame) -> DataFrame:
    """The bitmaps stay where their block is; only a sum per candidate and task is shuffled."""
    wanted = candidates.select("cid", "k", F.explode("items").alias("iid"))
    joined = ds.bitmaps.join(F.broadcast(wanted), "iid")
    met = joined.groupBy("block", "cid", "k").agg(F.bitmap_and_agg("bm").alias("bm"), F.count("*").alias("n")).where("n = k")
    return met.groupBy("cid").agg(F.sum(F.bitmap_count("bm")).alias("support")).where("support > 0")


def subset_counts(ds: Dataset, candidates: DataFrame, k: int) -> DataFrame:
    """For two or three items: enumerates each transaction's subsets of that size."""
    parts = ds.tx.select("items", F.posexplode("items").alias("p", "a"))
    for name in ("b", "c")[: k - 1]:
        rest = F.slice("items", F.col("p") + 2, F.greatest(F.size("items"), F.lit(1)))
        parts = parts.select(*[c for c in parts.columns if c != "p"], F.col("p").alias("q"), F.posexplode(rest).alias("d", name)).withColumn("p", F.col("q") + 1 + F.col("d")).drop("q", "d")
    made = parts.select(F.array(*"abc"[:k]).alias("items"))
    return made.join(F.broadcast(candidates.select("cid", "items")), "items").groupBy("cid").agg(F.count("*").alias("support"))


def pair_counts(ds: Dataset, need: int, allowed: list[int] | None = None) -> DataFrame:
    """(a, b, support) of all pairs that occur and reach ``need``, without a list of candidates."""
    tx = ds.tx if allowed is None else ds.tx.select(F.array_intersect("items", F.array(*map(F.lit, allowed)).cast("array<int>")).alias("items"))
    firsts = tx.select("items", F.posexplode("items").alias("p", "a"))
    pairs = firsts.select("a", F.explode(F.slice("items", F.col("p") + 2, F.greatest(F.size("items"), F.lit(1)))).alias("b"))
    return pairs.groupBy("a", "b").agg(F.count("*").alias("support")).where(F.col("support") >= need)


def chosen_kernel(ds: Dataset, sets: list[Itemset]) -> str:
    width = sum(32 + 12 * len(s) for s in sets)
    if width > BROADCAST_BYTES:
        return "partitioned"
    fill = ds.occurrences / max(1, len(ds.names) * ds.size)
    return "bitmap" if fill > DENSE else "probe"


def count_sets(ds: Dataset, sets: list[Itemset], kernel: str = "auto") -> dict[Itemset, int]:
    """Supports of all given itemsets; single items and the empty set need no scan."""
    known = {s: ds.size if not s else ds.supports[s[0]] for s in sets if len(s) < 2}
    asked = [s for s in dict.fromkeys(sets) if len(s) > 1]
    if not asked:
        return known
    table = candidate_table(ds, asked)
    kind = chosen_kernel(ds, asked) if kernel == "auto" else kernel
    if kind == "subset" and {len(s) for s in asked} - {2, 3}:
        kind = "probe"
    for _ in range(len({len(s) for s in asked}) if kind == "subset" else 1):
        ds.scanned(ds.size, ds.occurrences)
    if kind == "bitmap":
        counted = bitmap_counts(ds, table)
    elif kind == "subset":
        parts = [subset_counts(ds, table.where(f"k = {k}"), k) for k in sorted({len(s) for s in asked})]
        counted = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    else:
        counted = probe_counts(ds, table, broadcast=kind != "partitioned")
    got = counted.collect()  # a row for each candidate at most
    supports = dict.fromkeys(asked, 0)
    supports.update((asked[r["cid"]], int(r["support"])) for r in got)
    return known | supports
