"""Other miners of all frequent itemsets: tree-based, vertical depth-first, and by sampling."""

from __future__ import annotations

import pandas as pd
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulelattice.operators.candidates import Itemset, joined
from rulelattice.operators.counting import count_sets
from rulelattice.operators.items import Dataset
from rulelattice.operators.levelwise import frequent_sets, mine_set_query, named_table
from rulelattice.plans.normalform import SetConj


def fpgrowth(ds: Dataset, minsup: int) -> DataFrame:
    """The library's tree-based miner, by codes; its itemsets only."""
    kept = ds.tx.where(F.size("items") > 0).select("items")
    share = max((minsup - 0.5) / max(kept.count(), 1), 0.0)
    found = FPGrowth(itemsCol="items", minSupport=share).fit(kept).freqItemsets
    return found.select(F.sort_array("items").alias("items"), F.size("items").alias("k"), F.col("freq").alias("support")).where(F.col("support") >= minsup)


def vertical(ds: Dataset, minsup: int) -> DataFrame:
    """Depth-first search over bitmaps: a task extends all itemsets that begin with one item.

    The bitmaps of a prefix's partners are brought to its task, which is this family's demand on memory.
    """
    frequent = [i for i in range(len(ds.names)) if ds.supports[i] >= minsup]
    owner = ds.bitmaps.where(F.col("iid").isin(frequent)) if len(frequent) < 5000 else ds.bitmaps
    prefixes = ds.spark.createDataFrame([(i,) for i in frequent], "prefix int")
    dealt = owner.join(F.broadcast(prefixes), F.col("iid") >= F.col("prefix"))

    def extend(pdf: pd.DataFrame) -> pd.DataFrame:
        prefix = int(pdf["prefix"].iloc[0])
        maps: dict[int, dict[int, int]] = {}
        for block, iid, bm in zip(pdf["block"], pdf["iid"], pdf["bm"], strict=True):
            maps.setdefault(int(iid), {})[int(block)] = int.from_bytes(bm, "little")
        out: list[tuple[list[int], int, int]] = []

        def size(m: dict[int, int]) -> int:
            return sum(v.bit_count() for v in m.values())

        def grow(items: list[int], own: dict[int, int], partners: list[tuple[int, dict[int, int]]]) -> None:
            out.append((items, len(items), size(own)))
            met = []
            for i, m in partners:
                both = {b: v & m[b] for b, v in own.items() if b in m and v & m[b]}
                if size(both) >= minsup:
                    met.append((i, both))
            for at, (i, both) in enumerate(met):
                grow([*items, i], both, [(j, maps[j]) for j, _ in met[at + 1 :]])

        if prefix in maps:
            grow([prefix], maps[prefix], [(j, maps[j]) for j in sorted(maps) if j > prefix])
        return pd.DataFrame(out, columns=["items", "k", "support"])

    return dealt.groupBy("prefix").applyInPandas(extend, "items array<int>, k int, support long")


def negative_border(frequent: set[Itemset], items: list[int]) -> list[Itemset]:
    """Smallest itemsets that are not frequent."""
    border = [(i,) for i in items if (i,) not in frequent]
    by_size: dict[int, list[Itemset]] = {}
    for s in frequent:
        by_size.setdefault(len(s), []).append(s)
    return border + [c for level in by_size.values() for c in joined(level) if c not in frequent]


def sampling(ds: Dataset, minsup: int, fraction: float = 0.2, slack: float = 0.8, kernel: str = "auto") -> dict[Itemset, int]:
    """Mines a hashed sample at a lowered threshold, counts its sets and their border in one scan of all data,
    and goes on from the border where that proves it necessary."""
    parts = max(1, round(1 / fraction))
    sampled = ds.tx.where(F.pmod(F.xxhash64("nid"), F.lit(parts)) == 0)
    rows = sampled.select(F.explode("items").alias("i")).groupBy("i").count().collect()
    counts = [0] * len(ds.names)
    for r in rows:
        counts[r["i"]] = r["count"]
    n = sampled.count()
    small = Dataset(ds.spark, sampled, ds.names, counts, n, 1)
    low = max(1, int(minsup * n / max(ds.size, 1) * slack))
    guess = {s for s in frequent_sets(small, low, kernel="probe")}
    items = [i for i in range(len(ds.names)) if ds.supports[i] >= minsup]
    asked, known = list(guess) + negative_border(guess, items), {}
    while asked:
        known |= count_sets(ds, asked, kernel)
        good = {s for s, c in known.items() if c >= minsup}
        asked = [s for s in negative_border(good, items) if s not in known]
    return {s: c for s, c in known.items() if c >= minsup}


def named(ds: Dataset, coded: DataFrame) -> DataFrame:
    return named_table(ds, coded)


def divide_and_mine(ds: Dataset, minsup: int, parts: int, kernel: str = "auto") -> list[dict[Itemset, int]]:
    """The unconstrained answer in disjoint runs: an item present and all rarer ones before it absent.

    Items are taken by rising support and grouped into runs of about equal support.
    """
    order = sorted((i for i in range(len(ds.names)) if ds.supports[i] >= minsup), key=lambda i: (ds.supports[i], ds.names[i]))
    conjs = [SetConj(frozenset([ds.names[i]]), frozenset(ds.names[j] for j in order[:at]), minsup) for at, i in enumerate(order)]
    total, share, runs = sum(ds.supports[i] for i in order), 0, [[] for _ in range(parts)]
    for i, c in zip(order, conjs, strict=True):
        runs[min(parts - 1, share * parts // max(total, 1))].append(c)
        share += ds.supports[i]
    return [{s: n for p in mine_set_query(ds, run, minsup, kernel) for s, n in p.items()} for run in runs if run]


def topdown_sets(ds: Dataset, universe: list[str], max_support: int, floor: int = 0, max_items: int = 16, kernel: str = "auto") -> dict[Itemset, int]:
    """Itemsets over a small universe with support below a bound, from the full set downwards.

    A set is looked at only if all sets that are larger by one item stayed below the bound.
    """
    codes = sorted(ds.code[u] for u in universe if u in ds.code)
    if len(codes) > max_items:
        raise ValueError(f"a universe of {len(codes)} items is too large to search downwards")
    level, out = [tuple(codes)] if codes else [], {}
    while level:
        counts = count_sets(ds, level, kernel)
        below = {s for s in level if counts[s] < max_support}
        out |= {s: counts[s] for s in below if s and counts[s] >= floor}
        parts = {s[:i] + s[i + 1 :] for s in below for i in range(len(s))}
        level = [s for s in parts if s and all(tuple(sorted((*s, c))) in below for c in codes if c not in s)]
    return out


def topdown_rules(sets: dict[Itemset, int], max_conf_n: int, max_conf_d: int) -> list[tuple[Itemset, Itemset, int, int]]:
    """Rules below a confidence bound, from the largest heads downwards: a smaller head is looked at only
    where every head larger by one item stayed below. Sets must hold all parts of their sets."""
    out = []
    for s, n in sets.items():
        level = {s[:i] + s[i + 1 :] for i in range(len(s))} if len(s) > 1 else set()
        while level:
            below = {h for h in level if n * max_conf_d < max_conf_n * sets[tuple(i for i in s if i not in h)]}
            out += [(tuple(i for i in s if i not in h), h, n, sets[tuple(i for i in s if i not in h)]) for h in below]
            smaller = {h[:i] + h[i + 1 :] for h in below for i in range(len(h)) if len(h) > 1}
            level = {h for h in smaller if all(tuple(sorted((*h, i))) in below for i in s if i not in h and len(h) + 1 < len(s))}
    return out

