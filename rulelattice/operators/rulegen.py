"""Rules from itemsets: all splits, heads grown level by level, and splits under a query's conditions."""

from __future__ import annotations

from fractions import Fraction

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.operators.items import Dataset
from rulelattice.operators.projection import ProjectedCounts
from rulelattice.plans.normalform import RuleConj
from rulelattice.runtime import LOCAL_CANDIDATES, cut

#: Most items that a rule's sides may share out freely where every split is made at once.
MOST_FREE = 16


def bits(mask: Column, items: Column, value: int) -> Column:
    """Items whose place has the given bit in a mask."""
    return F.filter(items, lambda x, i: F.pmod(F.floor(mask / F.pow(F.lit(2.0), i)), F.lit(2)) == value)


def shown(rules: DataFrame) -> DataFrame:
    """Rules in output form: names joined with ``|``, supports and confidence."""
    return rules.select(
        F.array_join("body_items", "|").alias("body"), F.array_join("head_items", "|").alias("head"), F.col("support").cast("long").alias("support"), F.col("body_support").cast("long").alias("body_support"), (F.col("support") / F.col("body_support")).alias("confidence")
    )


def confident(share: Fraction, strict: bool = False) -> Column:
    """Support over body support reaches (or exceeds) a share; by whole numbers."""
    left, right = F.col("support") * share.denominator, F.col("body_support") * share.numerator
    return left > right if strict else left >= right


def all_splits(sets: DataFrame, minconf: Fraction, strict: bool = False) -> DataFrame:
    """Every split of every itemset into two nonempty sides; body supports come from the sets themselves."""
    long_ = sets.where(F.size("items") > 1).select("items", "support", F.explode(F.sequence(F.lit(1), (F.pow(F.lit(2.0), F.size("items")) - 2).cast("int"))).alias("mask"))
    sides = long_.select(bits(F.col("mask"), F.col("items"), 1).alias("body_items"), bits(F.col("mask"), F.col("items"), 0).alias("head_items"), "support")
    return sides.join(sets.select(F.col("items").alias("body_items"), F.col("support").alias("body_support")), "body_items").where(confident(minconf, strict))


def levelwise(sets: DataFrame, minconf: Fraction) -> DataFrame:
    """Heads of one item, then larger ones made of confident ones only: a head is confident only if its parts are."""
    bodies = sets.select(F.col("items").alias("body_items"), F.col("support").alias("body_support"))
    base = sets.where(F.size("items") > 1).select("items", "support")

    def tested(heads: DataFrame) -> DataFrame:
        sided = heads.withColumn("body_items", F.array_except("items", "head_items")).where(F.size("body_items") > 0)
        return sided.join(bodies, "body_items").where(confident(minconf)).persist()

    level = tested(base.select("items", "support", F.explode(F.transform("items", lambda i: F.array(i))).alias("head_items")))
    out, held = level, [level]
    while not level.isEmpty():
        n = F.size("head_items")
        half = level.select("items", "support", F.slice("head_items", 1, n - 1).alias("prefix"), F.element_at("head_items", -1).alias("last"))
        other = half.select(F.col("items").alias("items2"), F.col("prefix").alias("prefix2"), F.col("last").alias("last2"))
        grown = half.join(other, (F.col("items") == F.col("items2")) & (F.col("prefix") == F.col("prefix2")) & (F.col("last") < F.col("last2")))
        level = tested(grown.select("items", "support", F.concat("prefix", F.array("last", "last2")).alias("head_items")))
        held.append(level)
        out = out.unionByName(level)
    return out.select("body_items", "head_items", "support", "body_support")


def _disjunct_table(ds: Dataset, conjs: list[RuleConj]) -> DataFrame:
    rows = [(i, *[sorted(getattr(c, n)) for n in ("body_in", "body_out", "head_in", "head_out")], c.sup_lo, c.sup_hi, *[getattr(f, p, None) for f in (c.conf_lo, c.conf_hi) for p in ("numerator", "denominator")]) for i, c in enumerate(conjs)]
    return ds.spark.createDataFrame(rows, "r int, body_in array<string>, body_out array<string>, head_in array<string>, head_out array<string>, sup_lo long, sup_hi long, lo_n long, lo_d long, hi_n long, hi_d long")


def placed_sets(ds: Dataset, sets: DataFrame, conjs: list[RuleConj]) -> DataFrame:
    """(r, items, ..., in_body, in_head, free): what each rule disjunct places of an itemset that it accepts."""
    rules = F.broadcast(_disjunct_table(ds, conjs))  # one row a disjunct; normal forms are bounded
    both = sets.join(rules, (F.col("support") >= F.col("sup_lo")) & F.col("sup_hi").isNull() | (F.col("support") >= F.col("sup_lo")) & (F.col("support") < F.col("sup_hi")))
    required = (F.size(F.array_except("body_in", "items")) == 0) & (F.size(F.array_except("head_in", "items")) == 0)
    placed = both.where(required).select(
        "r", "items", "support", "lo_n", "lo_d", "hi_n", "hi_d",
        F.array_intersect("items", F.array_union("body_in", "head_out")).alias("in_body"), F.array_intersect("items", F.array_union("head_in", "body_out")).alias("in_head"),
    ).where(~F.arrays_overlap("in_body", "in_head"))
    return placed.withColumn("free", F.array_except("items", F.concat("in_body", "in_head")))


def split_candidates(placed: DataFrame, allow_empty: bool = False) -> DataFrame:
    """Rules without confidence: every way to share out the free items, of which there are ``MOST_FREE`` at most."""
    masks = F.sequence(F.lit(0), (F.pow(F.lit(2.0), F.size("free")) - 1).cast("int"))
    split = placed.select("*", F.explode(masks).alias("mask"))
    sided = split.select("r", "support", "lo_n", "lo_d", "hi_n", "hi_d", F.array_sort(F.concat("in_body", bits(F.col("mask"), F.col("free"), 1))).alias("body_items"), F.array_sort(F.concat("in_head", bits(F.col("mask"), F.col("free"), 0))).alias("head_items"))
    return sided if allow_empty else sided.where("size(body_items) > 0 and size(head_items) > 0")


def missing_supports(ds: Dataset, wanted: DataFrame, known: DataFrame, kernel: str = "auto", remember: dict | None = None, required: list[frozenset[str]] = ()) -> DataFrame:
    """(items, support) of ``wanted`` item arrays: those in ``known``, the others by one more scan.

    Sets that hold all items of one of ``required`` are counted on the transactions that hold those.
    """
    asked = wanted.select("items").distinct()
    absent = asked.join(known.select("items"), "items", "left_anti").limit(LOCAL_CANDIDATES + 1).collect()
    if len(absent) > LOCAL_CANDIDATES:
        raise ValueError(f"over {LOCAL_CANDIDATES} bodies to count; mine the query in parts")
    sets = [tuple(sorted(ds.code[i] for i in r["items"])) for r in absent]
    frames = list(dict.fromkeys(tuple(sorted(ds.code[i] for i in q)) for q in required if q and all(i in ds.code for i in q)))
    held = [(next((d for d, f in enumerate(frames) if len(f) < len(s) and set(f) <= set(s)), len(frames)), s) for s in sets]
    beside = [sorted({i for d2, s in held if d2 == d for i in s if i not in f}) for d, f in enumerate([*frames, ()])]
    counts_of = ProjectedCounts(ds, [(f if beside[d] else (), beside[d]) for d, f in enumerate([*frames, ()])])
    counted = counts_of.count([(d, tuple(i for i in s if i not in counts_of.frames[d][0])) for d, s in held], kernel)
    if remember is not None:
        remember.update(counted)
    if not sets:
        return known.select("items", "support")
    rows = pd.DataFrame({"items": [ds.named(s) for s in sets], "support": [counted[s] for s in sets]})
    return known.select("items", "support").unionByName(ds.spark.createDataFrame(rows, "items array<string>, support long"))


def _tested(offered: DataFrame, supports: DataFrame, strict: bool) -> DataFrame:
    """The offered rules that reach their disjunct's confidence, with their body's support."""
    joined = offered.join(supports.select(F.col("items").alias("body_items"), F.col("support").alias("body_support")), "body_items")
    left, low = F.col("support") * F.col("lo_d"), F.col("body_support") * F.col("lo_n")
    return joined.where(F.col("lo_n").isNull() | (left > low if strict else left >= low))


def levelwise_splits(ds: Dataset, placed: DataFrame, pool: DataFrame, kernel: str, allow_empty: bool, strict: bool, remember: dict | None, required: list[frozenset[str]]) -> DataFrame:
    """Confident rules with heads that grow from the items that must be in them.

    A head is confident only if its parts are, so items move from the body to the head one by one and a
    level offers only heads all of whose parts (beside the forced items) were confident.
    """
    body = F.array_sort(F.concat("in_body", F.array_except("free", "moved")))
    whole = placed.withColumn("moved", F.array().cast("array<string>"))
    level, kept, k = whole, [], 0
    while True:
        offered = level.withColumn("body_items", body)
        if not allow_empty:
            offered = offered.where("size(body_items) > 0")
        if offered.isEmpty():
            break
        supports = missing_supports(ds, offered.select(F.col("body_items").alias("items")), pool, kernel, remember, required)
        good = cut(_tested(offered, supports, strict))
        kept.append(good)
        n = F.size("moved")
        if k == 0:
            level = good.select(*whole.columns[:-1], F.explode("free").alias("_i")).withColumn("moved", F.array("_i")).drop("_i")
        else:
            half = good.select(*whole.columns[:-1], F.slice("moved", 1, n - 1).alias("_p"), F.element_at("moved", -1).alias("_l"))
            other = good.select(F.col("r").alias("_r"), F.col("items").alias("_items"), F.slice("moved", 1, n - 1).alias("_p2"), F.element_at("moved", -1).alias("_l2"))
            level = half.join(other, (F.col("r") == F.col("_r")) & (F.col("items") == F.col("_items")) & (F.col("_p") == F.col("_p2")) & (F.col("_l") < F.col("_l2"))).select(*whole.columns[:-1], F.concat("_p", F.array("_l", "_l2")).alias("moved"))
        k += 1
    if not kept:
        return _tested(whole.withColumn("body_items", body), pool, strict).withColumn("head_items", F.col("in_head")).limit(0)
    out = kept[0]
    for part in kept[1:]:
        out = out.unionByName(part)
    out = out.withColumn("head_items", F.array_sort(F.concat("in_head", "moved")))
    return out if allow_empty else out.where("size(head_items) > 0")


def rules_of(ds: Dataset, sets: DataFrame, conjs: list[RuleConj], known: DataFrame | None = None, kernel: str = "auto", allow_empty: bool = False, strict: bool = False, negated_confidence: str = "filter", remember: dict | None = None, heads: str = "auto") -> DataFrame:
    """Rules of the query's disjuncts from the itemsets that it accepts.

    ``known`` are further sets with supports. With ``negated_confidence="ignore"`` upper bounds of
    confidence are left out and rules found twice are dropped. ``heads``: ``splits`` makes every split at
    once and counts all bodies in one scan, ``levelwise`` grows heads and lets confidence prune them, with a
    scan a level; ``auto`` takes the latter where an itemset has more than ``MOST_FREE`` free items.
    """
    placed = placed_sets(ds, sets, conjs)
    pool = sets.select("items", "support") if known is None else known.select("items", "support")
    required = [c.body_in for c in conjs]
    free = (placed.agg(F.max(F.size("free"))).first()[0] or 0) if heads != "levelwise" else 0
    if heads == "splits" and free > MOST_FREE:
        raise ValueError(f"an itemset has {free} free items, over {MOST_FREE}; grow its heads level by level")
    if heads == "levelwise" or free > MOST_FREE:
        kept = levelwise_splits(ds, placed, pool, kernel, allow_empty, strict, remember, required)
    else:
        offered = split_candidates(placed, allow_empty)
        supports = missing_supports(ds, offered.select(F.col("body_items").alias("items")), pool, kernel, remember, required)
        kept = _tested(offered, supports, strict)
    if negated_confidence == "filter":
        kept = kept.where(F.col("hi_n").isNull() | (F.col("support") * F.col("hi_d") < F.col("body_support") * F.col("hi_n")))
    out = kept.select("body_items", "head_items", "support", "body_support")
    return out.dropDuplicates(["body_items", "head_items"]) if negated_confidence == "ignore" else out
