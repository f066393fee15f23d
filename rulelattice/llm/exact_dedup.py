"""Exact deduplication by 128-bit content hash, with a comparison of bytes.

Two texts are equal when nothing differs after white space is deleted. A group is found by the
MD5 of its normalised text; the distinct normalised texts behind every hash are counted, and where
a hash stands for more than one of them (a collision) the rows are told apart by a second hash.
Of equal texts the row with the most code points stays, then the smallest id.

Edge cases: a null text counts as empty, and all empty texts form one group; a null id ranks before
all others; rows repeated with the same id and text keep one of them; an empty table gives an empty
result; other columns are not read by :func:`duplicate_classes` and pass through :func:`drop_copies`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import SPACE, cut, fresh_key, set_aside


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), f"[{SPACE}]+", "")


def _hashed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    norm = docs.select(
        F.col(id_col).alias("_id"), F.length(F.coalesce(text_col, F.lit(""))).alias("_n"), normalised(F.col(text_col)).alias("_norm")
    )
    return norm.select("_id", "_n", F.md5("_norm").alias("_h"), F.sha2("_norm", 256).alias("_sha"))


def colliding_hashes(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Hashes that stand for several different normalised texts: the comparison of bytes.

    Grouping on the text itself compares bytes. Equal texts of one task leave it as a single row,
    so a hot group is not gathered.
    """
    texts = docs.select(normalised(F.col(text_col)).alias("_norm")).select(F.md5("_norm").alias("_h"), "_norm")
    return texts.distinct().groupBy("_h").agg(F.count("*").alias("_texts")).where("_texts > 1").select("_h")


def _classes(rows: DataFrame, collided: DataFrame) -> DataFrame:
    """Rows (id, n, class, sha), each distinct one once with its multiplicity.

    Only where some hash does collide are rows joined with those hashes.
    """
    name = F.col("_h")
    collided = cut(collided)
    if not collided.isEmpty():
        rows = rows.join(collided.select("_h", F.lit(True).alias("_hit")), "_h", "left")
        name = F.when(F.col("_hit"), F.concat("_h", F.lit("+"), "_sha")).otherwise(F.col("_h"))
    keyed = rows.select("_id", "_n", "_sha", name.alias("_class"))
    return keyed.groupBy("_id", "_n", "_sha", "_class").agg(F.count("*").alias("_times"))


def duplicate_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: its id, ``keep_id``, ``group_size``, ``kept`` and ``text_sha256``."""
    rows = _classes(_hashed(docs, id_col, text_col), colliding_hashes(docs, text_col))
    best = F.min(F.struct((-F.col("_n")).alias("less"), F.col("_id").alias("id")))
    groups = rows.groupBy("_class").agg(best.alias("_best"), F.sum("_times").alias("group_size"))
    groups = groups.select(fresh_key(F.col("_class")).alias("_class"), (-F.col("_best.less")).alias("_keep_n"), F.col("_best.id").alias("keep_id"), "group_size")
    joined = rows.join(groups, "_class")
    each = joined.select("*", F.explode(F.sequence(F.lit(1), F.col("_times"))).alias("_turn"))
    return each.select(
        F.col("_id").alias(id_col),
        "keep_id",
        "group_size",
        (F.col("_id").eqNullSafe(F.col("keep_id")) & (F.col("_n") == F.col("_keep_n")) & (F.col("_turn") == 1)).alias("kept"),
        F.col("_sha").alias("text_sha256"),
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents that stay, with all their columns.

    Groups without copies are left out of the lookup, which keeps its side small; adaptive execution
    broadcasts it below its threshold and splits hot groups beyond it.
    """
    own, name = set_aside(docs)
    id_col, text_col = name(id_col), name(text_col)
    rows = _classes(_hashed(own, id_col, text_col), colliding_hashes(own, text_col))
    best = F.min(F.struct((-F.col("_n")).alias("less"), F.col("_id").alias("id"), F.col("_sha").alias("sha")))
    groups = rows.groupBy("_class").agg(best.alias("_best"), F.sum("_times").alias("_size")).where("_size > 1")
    # Equal normalised texts have one SHA-256, which together with MD5 names the class of a row.
    groups = groups.select(F.col("_best.sha").alias("_sha"), (-F.col("_best.less")).alias("_keep_n"), F.col("_best.id").alias("_keep_id"))
    marked = own.withColumn("_norm", normalised(F.col(text_col))).withColumn("_sha", F.sha2("_norm", 256)).drop("_norm")
    joined = marked.join(groups, "_sha", "left").withColumn("_n", F.length(F.coalesce(text_col, F.lit(""))))
    winner = F.col(id_col).eqNullSafe(F.col("_keep_id")) & (F.col("_n") == F.col("_keep_n"))
    alone = joined.where(F.col("_keep_n").isNull()).select(*own.columns)
    best_rows = joined.where(F.col("_keep_n").isNotNull() & winner)
    one_each = best_rows.dropDuplicates(["_sha"]).select(*own.columns)
    return alone.unionByName(one_each).toDF(*docs.columns)
