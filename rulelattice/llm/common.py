"""Pieces shared by the training-data operators."""

from __future__ import annotations

import math
import os
import tempfile
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: the white space that separates words in every operator of this subpackage.
SPACE = r"\x20\x09-\x0D"
#: Last bits of a hash by which ``sifted`` marks it: a table of a megabyte of bits at most.
SIEVE_BITS = 23


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once a row, however often ``body`` uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    """The words of a text in order; none for null."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), f"[{SPACE}]+"), lambda w: w != "")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Keeps the session's shared folder; only a local session without one, as in tests, gets a temporary one."""
    if spark.sparkContext.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(shared or tempfile.mkdtemp(prefix="checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """The same rows from the shared checkpoint folder, with their lineage cut."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_afresh(df: DataFrame) -> DataFrame:
    """``cut`` without the planner's guess of the size, for results that are put into the same joins again and again.

    A checkpoint keeps that guess, and a join's is the product of its sides'. So its digits would grow by a factor with
    each round, and planning a few rounds more would fill the driver's memory. A fresh table has a guess of fixed length.
    """
    held, spark = cut(df), df.sparkSession
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(held._jdf.queryExecution().toRdd(), held._jdf.schema(), False), spark)


def set_aside(docs: DataFrame) -> tuple[DataFrame, Callable[[str], str]]:
    """``docs`` under names that no operator uses for columns of its own, and the new name of an old one.

    Operators that hand all columns on work on these and give the old names back at the end.
    """
    old = [c.lower() for c in docs.columns]
    return docs.toDF(*[f"own{i}" for i in range(len(old))]), lambda name: f"own{old.index(name.lower())}"


def sifted(rows: DataFrame, hashed: Column, keys: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The rows whose hash may be among ``keys``, a table of one long column, and those whose hash surely is not.

    Only the keys are dealt anew: their last bits are marked in a table of bounded size that is sent to the
    rows. So an exact join that follows exchanges the rows that may have a partner, and no others.
    """
    mask = (1 << SIEVE_BITS) - 1
    word = lambda h: F.shiftright(h.bitwiseAND(F.lit(mask)), 6)
    bit = lambda h: F.call_function("shiftleft", F.lit(1).cast("long"), h.bitwiseAND(F.lit(min(63, mask))).cast("int"))
    key = F.col(keys.columns[0])
    marks = F.broadcast(cut(keys.groupBy(word(key).alias("_word")).agg(F.bit_or(bit(key)).alias("_bits"))))
    marked = rows.join(marks, word(hashed) == F.col("_word"), "left").withColumn("_bits", F.coalesce("_bits", F.lit(0).cast("long")).bitwiseAND(bit(hashed)))
    return marked.where("_bits <> 0").select(*rows.columns), marked.where("_bits = 0").select(*rows.columns)


def fresh_key(key: Column) -> Column:
    """A string key equal in value, but not in the planner's eyes, so that a join deals both sides anew.

    After an aggregate on the same key Spark would reuse its partitioning, and adaptive execution
    cannot split a hot key of the other side then.
    """
    return F.concat(key, F.lit(""))


def shared_folder(spark: SparkSession) -> str:
    """Where tables that executors share may be written."""
    ensure_checkpoint_dir(spark)
    return str(spark.sparkContext.getCheckpointDir())


def shards_for(rows: int, per_shard: int) -> int:
    return max(1, math.ceil(rows / per_shard))


def cores(spark: SparkSession) -> int:
    return max(spark.sparkContext.defaultParallelism, os.cpu_count() or 1)
