"""Session helpers: checkpoints, table reading, bounds."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession

#: Most itemsets that the driver holds as candidates of one scan; beyond it they stay tables.
LOCAL_CANDIDATES = 200_000
#: Most bytes of a side that may be broadcast.
BROADCAST_BYTES = 64 << 20


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; only a local session without one, as in tests, gets a temporary one."""
    if spark.sparkContext.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(shared or tempfile.mkdtemp(prefix="checkpoint-"))
    return str(spark.sparkContext.getCheckpointDir())


def cut(df: DataFrame) -> DataFrame:
    """The same rows from the checkpoint folder: a stable boundary for loops and row numbers."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)
