"""Where lineage is cut: the folder that all executors share."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def shared(spark: SparkSession) -> None:
    """Set the checkpoint folder that the session names; where it names none, a temporary one, on a single machine only."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isDefined():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not context.master.startswith("local"):
        raise ValueError("a cluster needs spark.checkpoint.dir, a folder that all executors share")
    context.setCheckpointDir(named or tempfile.mkdtemp(prefix="tilebalance-"))


def stored(df: DataFrame) -> DataFrame:
    """The rows as they are now, written to the shared folder."""
    shared(df.sparkSession)
    return df.checkpoint()
