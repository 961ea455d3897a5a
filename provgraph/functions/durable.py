"""Cutting lineage in a place that every executor can read."""
from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> str:
    """The session's shared checkpoint folder.

    A cluster names it in ``spark.checkpoint.dir``.  Only in local mode, where neither that setting
    nor a folder set on the context exists, a temporary one is made.
    """
    jsc = spark.sparkContext._jsc.sc()
    current = jsc.getCheckpointDir()
    if current.isDefined():
        return current.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-", dir=os.environ.get("TMPDIR")))
    return jsc.getCheckpointDir().get()


#: Files of an intermediate table for each core of the cluster, at most: many tiny files cost more than they hold.
FILES_A_CORE = 4


def _packed_up(df: DataFrame) -> DataFrame:
    """``df`` in no more partitions than FILES_A_CORE for each core; nothing is shuffled for that."""
    return df.coalesce(max(8, FILES_A_CORE * df.sparkSession.sparkContext.defaultParallelism))


def cut(df: DataFrame) -> DataFrame:
    """``df`` computed once and kept in the shared checkpoint folder."""
    checkpoint_folder(df.sparkSession)
    return _packed_up(df).checkpoint(eager=True)


def cut_table(df: DataFrame) -> DataFrame:
    """``df`` as Parquet in the shared checkpoint folder: compressed, read by column, without a partitioning."""
    path = f"{checkpoint_folder(df.sparkSession)}/table-{uuid.uuid4().hex}"
    _packed_up(df).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
