"""Cutting lineage in the folder that driver and executors share."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a local folder is set only where that is unset and all runs in one process, as in tests."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared folder and go on from there: no lineage, and nothing that dies with an executor."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def bounded(df: DataFrame, rows: int, what: str) -> DataFrame:
    """df to be broadcast, after a count that stops one row beyond the bound."""
    if df.limit(rows + 1).count() > rows:
        raise ValueError(f"{what}: over {rows} rows, too many to send to every task")
    return F.broadcast(df)


def running_total(df: DataFrame, order: str, value: str, name: str) -> DataFrame:
    """df with the sum of `value` over all rows that come before in `order` (its values must be distinct).

    Rows are dealt by ranges of `order`; each range is summed, ranges are prefixed (a row each), and rows are then
    prefixed within their range, so no task holds all of them."""
    parts = cut(df.repartitionByRange(F.col(order)).withColumn("__part", F.spark_partition_id()))
    upto = W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)
    starts = parts.groupBy("__part").agg(F.sum(value).alias("__sum")).select("__part", F.coalesce(F.sum("__sum").over(upto), F.lit(0)).alias("__start"))
    inside = W.partitionBy("__part").orderBy(order).rowsBetween(W.unboundedPreceding, -1)
    j = parts.join(F.broadcast(starts), "__part")
    return j.withColumn(name, F.col("__start") + F.coalesce(F.sum(value).over(inside), F.lit(0))).drop("__part", "__start")
