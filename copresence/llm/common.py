"""Helpers that the corpus operators share: checkpoints in the shared folder, text keys, components."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from copresence.plans.shared import cut, shared_dir

__all__ = ["components", "cut", "hex_number", "shared_dir", "table", "whole"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def whole(text: str | Column) -> Column:
    """The text with null read as empty."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def hex_number(digest: Column, start: int, digits: int) -> Column:
    """Part of a hex digest as a long (at most 15 digits)."""
    return F.conv(F.substring(digest, start, digits), 16, 10).cast("long")


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of edges(a long, b long): one row (id, root) per node that has an edge, root the least id.

    Each round takes the least root among a node's neighbours and then jumps to that root's root, so chains halve.
    State is written to the shared folder each round; only one changed-row count comes to the driver.
    """
    once = cut(edges.select("a", "b").filter("a <> b").distinct())
    both = once.unionByName(once.select(F.col("b").alias("a"), F.col("a").alias("b")))
    state = cut(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m")).select("id", F.least("id", "m").alias("root")))
    for _ in range(max_rounds):
        near = both.join(state.select(F.col("id").alias("b"), "root"), "b").select(F.col("a").alias("id"), "root").unionByName(state)
        step = near.groupBy("id").agg(F.min("root").alias("root"), F.max("root").alias("most"))
        up = state.select(F.col("id").alias("root"), F.col("root").alias("up"))
        # settled: every node and its neighbours had one root already, and that root is its own root
        state = cut(step.join(up, "root", "left").select("id", F.coalesce("up", "root").alias("root"), ((F.col("most") != F.col("root")) | (F.coalesce("up", "root") != F.col("root"))).alias("moved")))
        moved = state.filter("moved").limit(1).count()
        state = state.select("id", "root")
        if not moved:
            return state
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
