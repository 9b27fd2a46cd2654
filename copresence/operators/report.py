"""What clusters are: medoids, distinguishing itemsets, sizes, peers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .profiles import both_ways


def medoids(dist: DataFrame, labelled: DataFrame) -> DataFrame:
    """k, cluster, medoid: the member with the least total distance to the others (rounded to 10 places, then name)."""
    j = both_ways(dist).join(labelled.select("k", F.col("grp").alias("a"), F.col("cluster").alias("ca")), "a").join(labelled.select("k", F.col("grp").alias("b"), F.col("cluster").alias("cb")), ["k", "b"]).filter("ca = cb")
    total = j.groupBy("k", F.col("a").alias("grp")).agg(F.sum("d").alias("t"))
    every = labelled.join(total, ["k", "grp"], "left").withColumn("t", F.round(F.coalesce("t", F.lit(0.0)), 10))
    first = F.row_number().over(W.partitionBy("k", "cluster").orderBy("t", "grp"))
    return every.withColumn("r", first).filter("r = 1").select("k", "cluster", F.col("grp").alias("medoid"))


def distinguishing(profile: DataFrame, labelled: DataFrame, top: int = 3) -> DataFrame:
    """k, cluster, feature, diff, rank: features whose mean in the cluster (zeros counted) is most over or under the
    overall mean; rank counts from 1 on either side."""
    n = labelled.groupBy("k", "cluster").agg(F.count(F.lit(1)).alias("n"))
    size = labelled.groupBy("k").agg(F.count(F.lit(1)).alias("g"))
    sums = labelled.join(profile, "grp").groupBy("k", "cluster", "feature").agg(F.sum("value").alias("s"))
    overall = sums.groupBy("k", "feature").agg(F.sum("s").alias("t"))
    every = overall.join(n, "k").join(size, "k").join(sums, ["k", "cluster", "feature"], "left")
    diff = F.round(F.coalesce("s", F.lit(0.0)) / F.col("n") - F.col("t") / F.col("g"), 9)
    e = every.withColumn("diff", diff)
    up = F.row_number().over(W.partitionBy("k", "cluster").orderBy(F.desc("diff"), "feature"))
    down = F.row_number().over(W.partitionBy("k", "cluster").orderBy("diff", "feature"))
    return e.withColumn("up", up).withColumn("down", down).filter((F.col("up") <= top) | (F.col("down") <= top)).select("k", "cluster", "feature", "diff", F.when(F.col("up") <= top, "over").otherwise("under").alias("side"), F.when(F.col("up") <= top, F.col("up")).otherwise(F.col("down")).alias("rank"))


def peers(dist: DataFrame, labelled: DataFrame, t: int = 5) -> DataFrame:
    """grp, peer, d, rank, same_cluster: the t nearest other groups. labelled: one k."""
    first = F.row_number().over(W.partitionBy("a").orderBy(F.round("d", 10), "b"))
    near = both_ways(dist).withColumn("rank", first).filter(F.col("rank") <= t)
    j = near.join(labelled.select(F.col("grp").alias("a"), F.col("cluster").alias("ca")), "a").join(labelled.select(F.col("grp").alias("b"), F.col("cluster").alias("cb")), "b")
    return j.select(F.col("a").alias("grp"), F.col("b").alias("peer"), "d", "rank", (F.col("ca") == F.col("cb")).alias("same_cluster"))


def cluster_table(dist: DataFrame, labelled: DataFrame, measure: DataFrame, value: str) -> DataFrame:
    """k, cluster, size, medoid and the median of a group measure(grp, value)."""
    size = labelled.groupBy("k", "cluster").agg(F.count(F.lit(1)).alias("size"))
    mid = labelled.join(measure, "grp").groupBy("k", "cluster").agg(F.percentile(value, F.lit(0.5)).alias(f"median_{value}"))
    return size.join(medoids(dist, labelled), ["k", "cluster"]).join(mid, ["k", "cluster"])
