"""Groups as sparse profiles of itemset support, their variants, and distances between them.

PROFILE(grp, feature, value) holds what is frequent in a group; a feature that isn't frequent there is 0 and has no row
(its true support is unknown below the minimum, it is not absence). A group without any feature keeps one row of value 0
(`keep_groups`): it is at distance 1 from every unit profile and is clustered like any other."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copresence.model import Classes


def profiles(itemsets: DataFrame) -> DataFrame:
    return itemsets.select("grp", F.col("itemset").alias("feature"), F.col("rel").alias("value"))


def with_absent_groups(profile: DataFrame, groups: DataFrame) -> DataFrame:
    """groups(grp) that have no feature at all, flagged: rows of zeros."""
    return groups.select("grp").distinct().join(profile.select("grp").distinct().withColumn("has", F.lit(True)), "grp", "left").select("grp", F.col("has").isNull().alias("degenerate"))


def keep_groups(profile: DataFrame, groups: DataFrame) -> DataFrame:
    """profile with a row of value 0 for each of groups(grp) that has no feature left, so that no later step loses it."""
    some = profile.agg(F.coalesce(F.min("feature"), F.lit(0)).cast("long").alias("feature"))  # one row
    lost = groups.select("grp").distinct().join(profile.select("grp").distinct(), "grp", "left_anti")
    return profile.unionByName(lost.crossJoin(F.broadcast(some)).withColumn("value", F.lit(0.0)).select("grp", "feature", "value"))


def densify(profile: DataFrame, groups: DataFrame | None = None) -> DataFrame:
    """Every group by every feature, zeros filled in: groups x features rows, for small results only."""
    groups = (groups if groups is not None else profile).select("grp").distinct()
    every = groups.crossJoin(profile.select("feature").distinct())
    return every.join(profile, ["grp", "feature"], "left").select("grp", "feature", F.coalesce("value", F.lit(0.0)).alias("value"))


def matrix_extract(profile: DataFrame, features: list[int]) -> DataFrame:
    """A wide view of chosen features."""
    return profile.groupBy("grp").pivot("feature", features).agg(F.first("value")).fillna(0.0)


def as_maps(profile: DataFrame) -> DataFrame:
    """grp, map feature -> value."""
    return profile.groupBy("grp").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("feature", "value")))).alias("profile"))


def l2(profile: DataFrame) -> DataFrame:
    """Rows scaled to length 1; a row of zeros stays as it is."""
    norm = profile.groupBy("grp").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
    return profile.join(norm, "grp").select("grp", "feature", F.when(F.col("norm") > 0, F.col("value") / F.col("norm")).otherwise(F.lit(0.0)).alias("value"))


def stats(profile: DataFrame) -> DataFrame:
    """Groups, features, nonzero values."""
    return profile.filter("value <> 0").agg(F.count_distinct("grp").alias("groups"), F.count_distinct("feature").alias("features"), F.count(F.lit(1)).alias("nonzero"))


# ---- variants


def rounded(itemsets: DataFrame) -> DataFrame:
    """Whole percent points, halves up, by whole numbers."""
    return itemsets.select("grp", F.col("itemset").alias("feature"), F.expr("CAST((200 * sup + n) DIV (2 * n) AS DOUBLE)").alias("value"))


def binary(itemsets: DataFrame) -> DataFrame:
    return itemsets.select("grp", F.col("itemset").alias("feature"), F.lit(1.0).alias("value"))


def absolute(itemsets: DataFrame) -> DataFrame:
    return itemsets.select("grp", F.col("itemset").alias("feature"), F.col("sup").cast("double").alias("value"))


def without_class(profile: DataFrame, bit: int) -> DataFrame:
    """Features that don't hold the class; no mining anew."""
    return profile.filter(F.col("feature").bitwiseAND(F.lit(1 << bit)) == 0)


def only_artificial(profile: DataFrame, classes: Classes) -> DataFrame:
    return profile.filter(F.col("feature").bitwiseAND(F.lit(classes.other)) == 0)


# ---- distances


def pairwise(profile: DataFrame, metric: str = "euclidean") -> DataFrame:
    """a, b (a < b), d over all pairs of groups, from products of features that two groups share.

    G * G / 2 rows by nature; for tens of thousands of groups take `peers`, which keeps the nearest only."""
    groups = profile.groupBy("grp").agg(F.sum(F.col("value") * F.col("value")).alias("sq"))
    x, y = profile.select(F.col("grp").alias("a"), "feature", F.col("value").alias("va")), profile.select(F.col("grp").alias("b"), "feature", F.col("value").alias("vb"))
    dots = x.join(y, "feature").filter("a < b").groupBy("a", "b").agg(F.sum(F.col("va") * F.col("vb")).alias("dot"))
    pairs = groups.select(F.col("grp").alias("a"), F.col("sq").alias("sa")).join(groups.select(F.col("grp").alias("b"), F.col("sq").alias("sb")), F.col("a") < F.col("b"))
    j = pairs.join(dots, ["a", "b"], "left").withColumn("dot", F.coalesce("dot", F.lit(0.0)))
    if metric == "euclidean":
        d = F.sqrt(F.greatest(F.lit(0.0), F.col("sa") + F.col("sb") - 2 * F.col("dot")))
    elif metric == "cosine":
        d = F.greatest(F.lit(0.0), 1 - F.when((F.col("sa") > 0) & (F.col("sb") > 0), F.col("dot") / F.sqrt(F.col("sa") * F.col("sb"))).otherwise(F.lit(0.0)))
    else:
        raise ValueError(f"unknown metric {metric}")
    return j.select("a", "b", d.alias("d"))


def both_ways(dist: DataFrame) -> DataFrame:
    return dist.unionByName(dist.select(F.col("b").alias("a"), F.col("a").alias("b"), "d"))


# ---- the baseline family: what an area is made of, without co-presence


def composition(units: DataFrame) -> DataFrame:
    """Share of each class among a group's units, as a profile (feature = class bit)."""
    n = units.groupBy("grp").agg(F.count(F.lit(1)).alias("n"))
    c = units.groupBy("grp", "bit").agg(F.count(F.lit(1)).alias("c"))
    return c.join(n, "grp").select("grp", F.col("bit").cast("long").alias("feature"), (F.col("c") / F.col("n")).alias("value"))


def mix_entropy(composition_profile: DataFrame) -> DataFrame:
    """Land-use mix: entropy of the shares over the log of the number of classes present (0 for one class)."""
    p = composition_profile.filter("value > 0")
    return p.groupBy("grp").agg(F.sum(-F.col("value") * F.log("value")).alias("h"), F.count(F.lit(1)).alias("m")).select("grp", F.when(F.col("m") > 1, F.col("h") / F.log(F.col("m"))).otherwise(F.lit(0.0)).alias("mix"))
