"""What the clustering depends on: minimum support, representation, geometry. Labels are compared by ARI and NMI,
distances by rank correlation, always against the primary solution at the same number of clusters."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copresence.model import Classes, Threshold
from copresence.plans.shared import cut

from . import clustering, mining, profiles
from .agreement import ari, distance_spearman, nmi

THRESHOLDS = ["5%", "7.5%", "10%", "12.5%", "15%"]
PRIMARY = "10%"


def _pca(x: np.ndarray, share: float) -> tuple[np.ndarray, np.ndarray]:
    """Scores on the least number of components that keep `share` of the variance, from the groups' Gram matrix; and the
    share that the first 1, 2, ... of these components reach."""
    c = x - x.mean(0)
    value, vector = np.linalg.eigh(c @ c.T)
    value, vector = np.maximum(value[::-1], 0), vector[:, ::-1]
    if value.sum() <= 0:
        return np.zeros((len(x), 1)), np.ones(1)
    reached = np.cumsum(value) / value.sum()
    m = int(np.searchsorted(reached, share - 1e-12) + 1)
    return vector[:, :m] * np.sqrt(value[:m]), reached[:m]


def pca(profile: DataFrame, share: float) -> DataFrame:
    """PROFILE of principal component scores (feature = component number). Groups gathered as for a tree."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp, _, x = clustering.matrix(pdf)
        s = _pca(x, share)[0]
        return pd.DataFrame({"grp": np.repeat(grp, s.shape[1]), "feature": np.tile(np.arange(s.shape[1]), len(grp)), "value": s.ravel()})

    return clustering._gathered(profile, run, "grp string, feature long, value double")


def explained_variance(profile: DataFrame, shares: tuple[float, ...] = (0.9, 0.95)) -> DataFrame:
    """share asked for, components kept, share of the variance that they reach."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = clustering.matrix(pdf)[2]
        got = [_pca(x, s)[1] for s in shares]
        return pd.DataFrame({"share": list(shares), "components": [len(g) for g in got], "reached": [float(g[-1]) for g in got]})

    return clustering._gathered(profile, run, "share double, components long, reached double")


def variant_profile(name: str, itemsets: DataFrame, classes: Classes, road_bit: int, patterns: DataFrame, threshold: Threshold | None = None) -> tuple[DataFrame, str, str]:
    """The profile that a variant clusters, its linkage and its distance. Every group of the patterns is in it."""
    base = profiles.profiles(itemsets)
    groups = patterns.select("grp").distinct()
    whole = lambda p: profiles.keep_groups(p, groups)
    unit = lambda p: profiles.l2(whole(p))
    if name == "primary":
        return unit(base), "ward", "euclidean"
    if name == "rounded":
        return unit(profiles.rounded(itemsets)), "ward", "euclidean"
    if name == "binary":
        return unit(profiles.binary(itemsets)), "ward", "euclidean"
    if name == "absolute":
        return unit(profiles.absolute(itemsets)), "ward", "euclidean"
    if name == "unnormalised":
        return whole(base), "ward", "euclidean"
    if name == "cosine_average":
        return whole(base), "average", "cosine"
    if name in ("pca90", "pca95"):
        return pca(unit(base), int(name[3:]) / 100), "ward", "euclidean"
    if name == "no_road":
        return unit(profiles.without_class(base, road_bit)), "ward", "euclidean"
    if name == "artificial_only":
        return unit(profiles.only_artificial(base, classes)), "ward", "euclidean"
    if name == "unique_pattern":
        mined = mining.mine(mining.unique_votes(patterns), threshold or Threshold.relative(PRIMARY))
        return unit(profiles.profiles(mined)), "ward", "euclidean"
    raise ValueError(f"unknown variant {name}")


VARIANTS = ("rounded", "binary", "absolute", "unnormalised", "cosine_average", "pca90", "pca95", "no_road", "artificial_only", "unique_pattern")


def compare(profile: DataFrame, method: str, metric: str, primary_labels: DataFrame, primary_dist: DataFrame, k: int) -> DataFrame:
    """features, ari, nmi, spearman of one solution against the primary one."""
    profile = cut(profile)
    own = cut(clustering.labels(profile, [k], method).select("grp", F.col("cluster").alias("u")))
    base = primary_labels.select("grp", F.col("cluster").alias("v"))
    features = profile.filter("value <> 0").select("feature").distinct().agg(F.count(F.lit(1)).alias("features"))
    dist = profiles.pairwise(profile, metric)
    return features.crossJoin(ari(own, base)).crossJoin(nmi(own, base)).crossJoin(distance_spearman(dist, primary_dist))


def variant_report(name: str, patterns: DataFrame, itemsets: DataFrame, classes: Classes, road_bit: int, k: int, threshold: Threshold | None = None) -> DataFrame:
    primary = cut(variant_profile("primary", itemsets, classes, road_bit, patterns)[0])
    base, dist = cut(clustering.labels(primary, [k])), cut(profiles.pairwise(primary))
    profile, method, metric = variant_profile(name, itemsets, classes, road_bit, patterns, threshold)
    return compare(profile, method, metric, base, dist, k).select(F.lit(name).alias("variant"), "features", "ari", "nmi", "spearman")


def sensitivity_table(patterns: DataFrame, itemsets: DataFrame, classes: Classes, road_bit: int, k: int, variants: tuple[str, ...] = VARIANTS) -> DataFrame:
    return reduce(DataFrame.unionByName, [variant_report(v, patterns, itemsets, classes, road_bit, k) for v in variants])


def threshold_sensitivity(patterns: DataFrame, k: int, shares: list[str] | None = None, primary: str = PRIMARY) -> DataFrame:
    """threshold, features, ari, nmi, spearman; one mining at the least threshold serves all."""
    shares = shares or THRESHOLDS
    every = cut(mining.mine_many(patterns, shares))
    pick = lambda s: every.filter(F.col("threshold") == Threshold.relative(s).label)
    groups = cut(patterns.select("grp").distinct())
    unit = lambda s: profiles.l2(profiles.keep_groups(profiles.profiles(pick(s)), groups))
    base = cut(unit(primary))
    labels, dist = cut(clustering.labels(base, [k])), cut(profiles.pairwise(base))
    rows = []
    for s in shares:
        rows.append(compare(unit(s), "ward", "euclidean", labels, dist, k).withColumn("threshold", F.lit(s)))
    return reduce(DataFrame.unionByName, rows).select("threshold", "features", "ari", "nmi", "spearman")


def extent_sensitivity(core: DataFrame, full: DataFrame, k: int, threshold: Threshold | None = None) -> DataFrame:
    """PATTERNS of an inner and of the full extent: how much the boundary matters."""
    t = threshold or Threshold.relative(PRIMARY)
    groups = full.select("grp").distinct()
    a, b = (cut(profiles.l2(profiles.keep_groups(profiles.profiles(mining.mine(p, t)), groups))) for p in (core, full))
    return compare(a, "ward", "euclidean", cut(clustering.labels(b, [k])), cut(profiles.pairwise(b)), k)
