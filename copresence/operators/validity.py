"""How many clusters: silhouette, Calinski-Harabasz, Davies-Bouldin, stability under feature subsampling, joint ranks.

labelled(k, grp, cluster) may hold any number of k; every index is one plan for all of them."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.plans.shared import bounded
from copresence.ship import arrow_map

from .clustering import labels_at, linkage
from .profiles import both_ways


def silhouette(dist: DataFrame, labelled: DataFrame) -> DataFrame:
    """k, silhouette: mean over groups; 0 for a group alone in its cluster."""
    j = both_ways(dist).join(labelled.select("k", F.col("grp").alias("a"), F.col("cluster").alias("ca")), "a").join(labelled.select("k", F.col("grp").alias("b"), F.col("cluster").alias("cb")), ["k", "b"])
    means = j.groupBy("k", "a", "ca", "cb").agg(F.avg("d").alias("m"))
    per = means.groupBy("k", "a").agg(F.max(F.when(F.col("ca") == F.col("cb"), F.col("m"))).alias("own"), F.min(F.when(F.col("ca") != F.col("cb"), F.col("m"))).alias("next"))
    own, other = F.col("own"), F.col("next")
    s = F.when(own.isNull() | other.isNull() | (F.greatest(own, other) == 0), F.lit(0.0)).otherwise((other - own) / F.greatest(own, other))
    return per.groupBy("k").agg(F.avg(s).alias("silhouette"))


def _centroids(profile: DataFrame, labelled: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(k, cluster, feature, c) without zeros, and (k, cluster, n)."""
    n = labelled.groupBy("k", "cluster").agg(F.count(F.lit(1)).cast("double").alias("n"))
    sums = labelled.join(profile, "grp").groupBy("k", "cluster", "feature").agg(F.sum("value").alias("s"))
    return sums.join(n, ["k", "cluster"]).select("k", "cluster", "feature", (F.col("s") / F.col("n")).alias("c")), n


def _to_centroid(profile: DataFrame, labelled: DataFrame, cent: DataFrame) -> DataFrame:
    """k, grp, cluster, d2: squared distance of each group to its cluster's centroid."""
    sq = profile.groupBy("grp").agg(F.sum(F.col("value") * F.col("value")).alias("sq"))
    cc = cent.groupBy("k", "cluster").agg(F.sum(F.col("c") * F.col("c")).alias("cc"))
    dot = labelled.join(profile, "grp").join(cent, ["k", "cluster", "feature"]).groupBy("k", "grp").agg(F.sum(F.col("value") * F.col("c")).alias("dot"))
    j = labelled.join(sq, "grp", "left").join(cc, ["k", "cluster"], "left").join(dot, ["k", "grp"], "left").fillna(0.0, ["sq", "cc", "dot"])
    return j.select("k", "grp", "cluster", F.greatest(F.lit(0.0), F.col("sq") + F.col("cc") - 2 * F.col("dot")).alias("d2"))


def calinski_harabasz(profile: DataFrame, labelled: DataFrame) -> DataFrame:
    cent, n = _centroids(profile, labelled)
    within = _to_centroid(profile, labelled, cent).groupBy("k").agg(F.sum("d2").alias("ssw"), F.count(F.lit(1)).cast("double").alias("g"), F.count_distinct("cluster").cast("double").alias("q"))
    groups = profile.select("grp").distinct().agg(F.count(F.lit(1)).cast("double").alias("all"))
    mean = profile.groupBy("feature").agg(F.sum("value").alias("s")).crossJoin(groups).select("feature", (F.col("s") / F.col("all")).alias("m"))
    mm = mean.agg(F.sum(F.col("m") * F.col("m")).alias("mm"))
    cc = cent.groupBy("k", "cluster").agg(F.sum(F.col("c") * F.col("c")).alias("cc"))
    cm = cent.join(mean, "feature").groupBy("k", "cluster").agg(F.sum(F.col("c") * F.col("m")).alias("cm"))
    between = n.join(cc, ["k", "cluster"]).join(cm, ["k", "cluster"]).crossJoin(mm).groupBy("k").agg(F.sum(F.col("n") * (F.col("cc") + F.col("mm") - 2 * F.col("cm"))).alias("ssb"))
    return within.join(between, "k").select("k", ((F.col("ssb") / (F.col("q") - 1)) / (F.col("ssw") / (F.col("g") - F.col("q")))).alias("calinski_harabasz"))


def davies_bouldin(profile: DataFrame, labelled: DataFrame) -> DataFrame:
    cent, _ = _centroids(profile, labelled)
    spread = _to_centroid(profile, labelled, cent).groupBy("k", "cluster").agg(F.avg(F.sqrt("d2")).alias("s"))
    cc = cent.groupBy("k", "cluster").agg(F.sum(F.col("c") * F.col("c")).alias("cc")).join(spread, ["k", "cluster"])
    x = cc.select("k", F.col("cluster").alias("i"), F.col("cc").alias("ci"), F.col("s").alias("si"))
    y = cc.select("k", F.col("cluster").alias("j"), F.col("cc").alias("cj"), F.col("s").alias("sj"))
    dot = cent.select("k", "feature", F.col("cluster").alias("i"), F.col("c").alias("vi")).join(cent.select("k", "feature", F.col("cluster").alias("j"), F.col("c").alias("vj")), ["k", "feature"]).groupBy("k", "i", "j").agg(F.sum(F.col("vi") * F.col("vj")).alias("dot"))
    j = x.join(y, "k").filter("i <> j").join(dot, ["k", "i", "j"], "left").fillna(0.0, ["dot"])
    ratio = (F.col("si") + F.col("sj")) / F.sqrt(F.greatest(F.lit(1e-300), F.col("ci") + F.col("cj") - 2 * F.col("dot")))
    return j.groupBy("k", "i").agg(F.max(ratio).alias("worst")).groupBy("k").agg(F.avg("worst").alias("davies_bouldin"))


# ---- stability


def feature_draws(profile: DataFrame, reps: int, fraction: float = 0.8, seed: int = 0) -> DataFrame:
    """rep, feature: floor(fraction * features) of the features for each repetition, without replacement, by digest order
    (so a draw depends on no partitioning and can be made in SQL)."""
    features = profile.select("feature").distinct()
    n = features.agg(F.count(F.lit(1)).alias("f"))
    each = features.crossJoin(profile.sparkSession.range(reps).select(F.col("id").cast("int").alias("rep")))
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("rep").cast("string"), F.col("feature").cast("string")))
    ranked = each.withColumn("r", F.row_number().over(W.partitionBy("rep").orderBy(key, "feature"))).crossJoin(F.broadcast(n))  # n: one row
    return ranked.filter(F.col("r") <= F.floor(F.col("f") * F.lit(fraction))).select("rep", "feature")


def adjusted_rand(u: np.ndarray, v: np.ndarray) -> float:
    cells = np.zeros((u.max() + 1, v.max() + 1))
    np.add.at(cells, (u, v), 1)
    pairs = lambda c: (c * (c - 1) / 2).sum()
    p, pu, pv, n = pairs(cells), pairs(cells.sum(1)), pairs(cells.sum(0)), len(u)
    low, top = pu * pv / (n * (n - 1) / 2) if n > 1 else 0.0, (pu + pv) / 2
    return 1.0 if top == low else float((p - low) / (top - low))


def _md5_ranks(seed: int, rep: int, features: np.ndarray) -> np.ndarray:
    keys = [md5(f"{seed}|{rep}|{f}".encode()).hexdigest() for f in features]
    return np.array(sorted(range(len(keys)), key=lambda i: (keys[i], features[i])))


PACKED = 4_000_000  # nonzero values of a profile that goes to every task, about 100 MB


def packed_profile(profile: DataFrame) -> DataFrame:
    """The profile as one row, to be broadcast; its size is checked."""
    bounded(profile, PACKED, "profile")
    return F.broadcast(profile.groupBy().agg(F.sort_array(F.collect_list(F.struct("grp", "feature", "value"))).alias("rows")))


def stability_runs(profile: DataFrame, ks: list[int], reps: int, fraction: float = 0.8, seed: int = 0, tasks: int | None = None) -> DataFrame:
    """rep, k, ari: each repetition draws features, scales rows to length 1, builds one tree, cuts it at every k and
    compares with the full tree's cut. The profile goes to the repetitions as one packed row; nothing comes to the driver."""
    spark = profile.sparkSession
    packed = packed_profile(profile)
    tasks = tasks or spark.sparkContext.defaultParallelism
    runs = spark.range(0, reps, 1, tasks).select(F.col("id").cast("int").alias("rep")).crossJoin(packed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cached = None
        for b in batches:
            out = []
            for rep, rows in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if cached is None:
                    flat = rows.values
                    g, f, v = (flat.field(i).to_pylist() for i in range(3))
                    grp, feature = sorted(set(g)), np.array(sorted(set(f)), np.int64)
                    x = np.zeros((len(grp), len(feature)))
                    x[np.searchsorted(grp, g), np.searchsorted(feature, f)] = v
                    full = _unit(x)
                    tree = linkage(full)
                    cached = x, feature, {k: labels_at(tree, len(grp), k) for k in ks if k <= len(grp)}
                x, feature, want = cached
                chosen = np.sort(_md5_ranks(seed, rep, feature)[: int(np.floor(fraction * len(feature)))])
                tree = linkage(_unit(x[:, chosen]))
                out += [(rep, k, adjusted_rand(u, labels_at(tree, len(x), k))) for k, u in want.items()]
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int32()), pa.array([o[1] for o in out], pa.int32()), pa.array([o[2] for o in out], pa.float64())], names=["rep", "k", "ari"])

    return arrow_map(runs, run, "rep int, k int, ari double")


def _unit(x: np.ndarray) -> np.ndarray:
    norm = np.sqrt((x * x).sum(1, keepdims=True))
    return np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)


def stability(profile: DataFrame, ks: list[int], reps: int = 500, fraction: float = 0.8, seed: int = 0) -> DataFrame:
    """k, stability (mean), sd."""
    return stability_runs(profile, ks, reps, fraction, seed).groupBy("k").agg(F.avg("ari").alias("stability"), F.stddev_pop("ari").alias("sd"))


# ---- joint ranks

DIRECTIONS = {"silhouette": -1, "calinski_harabasz": -1, "davies_bouldin": 1, "stability": -1}


def rank_criteria(table: DataFrame) -> DataFrame:
    """table(k, four criteria) with a rank for each (ties averaged) and their mean; a row a candidate k."""
    out = table
    for name, sign in DIRECTIONS.items():
        v = F.round(F.col(name) * sign, 10)
        out = out.withColumn("__v", v).withColumn(f"rank_{name}", F.rank().over(W.partitionBy(F.lit(0)).orderBy("__v")) + (F.count(F.lit(1)).over(W.partitionBy("__v")) - 1) / 2)
    out = out.drop("__v")
    return out.withColumn("mean_rank", sum((F.col(f"rank_{n}") for n in DIRECTIONS), F.lit(0.0)) / len(DIRECTIONS))


def criteria(profile: DataFrame, dist: DataFrame, labelled: DataFrame, stable: DataFrame) -> DataFrame:
    """All four criteria with ranks. profile: unit rows; stable: what `stability` gives for the rows before scaling."""
    t = silhouette(dist, labelled).join(calinski_harabasz(profile, labelled), "k").join(davies_bouldin(profile, labelled), "k").join(stable, "k")
    return rank_criteria(t)


def choose_k(ranked: DataFrame) -> DataFrame:
    """The k of the best mean rank, the smaller k on a tie. Evidence for a choice, not the true number."""
    return ranked.orderBy(F.round("mean_rank", 9), "k").limit(1).select("k", "mean_rank")
