"""Agglomerative clustering of profiles: Ward's criterion and average linkage, cuts, order, cophenetic distances.

Up to GATHER groups the profile's rows (sparse, one per nonzero) are gathered into one Arrow task; beyond that, rounds
merge all reciprocal nearest pairs at once, which for these reducible criteria gives the same tree.

Leaves are numbered by group name. A cluster is known by its least leaf; of equal costs (to 12 places) the pair with the
least (least leaf, least leaf) merges first. A merge's height is the root of twice Ward's increase, so two leaves merge
at their distance. Clusters of a cut are numbered by their least leaf."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.model import LABELS, MERGES
from copresence.plans.shared import cut as write
from copresence.ship import pandas_groups

from .profiles import both_ways

GATHER = 4000
CELLS = 200_000_000  # groups x features of a dense matrix, 1.6 GB
PLACES = 12


def matrix(pdf: pd.DataFrame) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Sorted groups, sorted features, dense values."""
    grp, feature = sorted(pdf["grp"].unique()), np.unique(pdf["feature"].to_numpy())
    x = np.zeros((len(grp), len(feature)))
    x[np.searchsorted(grp, pdf["grp"]), np.searchsorted(feature, pdf["feature"])] = pdf["value"]
    return grp, feature, x


def _costs(x: np.ndarray, method: str, size: np.ndarray) -> np.ndarray:
    """Cost of joining each pair of rows."""
    if method == "ward":
        sq = (x * x).sum(1)
        return np.maximum(sq[:, None] + sq[None] - 2 * x @ x.T, 0) * (size[:, None] * size[None] / (size[:, None] + size[None]))
    norm = np.sqrt((x * x).sum(1))
    u = np.divide(x, norm[:, None], out=np.zeros_like(x), where=norm[:, None] > 0)
    return 1 - u @ u.T


def linkage(x: np.ndarray, method: str = "ward", sizes: np.ndarray | None = None) -> np.ndarray:
    """Merges (left, right, height, size) of the rows of x; leaf ids 0..G-1, merge t makes G + t. method: ward, or
    average (mean cosine distance). sizes: the rows are centroids of so many points each (ward)."""
    n = len(x)
    size = np.ones(n) if sizes is None else np.array(sizes, float)
    cost = _costs(x, method, size)
    np.fill_diagonal(cost, np.inf)
    name, alive = list(range(n)), np.ones(n, bool)
    upper = np.triu(np.ones((n, n), bool), 1)
    out = np.zeros((max(n - 1, 0), 4))
    work = np.where(upper, np.round(cost, PLACES), np.inf)  # each pair once, in the row of its lesser slot
    near = work.argmin(1) if n > 1 else np.zeros(0, int)
    low = work[np.arange(n), near] if n > 1 else np.zeros(0)
    for t in range(n - 1):
        i = int(np.argmin(low))
        j = int(near[i])
        c = cost[i, j]
        out[t] = name[i], name[j], np.sqrt(2 * max(c, 0)) if method == "ward" else c, size[i] + size[j]
        others = alive.copy()
        others[[i, j]] = False
        if method == "ward":
            new = ((size[i] + size) * cost[i] + (size[j] + size) * cost[j] - size * c) / (size[i] + size[j] + size)
        else:
            new = (size[i] * cost[i] + size[j] * cost[j]) / (size[i] + size[j])
        cost[i, others] = cost[others, i] = new[others]
        alive[j] = False
        cost[j, :] = cost[:, j] = np.inf
        size[i] += size[j]
        name[i] = n + t
        rounded = np.round(new, PLACES)
        work[j, :] = work[:, j] = np.inf
        right, left = i + 1 + np.flatnonzero(others[i + 1 :]), np.flatnonzero(others[:i])
        work[i, :] = np.inf
        work[i, right], work[left, i] = rounded[right], rounded[left]
        # only rows whose nearest was one of the two are searched again; for the others the new cost alone can be nearer
        low[j] = np.inf
        again = np.flatnonzero(alive & ((near == i) | (near == j)))
        again = np.append(again[again != i], i)
        near[again] = work[again].argmin(1)
        low[again] = work[again, near[again]]
        closer = left[(work[left, i] < low[left]) | ((work[left, i] == low[left]) & (i < near[left]))]
        near[closer], low[closer] = i, work[closer, i]
    return out


def labels_at(merges: np.ndarray, n: int, k: int) -> np.ndarray:
    """Cluster of each leaf when the tree is cut into k, numbered by least leaf."""
    root = np.arange(2 * n - 1)
    for t in range(n - k):
        a, b = int(merges[t, 0]), int(merges[t, 1])
        root[a] = root[b] = n + t
    top = root[:n].copy()
    while True:
        up = root[top]
        if (up == top).all():
            break
        top = up
    _, first = np.unique(top, return_index=True)
    rank = {top[f]: r for r, f in enumerate(sorted(first))}
    return np.array([rank[t] for t in top])


def _gathered(profile: DataFrame, run, schema: str) -> DataFrame:
    """One task over a profile of at most GATHER groups and, dense, CELLS values (both checked)."""
    n = profile.select("grp").distinct().limit(GATHER + 1).count()
    if n > GATHER:
        raise ValueError(f"over {GATHER} groups: use ward_rounds")
    most = CELLS // max(n, 1)
    if profile.select("feature").distinct().limit(most + 1).count() > most:
        raise ValueError(f"over {CELLS} values for {n} groups: use ward_rounds or a higher minimum support")
    return pandas_groups(profile.select("grp", "feature", "value", F.lit(0).alias("one")), ["one"], run, schema)


def merges(profile: DataFrame, method: str = "ward") -> DataFrame:
    """MERGES of the profile's groups."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = matrix(pdf)[2]
        m = linkage(x, method)
        least = list(range(len(x)))
        for a, b, *_ in m:
            least.append(min(least[int(a)], least[int(b)]))
        leaves = [[least[int(r[c])] for r in m] for c in (0, 1)]
        return pd.DataFrame({"step": np.arange(1, len(m) + 1), "left": m[:, 0].astype(int), "right": m[:, 1].astype(int), "left_leaf": leaves[0], "right_leaf": leaves[1], "height": m[:, 2], "size": m[:, 3].astype(int)})

    return _gathered(profile, run, MERGES)


def labels(profile: DataFrame, ks: list[int], method: str = "ward") -> DataFrame:
    """LABELS for every k in ks (those up to the number of groups), from one tree."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp, _, x = matrix(pdf)
        m = linkage(x, method)
        parts = [pd.DataFrame({"k": k, "grp": grp, "cluster": labels_at(m, len(grp), k)}) for k in ks if k <= len(grp)]
        return pd.concat(parts) if parts else pd.DataFrame({"k": [], "grp": [], "cluster": []})

    return _gathered(profile, run, LABELS)


def leaf_order_of(m: np.ndarray, n: int) -> list[int]:
    """Leaves from left to right; the child with the lesser least leaf is on the left."""
    inside: dict[int, list[int]] = {i: [i] for i in range(n)}
    for t, (a, b, *_) in enumerate(m):
        x, y = inside.pop(int(a)), inside.pop(int(b))
        inside[n + t] = x + y if min(x) < min(y) else y + x
    return [leaf for part in inside.values() for leaf in part]


def leaf_order(profile: DataFrame, method: str = "ward") -> DataFrame:
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp, _, x = matrix(pdf)
        order = leaf_order_of(linkage(x, method), len(grp))
        return pd.DataFrame({"grp": [grp[i] for i in order], "place": np.arange(len(order))})

    return _gathered(profile, run, "grp string, place int")


def cophenetic(profile: DataFrame, method: str = "ward") -> DataFrame:
    """a, b, height at which two groups first share a cluster."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp, _, x = matrix(pdf)
        m, n = linkage(x, method), len(grp)
        inside: dict[int, list[int]] = {i: [i] for i in range(n)}
        rows = []
        for t, (a, b, h, _) in enumerate(m):
            p, q = inside.pop(int(a)), inside.pop(int(b))
            rows += [(grp[min(i, j)], grp[max(i, j)], h) for i in p for j in q]
            inside[n + t] = p + q
        return pd.DataFrame(rows, columns=["a", "b", "height"])

    return _gathered(profile, run, "a string, b string, height double")


def heatmap(dist: DataFrame, order: DataFrame) -> DataFrame:
    """Distances with both axes in leaf order."""
    j = both_ways(dist).join(order.select(F.col("grp").alias("a"), F.col("place").alias("row")), "a").join(order.select(F.col("grp").alias("b"), F.col("place").alias("col")), "b")
    return j.select("row", "col", "a", "b", "d")


# ---- beyond one task


def ward_rounds(profile: DataFrame, gather_below: int = GATHER, max_rounds: int = 200) -> DataFrame:
    """Ward's tree by rounds over (cluster, feature, sum) rows: every cluster finds its nearest, pairs that chose each
    other merge, sums add up; when gather_below clusters or fewer are left, one task finishes on their centroids.
    Returns left, right (least group names), height, size; sorted by height it is the tree.

    State is one row per cluster and feature, written to the shared folder each round; distances are never stored."""
    state = write(profile.select(F.col("grp").alias("c"), F.lit(1).cast("long").alias("n"), "feature", F.col("value").alias("s")))
    done: DataFrame | None = None
    for turn in range(max_rounds + 1):
        if state.select("c").distinct().limit(gather_below + 1).count() <= gather_below:
            break
        if turn == max_rounds:
            raise RuntimeError(f"more than {gather_below} clusters are left after {max_rounds} rounds")
        mean = state.select("c", "n", "feature", (F.col("s") / F.col("n")).alias("v"))
        sq = mean.groupBy("c", "n").agg(F.sum(F.col("v") * F.col("v")).alias("q"))
        x, y = mean.select(F.col("c").alias("a"), "feature", F.col("v").alias("va")), mean.select(F.col("c").alias("b"), "feature", F.col("v").alias("vb"))
        dots = x.join(y, "feature").filter("a < b").groupBy("a", "b").agg(F.sum(F.col("va") * F.col("vb")).alias("dot"))
        pairs = sq.select(F.col("c").alias("a"), F.col("n").alias("na"), F.col("q").alias("qa")).join(sq.select(F.col("c").alias("b"), F.col("n").alias("nb"), F.col("q").alias("qb")), F.col("a") < F.col("b")).join(dots, ["a", "b"], "left")
        inc = F.round(F.greatest(F.lit(0.0), F.col("qa") + F.col("qb") - 2 * F.coalesce("dot", F.lit(0.0))) * F.col("na") * F.col("nb") / (F.col("na") + F.col("nb")), PLACES)
        # a pair's cost is computed once and counts for both its ends
        each = pairs.select(F.struct(inc.alias("inc"), F.col("a").alias("lo"), F.col("b").alias("hi")).alias("m"), (F.col("na") + F.col("nb")).alias("n"))
        near = each.select(F.explode(F.array("m.lo", "m.hi")).alias("c"), "m", "n").groupBy("c").agg(F.min(F.struct("m", "n")).alias("p"))
        rows = write(near.groupBy("p").agg(F.count(F.lit(1)).alias("votes")).filter("votes = 2").select(F.col("p.m.lo").alias("left"), F.col("p.m.hi").alias("right"), F.sqrt(2 * F.col("p.m.inc")).alias("height"), F.col("p.n").cast("int").alias("size")))
        done = rows if done is None else done.unionByName(rows)
        to = rows.select(F.explode(F.array("left", "right")).alias("c"), F.col("left").alias("into"), F.col("size").cast("long").alias("total"))
        moved = state.join(to, "c", "left").select(F.coalesce("into", "c").alias("c"), F.coalesce("total", "n").alias("n"), "feature", "s")
        state = write(moved.groupBy("c", "n", "feature").agg(F.sum("s").alias("s")))

    def finish(pdf: pd.DataFrame) -> pd.DataFrame:
        sizes = pdf.groupby("c")["n"].first()
        grp, _, x = matrix(pdf.rename(columns={"c": "grp", "s": "value"}))
        n = sizes.loc[grp].to_numpy(float)
        m = linkage(x / n[:, None], sizes=n)
        least = list(range(len(grp)))
        for a, b, *_ in m:
            least.append(min(least[int(a)], least[int(b)]))
        names = [pd.Series([str(grp[least[int(r[side])]]) for r in m], dtype=object) for side in (0, 1)]
        return pd.DataFrame({"left": names[0], "right": names[1], "height": m[:, 2], "size": m[:, 3].astype("int32")})

    if done is not None and not state.select("c").distinct().limit(2).count() > 1:
        return done
    rest = pandas_groups(state.withColumn("one", F.lit(0)), ["one"], finish, "left string, right string, height double, size int")
    return rest if done is None else done.unionByName(rest)


def cluster_sizes(labelled: DataFrame) -> DataFrame:
    return labelled.groupBy("k", "cluster").agg(F.count(F.lit(1)).alias("size"))


def rank_of_leaf(labelled: DataFrame) -> DataFrame:
    return labelled.withColumn("leaf", F.dense_rank().over(W.partitionBy("k").orderBy("grp")) - 1)
