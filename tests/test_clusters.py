from __future__ import annotations

import hashlib
import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from copresence.model import Classes, Threshold
from copresence.operators import agreement, clustering, inference, layout2d, mining, profiles, report, sensitivity, validity

from .reference import brute


def frame(spark, x):
    return spark.createDataFrame([(f"g{i:02d}", j, float(v)) for i, row in enumerate(x) for j, v in enumerate(row) if v], "grp string, feature long, value double")


@pytest.fixture(scope="module")
def points():
    rng = np.random.default_rng(3)
    return np.abs(np.concatenate([rng.normal(c, 0.3, (6, 5)) for c in ([3, 0, 0, 1, 0], [0, 3, 0, 0, 1], [0, 0, 3, 1, 1])]))


@pytest.mark.parametrize("seed", range(3))
def test_ward_against_sums_of_squares(seed):
    x = np.random.default_rng(seed).random((14, 4))
    m = clustering.linkage(x)
    want = brute.ward(x)
    assert np.allclose(m[:, 2], [w[2] for w in want]) and [int(s) for s in m[:, 3]] == [w[3] for w in want]
    assert (np.diff(m[:, 2]) >= -1e-9).all()
    for k in range(1, 15):
        assert len(set(clustering.labels_at(m, 14, k))) == k


@pytest.mark.parametrize("method", ["ward", "average"])
def test_linkage_against_whole_searches(method):
    for seed in range(4):
        rng = np.random.default_rng(seed)
        x = rng.integers(0, 4, (40, 3)).astype(float) + 0.5 if seed % 2 else rng.random((40, 6))  # many ties; none
        got, want = clustering.linkage(x, method), plain_linkage(x, method)
        assert [tuple(map(int, r[[0, 1, 3]])) for r in got] == [(a, b, n) for a, b, _, n in want] and np.allclose(got[:, 2], [h for _, _, h, _ in want], atol=1e-9)


def plain_linkage(x, method):
    """Merges by searching all pairs of clusters each time, from the points themselves."""
    members, name, out = {i: [i] for i in range(len(x))}, {i: i for i in range(len(x))}, []
    u = x / np.linalg.norm(x, axis=1, keepdims=True)

    def cost(p, q):
        if method == "average":
            return float(np.mean([1 - u[i] @ u[j] for i in p for j in q]))
        gap = x[p].mean(0) - x[q].mean(0)
        return float(gap @ gap) * len(p) * len(q) / (len(p) + len(q))

    costs = {(a, b): cost(members[a], members[b]) for a in members for b in members if a < b}
    while len(members) > 1:
        a, b = min(costs, key=lambda p: (round(costs[p], 10), p))
        c = costs[a, b]
        members[a] = members[a] + members.pop(b)
        out.append((name[a], name[b], np.sqrt(2 * c) if method == "ward" else c, len(members[a])))
        name[a] = len(x) + len(out) - 1
        costs = {p: v for p, v in costs.items() if b not in p}
        costs |= {(min(a, o), max(a, o)): cost(members[a], members[o]) for o in members if o != a}
    return out


def plain_labels(x, k, method="ward"):
    m = plain_linkage(x, method)
    inside = {i: [i] for i in range(len(x))}
    for t, (a, b, *_) in enumerate(m[: len(x) - k]):
        inside[len(x) + t] = inside.pop(a) + inside.pop(b)
    out = np.zeros(len(x), int)
    for c, part in enumerate(sorted(inside.values(), key=min)):
        out[part] = c
    return out


def unit_rows(x):
    norm = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)


def ranks(v):
    v = np.round(v, 10)
    return np.array([(v < y).sum() + ((v == y).sum() + 1) / 2 for y in v])


def pair_distances(x):
    return np.array([np.linalg.norm(x[i] - x[j]) for i in range(len(x)) for j in range(i + 1, len(x))])


def plain_stability(x, features, ks, reps, seed):
    """Mean ARI by k: draws by digest order, trees by searching all pairs."""
    full = {k: plain_labels(unit_rows(x), k) for k in ks}
    got = {k: [] for k in ks}
    for rep in range(reps):
        order = sorted(range(len(features)), key=lambda i: (hashlib.md5(f"{seed}|{rep}|{features[i]}".encode()).hexdigest(), features[i]))
        own = unit_rows(x[:, sorted(order[: int(0.8 * len(features))])])
        for k in ks:
            got[k].append(brute.rand_index(full[k], plain_labels(own, k)))
    return {k: (np.mean(v), np.std(v)) for k, v in got.items()}


def test_stability_and_choice_against_plain_versions(spark, points):
    p, ks = frame(spark, points), [2, 3, 4]
    features = sorted(j for j in range(points.shape[1]) if points[:, j].any())
    want = plain_stability(points[:, features], features, ks, 12, 5)
    stable = validity.stability(p, ks, 12, seed=5).persist()
    for r in stable.collect():
        assert (r["stability"], r["sd"]) == pytest.approx(want[r["k"]])
    unit = profiles.l2(p)
    lab = clustering.labels(unit, ks).persist()
    ranked = validity.criteria(unit, profiles.pairwise(unit), lab, stable).persist()
    rows = {r["k"]: r for r in ranked.collect()}
    x = unit_rows(points)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    criteria = {k: [] for k in ks}
    for k in ks:
        u = plain_labels(x, k)
        cents = np.array([x[u == c].mean(0) for c in range(k)])
        within = sum(((x[u == c] - cents[c]) ** 2).sum() for c in range(k))
        between = sum((u == c).sum() * ((cents[c] - x.mean(0)) ** 2).sum() for c in range(k))
        spread = [np.linalg.norm(x[u == c] - cents[c], axis=1).mean() for c in range(k)]
        bouldin = np.mean([max((spread[i] + spread[j]) / np.linalg.norm(cents[i] - cents[j]) for j in range(k) if j != i) for i in range(k)])
        criteria[k] = [-brute.silhouette(d, u), -between / (k - 1) / (within / (len(x) - k)), bouldin, -want[k][0]]
    mean = np.mean([ranks(np.array([criteria[k][c] for k in ks])) for c in range(4)], 0)
    for k, m in zip(ks, mean, strict=True):
        assert rows[k]["mean_rank"] == pytest.approx(m)
    assert validity.choose_k(ranked).first()["k"] == ks[int(np.argmin(np.round(mean, 9)))]


def test_components_variant_against_a_plain_version(spark, points):
    items = spark.createDataFrame([(f"g{i:02d}", 1 << j, int(100 * v / points.max()), 100) for i, row in enumerate(points) for j, v in enumerate(row) if int(100 * v / points.max())], "grp string, itemset long, sup long, n long")
    items = items.withColumn("rel", F.col("sup") / F.col("n")).persist()
    patterns = items.select("grp", F.col("itemset").alias("mask"), F.col("sup").alias("weight"))
    x = unit_rows(np.floor(100 * points / points.max()) / 100)
    for name, share in (("pca90", 0.9), ("pca95", 0.95)):
        got = sensitivity.variant_report(name, patterns, items, None, 0, 4).first()
        c = x - x.mean(0)
        u, s, _ = np.linalg.svd(c, full_matrices=False)
        m = int(np.flatnonzero(np.cumsum(s**2) / (s**2).sum() >= share - 1e-12)[0]) + 1
        scores = u[:, :m] * s[:m]
        assert got["features"] == m
        assert got["ari"] == pytest.approx(brute.rand_index(plain_labels(scores, 4), plain_labels(x, 4)))
        assert got["spearman"] == pytest.approx(np.corrcoef(ranks(pair_distances(scores)), ranks(pair_distances(x)))[0, 1])
        kept = sensitivity.explained_variance(profiles.l2(profiles.profiles(items)), (share,)).first()
        assert kept["components"] == m and kept["reached"] == pytest.approx((s[:m] ** 2).sum() / (s**2).sum())


def test_groups_without_features_stay(spark):
    classes = Classes((1, 1, 2))
    rows = [("a", 0b001, 60), ("a", 0b010, 40), ("b", 0b001, 50), ("b", 0b011, 50), ("c", 0b100, 90), ("c", 0b001, 5), ("d", 0b010, 70), ("d", 0b001, 30)]
    patterns = spark.createDataFrame(rows, "grp string, mask long, weight long")
    items = mining.mine(patterns, Threshold.relative("10%")).persist()
    profile, method, metric = sensitivity.variant_profile("artificial_only", items, classes, 0, patterns)
    assert {r["grp"] for r in profile.collect()} == {"a", "b", "c", "d"} and {r["grp"] for r in clustering.labels(profile, [2], method).collect()} == {"a", "b", "c", "d"}
    lost = {r["grp"]: r["degenerate"] for r in profiles.with_absent_groups(profiles.only_artificial(profiles.profiles(items), classes), patterns).collect()}
    assert lost == {"a": False, "b": False, "c": True, "d": False}
    d = {(r["a"], r["b"]): r["d"] for r in profiles.pairwise(profile, metric).collect()}
    assert len(d) == 6 and d["a", "c"] == pytest.approx(1) and d["c", "d"] == pytest.approx(1)
    report_row = sensitivity.variant_report("artificial_only", patterns, items, classes, 0, 2).first()
    assert report_row["features"] == 3
    both = sensitivity.threshold_sensitivity(patterns, 2, ["10%", "95%"]).collect()  # one set reaches 95 %, in one group
    assert {r["threshold"]: r["features"] for r in both}["95%"] == 1 and len(both) == 2
    empty = profiles.keep_groups(profiles.profiles(items.limit(0)), patterns)
    assert {(r["grp"], r["value"]) for r in empty.collect()} == {(g, 0.0) for g in "abcd"}


def test_order_of_leaves_and_heatmap(spark, points):
    p = frame(spark, points)
    order = {r["grp"]: r["place"] for r in clustering.leaf_order(p).collect()}
    m = plain_linkage(points, "ward")

    def leaves(node):
        if node < len(points):
            return [node]
        parts = [leaves(c) for c in m[node - len(points)][:2]]
        return [leaf for part in sorted(parts, key=min) for leaf in part]

    assert [order[f"g{i:02d}"] for i in leaves(2 * len(points) - 2)] == list(range(len(points)))
    cells = clustering.heatmap(profiles.pairwise(p), clustering.leaf_order(p)).collect()
    assert len(cells) == len(points) * (len(points) - 1)
    for r in cells:
        assert (r["row"], r["col"]) == (order[r["a"]], order[r["b"]]) and r["d"] == pytest.approx(np.linalg.norm(points[int(r["a"][1:])] - points[int(r["b"][1:])]), abs=1e-6)


def test_layout_measures_against_plain_versions(spark, points):
    rng = np.random.default_rng(2)
    planes = {0: rng.random((18, 2)), 1: points[:, :2]}
    coords = spark.createDataFrame([(run, f"g{i:02d}", float(a), float(b)) for run, y in planes.items() for i, (a, b) in enumerate(y)], "run int, grp string, x double, y double")
    lab = plain_labels(points, 3)
    labelled = spark.createDataFrame([(f"g{i:02d}", int(c)) for i, c in enumerate(lab)], "grp string, cluster int")
    got = {r["run"]: r for r in layout2d.layout_metrics(coords, profiles.pairwise(frame(spark, points)), labelled, 3, near=4).collect()}
    near = lambda z: [sorted((round(float(np.linalg.norm(z[i] - z[j])), 10), j) for j in range(18) if j != i) for i in range(18)]
    high = near(points)
    for run, y in planes.items():
        low, k = near(y), 4
        over = sum(max(0, [j for _, j in high[i]].index(b) + 1 - k) for i in range(18) for _, b in low[i][:k])
        assert got[run]["trustworthiness"] == pytest.approx(1 - 2 * over / (18 * k * (2 * 18 - 3 * k - 1)))
        assert got[run]["overlap"] == pytest.approx(np.mean([len({j for _, j in low[i][:k]} & {j for _, j in high[i][:k]}) / k for i in range(18)]))
        assert got[run]["spearman"] == pytest.approx(np.corrcoef(ranks(pair_distances(y)), ranks(pair_distances(points)))[0, 1])
        assert got[run]["ari"] == pytest.approx(brute.rand_index(plain_labels(y, 3), lab))


def test_ranks_over_ranges(spark):
    rng = np.random.default_rng(9)
    x, y = rng.integers(0, 30, 400) / 7, rng.random(400)
    names = [(f"a{i:03d}", f"b{i:03d}") for i in range(400)]
    one, two = (spark.createDataFrame([(*n, float(v)) for n, v in zip(names, w, strict=True)], "a string, b string, d double") for w in (x, y))
    assert agreement.distance_spearman(one, two).first()["spearman"] == pytest.approx(np.corrcoef(ranks(x), ranks(y))[0, 1])
    assert agreement.distance_spearman(one, one).first()["spearman"] == pytest.approx(1)


def test_what_is_sent_to_every_task_is_bounded(spark):
    from copresence.plans.shared import bounded

    assert bounded(spark.range(5), 5, "rows").count() == 5
    with pytest.raises(ValueError):
        bounded(spark.range(6), 5, "rows")


def test_ties_duplicates_and_small_inputs():
    x = np.array([[0.0], [1], [2], [3], [3]])
    assert [tuple(map(int, r[:2])) for r in clustering.linkage(x)][:2] == [(3, 4), (0, 1)]
    assert clustering.linkage(np.zeros((1, 2))).shape == (0, 4)
    assert clustering.linkage(np.array([[0.0, 0], [3, 4]]))[0, 2] == pytest.approx(5)


def test_rounds_give_the_same_tree(spark, points):
    p = frame(spark, points)
    want = clustering.linkage(points)
    for below in (1, 9, 100):
        got = clustering.ward_rounds(p, below).orderBy("height").collect()
        assert np.allclose([r["height"] for r in got], want[:, 2]) and [r["size"] for r in got] == [int(s) for s in want[:, 3]]


def test_indices_against_plain_versions(spark, points):
    p = frame(spark, points)
    lab = clustering.labels(p, [2, 3, 5]).persist()
    dist = profiles.pairwise(p)
    d = np.sqrt(((points[:, None] - points[None]) ** 2).sum(2))
    sil = {r["k"]: r["silhouette"] for r in validity.silhouette(dist, lab).collect()}
    ch = {r["k"]: r["calinski_harabasz"] for r in validity.calinski_harabasz(p, lab).collect()}
    db = {r["k"]: r["davies_bouldin"] for r in validity.davies_bouldin(p, lab).collect()}
    for k in (2, 3, 5):
        u = np.array([r["cluster"] for r in lab.filter(F.col("k") == k).orderBy("grp").collect()])
        assert sil[k] == pytest.approx(brute.silhouette(d, u))
        cents = np.array([points[u == c].mean(0) for c in range(k)])
        ssw = sum(((points[u == c] - cents[c]) ** 2).sum() for c in range(k))
        ssb = sum((u == c).sum() * ((cents[c] - points.mean(0)) ** 2).sum() for c in range(k))
        assert ch[k] == pytest.approx(ssb / (k - 1) / (ssw / (len(u) - k)))
        s = [np.sqrt(((points[u == c] - cents[c]) ** 2).sum(1)).mean() for c in range(k)]
        assert db[k] == pytest.approx(np.mean([max((s[i] + s[j]) / np.linalg.norm(cents[i] - cents[j]) for j in range(k) if j != i) for i in range(k)]))
    med = {r["cluster"]: r["medoid"] for r in report.medoids(dist, lab.filter("k = 3")).collect()}
    assert len(med) == 3


def test_adjusted_rand_and_mutual_information(spark):
    rng = np.random.default_rng(8)
    u, v = rng.integers(0, 3, 20), rng.integers(0, 4, 20)
    a, b = (spark.createDataFrame([(f"g{i}", int(x)) for i, x in enumerate(w)], f"grp string, {c} int") for w, c in ((u, "u"), (v, "v")))
    assert agreement.ari(a, b).first()["ari"] == pytest.approx(brute.rand_index(u, v)) == pytest.approx(validity.adjusted_rand(u, v))
    same = a.withColumnRenamed("u", "v")
    assert agreement.ari(a, same).first()["ari"] == 1 and agreement.nmi(a, same).first()["nmi"] == pytest.approx(1)


def test_stability_depends_on_the_seed_alone(spark, points):
    p = frame(spark, points)
    one = validity.stability_runs(p, [2, 3], 6, seed=1, tasks=1).orderBy("rep", "k").collect()
    two = validity.stability_runs(p.repartition(5), [2, 3], 6, seed=1, tasks=4).orderBy("rep", "k").collect()
    assert one == two
    assert all(r["ari"] == 1 for r in validity.stability_runs(profiles.l2(p), [3], 2, fraction=1.0).collect())


def test_ranks_average_ties(spark):
    t = spark.createDataFrame([(2, 0.5, 9.0, 1.0, 0.9), (3, 0.5, 7.0, 2.0, 0.8), (4, 0.1, 8.0, 3.0, 0.7)], "k int, silhouette double, calinski_harabasz double, davies_bouldin double, stability double")
    r = {x["k"]: x for x in validity.rank_criteria(t).collect()}
    assert r[2]["rank_silhouette"] == r[3]["rank_silhouette"] == 1.5 and r[2]["mean_rank"] == (1.5 + 1 + 1 + 1) / 4
    assert validity.choose_k(validity.rank_criteria(t)).first()["k"] == 2


def test_absolute_support_is_relative_support_after_scaling(spark):
    items = spark.createDataFrame([("a", 1, 30, 100), ("a", 2, 10, 100), ("b", 1, 5, 40), ("b", 4, 20, 40)], "grp string, itemset long, sup long, n long").withColumn("rel", F.col("sup") / F.col("n"))
    x, y = ({(r["grp"], r["feature"]): r["value"] for r in profiles.l2(f(items)).collect()} for f in (profiles.profiles, profiles.absolute))
    assert x.keys() == y.keys() and all(x[k] == pytest.approx(y[k]) for k in x)


def test_components_keep_the_variance(points):
    c = points - points.mean(0)
    total = (c**2).sum()
    for share in (0.9, 0.95):
        s, reached = sensitivity._pca(points, share)
        assert (s**2).sum() / total == pytest.approx(reached[-1]) and reached[-1] >= share and len(reached) == s.shape[1]
        assert s.shape[1] == 1 or (s[:, :-1] ** 2).sum() / total < share


def test_printed_p_values(spark):
    t = spark.createDataFrame([("a", 51.99, 6), ("b", 50.03, 6), ("c", 15.07, 6)], "measure string, h double, df int").withColumn("p", inference.chi2_p())
    got = {r["measure"]: r["adjusted"] for r in inference.holm(t).collect()}
    assert got["a"] == pytest.approx(5.62e-9, rel=1e-3) and got["b"] == pytest.approx(9.273e-9, rel=1e-3) and got["c"] == pytest.approx(0.0197, abs=5e-5)


def test_association(spark):
    perfect = spark.createDataFrame([(f"g{i}", str(i % 3), str(i % 3)) for i in range(30)], "grp string, u string, v string")
    r = inference.cramers_v_permutation(perfect, 99).first()
    assert r["v"] == pytest.approx(1) and r["p"] == pytest.approx(1 / 100)
    square = spark.createDataFrame([(f"g{i}", u, v) for i, (u, v) in enumerate([("x", "p")] * 10 + [("x", "q")] * 20 + [("y", "p")] * 30 + [("y", "q")] * 40)], "grp string, u string, v string")
    chi2 = sum((o - e) ** 2 / e for o, e in ((10, 12), (20, 18), (30, 28), (40, 42)))
    assert inference.cramers_v(square).first()["v"] == pytest.approx((chi2 / 100) ** 0.5)


def test_layout_is_repeatable_and_faithful(spark, points):
    a, b = layout2d.layout(points, 5, passes=80), layout2d.layout(points, 5, passes=80)
    assert np.array_equal(a, b) and np.isfinite(a).all()
    p = frame(spark, points)
    high = profiles.pairwise(p)
    own = spark.createDataFrame([(0, f"g{i:02d}", float(x), float(y)) for i, (x, y) in enumerate(a)] + [(1, f"g{i:02d}", float(x), float(y)) for i, (x, y) in enumerate(np.random.default_rng(0).random((18, 2)))], "run int, grp string, x double, y double")
    low = layout2d.layout_distances(own)
    trust = {r["run"]: r["trustworthiness"] for r in layout2d.trustworthiness(high, low, 4).collect()}
    assert trust[0] > trust[1]
    same = high.select(F.lit(0).alias("run"), "a", "b", "d")
    assert layout2d.trustworthiness(high, same, 4).first()["trustworthiness"] == 1 and layout2d.neighbour_overlap(high, same, 4).first()["overlap"] == 1
    placed = layout2d.display_positions(own, 0.3)
    assert placed.join(own.withColumnsRenamed({"x": "x0", "y": "y0"}), ["run", "grp"]).filter("x <> x0 OR y <> y0").count() == 0


def edges_of(x, k):
    """The edges of `neighbour_edges`, from one whole matrix."""
    near, d = layout2d.Meeting(x, np.float32).nearest(0, len(x), k)
    w = layout2d.row_weights(d)
    return layout2d.joined(np.repeat(np.arange(len(x)), k), near.ravel(), w.ravel(), len(x))


def test_edges_are_the_memberships():
    x = np.random.default_rng(5).normal(size=(150, 6))
    i, j, w = edges_of(x, 7)
    want = layout2d.memberships(layout2d.distances(x, "euclidean"), 7)
    got = np.zeros_like(want)
    got[i, j] = got[j, i] = w
    assert (i < j).all() and np.allclose(got, want, atol=1e-5)
    y = layout2d.slow_directions(i, j, w, 150, np.random.default_rng(0))
    deg = want.sum(1)
    val, vec = np.linalg.eigh(np.eye(150) - want / np.sqrt(deg[:, None] * deg[None]))
    assert np.allclose(np.abs((vec[:, 1:3] * y).sum(0)), 1, atol=1e-3) and val[1] > 1e-3


def test_layout_of_many_points_holds_no_pairs():
    """A matrix of all pairs of these points takes 72 MB; whole matrices took several of them."""
    rng = np.random.default_rng(1)
    x = rng.normal(size=(3000, 4)) + 12 * np.eye(4)[rng.integers(0, 4, 3000)]
    for kind in (np.float32, np.float64):
        meeting, d = layout2d.Meeting(x, kind), np.sqrt(((x[40:60, None] - x) ** 2).sum(2))
        d[np.arange(20), np.arange(40, 60)] = np.inf
        near, far = meeting.nearest(40, 60, 10)
        assert np.array_equal(near, np.argsort(d, 1)[:, :10]) and np.allclose(far, np.sort(d, 1)[:, :10])
        assert np.array_equal(meeting.ranks(40, 60, near[:, ::3]), np.tile([1, 4, 7, 10], (20, 1)))
    i, j, w = edges_of(x, 10)
    tracemalloc.start()
    y = layout2d.graph_layout(i, j, w, 3000, passes=15)
    assert tracemalloc.get_traced_memory()[1] < 40e6
    tracemalloc.stop()
    assert np.isfinite(y).all() and np.array_equal(y, layout2d.graph_layout(i, j, w, 3000, passes=15))


def test_layout_of_many_points_is_as_faithful_as_by_matrices(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(200, 5)) + 4 * np.eye(5)[rng.integers(0, 4, 200)]
    rows = spark.createDataFrame([(f"{k:03d}", [float(v) for v in r]) for k, r in enumerate(x)], "grp string, vec array<double>")
    packed = layout2d.pack(rows.repartition(5))
    a, b = ({r["grp"]: (r["x"], r["y"]) for r in layout2d.layout_points(p, 10).collect()} for p in (packed, layout2d.pack(rows.repartition(2))))
    assert a == b and len(a) == 200
    y = layout2d.layout(x, 10)
    coords = spark.createDataFrame([(run, g, float(p), float(q)) for run, at in ((0, a), (1, {f"{k:03d}": v for k, v in enumerate(y)})) for g, (p, q) in at.items()], "run int, grp string, x double, y double")
    got = {r["run"]: r for r in layout2d.points_faithful(packed, coords).collect()}
    assert got[0]["trustworthiness"] > got[1]["trustworthiness"] - 0.02 and got[0]["overlap"] > got[1]["overlap"] - 0.05


def test_measures_of_many_points_are_those_of_all_pairs(spark):
    """Also where points are copies, lie within the ten places of each other, or tie."""
    rng = np.random.default_rng(7)
    x = np.concatenate([rng.integers(0, 3, (90, 4)).astype(float), rng.normal(size=(40, 4))])
    x = np.concatenate([x, x[-20:] + 1e-7 * rng.normal(size=(20, 4))])
    y = np.concatenate([rng.integers(0, 6, (80, 2)).astype(float), rng.normal(size=(70, 2))])
    n, k = len(x), 6
    coords = spark.createDataFrame([(3, f"{i:03d}", float(a), float(b)) for i, (a, b) in enumerate(y)], "run int, grp string, x double, y double")
    packed = layout2d.pack(spark.createDataFrame([(f"{i:03d}", [float(v) for v in r]) for i, r in enumerate(x)], "grp string, vec array<double>").repartition(3))
    got = layout2d.points_faithful(packed, coords, k).first()
    order = lambda z: [[j for _, j in sorted((round(float(np.sqrt(((z[i] - z[j]) ** 2).sum())), 10), j) for j in range(n) if j != i)] for i in range(n)]
    high, low = order(x), order(y)
    over = sum(max(0, high[i].index(b) + 1 - k) for i in range(n) for b in low[i][:k])
    assert got["run"] == 3 and got["trustworthiness"] == pytest.approx(1 - 2 * over / (n * k * (2 * n - 3 * k - 1)), abs=1e-12)
    assert got["overlap"] == pytest.approx(np.mean([len(set(low[i][:k]) & set(high[i][:k])) / k for i in range(n)]))


def test_points_packed(spark):
    rows = spark.createDataFrame([("b", [3.0, 4.0]), ("a", [2.0]), ("c", [0.0, 0.0, None])], "grp string, vec array<double>")
    r = layout2d.pack(rows, unit=True).first()
    assert r["names"] == ["a", "b", "c"] and np.allclose(np.frombuffer(r["data"]).reshape(3, r["width"]), [[1, 0, 0], [0.6, 0.8, 0], [0, 0, 0]])
    for few in (rows.limit(0), rows.limit(1), rows.limit(2)):
        packed = layout2d.pack(few)
        coords = layout2d.layout_points(packed)
        assert coords.count() == (few.count() if few.count() > 1 else 0) and layout2d.points_faithful(packed, coords).count() == (few.count() == 2)
