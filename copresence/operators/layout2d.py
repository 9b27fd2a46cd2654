"""Neighbour-graph layout in two dimensions, for display and diagnosis only; no cluster comes from it.

A point's neighbours get membership weights that fall with distance beyond the nearest one, at a rate set so that the
weights sum to log2 of the number of neighbours; memberships of both directions join as independent chances. Points then
move: edges attract by a curve that is flat within min_dist, random other points repel. All random choices come from the
seed, and updates are made in whole passes, so a run is repeatable."""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.model import LAYOUT
from copresence.ship import arrow_groups, arrow_map, pandas_groups

from .agreement import ari, distance_spearman, nmi
from .clustering import labels_at, linkage
from .profiles import both_ways
from .validity import packed_profile

GRID = [(n, m, metric, seed) for n, m, metric, seed in itertools.product((5, 15, 30), (0.0, 0.1, 0.5), ("euclidean", "cosine"), (0, 42, 2026))]
PRIMARY = (15, 0.1, "euclidean", 42)
PASSES = 200


def distances(x: np.ndarray, metric: str) -> np.ndarray:
    if metric == "cosine":
        norm = np.sqrt((x * x).sum(1, keepdims=True))
        u = np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)
        d = 1 - u @ u.T
    else:
        sq = (x * x).sum(1)
        d = np.sqrt(np.maximum(sq[:, None] + sq[None] - 2 * x @ x.T, 0))
    np.fill_diagonal(d, 0)
    return np.maximum(d, 0)


def row_weights(own: np.ndarray) -> np.ndarray:
    """Directed weights of points to their neighbours, from the distances to them (a row a point)."""
    rho = np.where(own > 0, own, np.inf).min(1)
    over = np.maximum(own - np.where(np.isinf(rho), 0.0, rho)[:, None], 0)
    goal = np.log2(max(own.shape[1], 2))
    lo, hi, sigma, live = np.zeros(len(own)), np.full(len(own), np.inf), np.ones(len(own)), np.ones(len(own), bool)
    for _ in range(64):
        total = np.exp(-over / sigma[:, None]).sum(1)
        live &= np.abs(total - goal) >= 1e-6
        if not live.any():
            break
        high = total > goal
        hi, lo = np.where(live & high, sigma, hi), np.where(live & ~high, sigma, lo)
        sigma = np.where(live, np.where(np.isinf(hi), sigma * 2, (lo + hi) / 2), sigma)
    return np.exp(-over / np.maximum(sigma, 1e-12)[:, None])


def memberships(d: np.ndarray, n_neighbors: int) -> np.ndarray:
    """Symmetric weights of the neighbour graph."""
    n = len(d)
    w = np.zeros((n, n))
    hidden = d + np.diag(np.full(n, np.inf))
    near = np.argsort(hidden, 1, kind="stable")[:, : min(n_neighbors, n - 1)]
    at = np.arange(n)[:, None]
    w[at, near] = row_weights(hidden[at, near])
    return w + w.T - w * w.T


def curve(min_dist: float, spread: float = 1.0) -> tuple[float, float]:
    """a, b of 1 / (1 + a d^(2b)), fitted to 1 within min_dist and an exponential fall beyond (Gauss-Newton on logs)."""
    d = np.linspace(1e-3, 3 * spread, 300)
    y = np.where(d < min_dist, 1.0, np.exp(-(d - min_dist) / spread))
    p = np.array([0.4, -0.1])  # logs of a and b
    for _ in range(200):
        a, b = np.exp(p)
        t = d ** (2 * b)
        f = 1 / (1 + a * t)
        jac = np.stack([-f * f * a * t, -f * f * a * t * 2 * b * np.log(d)], 1)
        step = np.linalg.solve(jac.T @ jac + 1e-9 * np.eye(2), jac.T @ (y - f))
        p += np.clip(step, -0.5, 0.5)
        if np.abs(step).max() < 1e-10:
            break
    return float(np.exp(p[0])), float(np.exp(p[1]))


def layout(x: np.ndarray, n_neighbors: int = 15, min_dist: float = 0.1, metric: str = "euclidean", seed: int = 42, passes: int = PASSES) -> np.ndarray:
    n = len(x)
    rng = np.random.default_rng(seed)
    if n < 3:
        return np.column_stack([np.arange(n, dtype=float), np.zeros(n)])
    w = memberships(distances(x, metric), n_neighbors)
    a, b = curve(min_dist)
    # start: the two slowest directions of the graph, with a little seeded noise
    deg = np.maximum(w.sum(1), 1e-12)
    _, vec = np.linalg.eigh(np.eye(n) - w / np.sqrt(deg[:, None] * deg[None]))
    y = vec[:, 1:3] * np.where(vec[np.abs(vec[:, 1:3]).argmax(0), [1, 2]] < 0, -1, 1)
    y = 10 * y / max(np.abs(y).max(), 1e-12) + rng.normal(0, 1e-2, (n, 2))
    for t in range(passes):
        rate = 1 - t / passes
        diff = y[:, None] - y[None]
        d2 = (diff**2).sum(2)
        keep = rng.random((n, n)) < w / w.max()
        keep = np.triu(keep, 1)
        keep = keep | keep.T
        with np.errstate(divide="ignore"):
            pull = np.where(keep & (d2 > 0), -2 * a * b * d2 ** (b - 1) / (1 + a * d2**b), 0.0)
        far = rng.random((n, n)) < np.minimum(1.0, 5 * keep.sum(1)[:, None] / n)
        push = np.where(far & ~np.eye(n, dtype=bool), 2 * b / ((1e-3 + d2) * (1 + a * d2**b)), 0.0)
        y = y + rate * (np.clip(pull[..., None] * diff, -4, 4).sum(1) + np.clip(push[..., None] * diff, -4, 4).sum(1)).clip(-4, 4)
    return y


def _runs(profile: DataFrame, settings: list[tuple]) -> DataFrame:
    """run, settings and the packed profile: one row, and one task, a run."""
    spark = profile.sparkSession
    rows = [(i, *s) for i, s in enumerate(settings)]
    frame = spark.createDataFrame(rows, "run int, n_neighbors int, min_dist double, metric string, seed int").repartition(len(rows), "run")
    return frame.crossJoin(packed_profile(profile))


def layout_grid(profile: DataFrame, settings: list[tuple] | None = None, passes: int = PASSES) -> DataFrame:
    """LAYOUT of every run."""
    settings = settings or GRID

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                flat = b.column("rows")[i].values
                g, f, v = (flat.field(c).to_pylist() for c in range(3))
                grp, feature = sorted(set(g)), sorted(set(f))
                x = np.zeros((len(grp), len(feature)))
                x[np.searchsorted(grp, g), np.searchsorted(feature, f)] = v
                args = [b.column(c)[i].as_py() for c in ("n_neighbors", "min_dist", "metric", "seed")]
                y = layout(x, *args, passes=passes)
                yield pa.RecordBatch.from_pandas(pd.DataFrame({"run": np.full(len(grp), b.column("run")[i].as_py(), np.int32), "grp": grp, "x": y[:, 0], "y": y[:, 1]}), preserve_index=False)

    return arrow_map(_runs(profile, settings), run, LAYOUT)


def layout2d(profile: DataFrame, n_neighbors: int = 15, min_dist: float = 0.1, metric: str = "euclidean", seed: int = 42) -> DataFrame:
    return layout_grid(profile, [(n_neighbors, min_dist, metric, seed)])


# ---- many points: nothing is as large as all pairs of them

LANES = 64  # columns whose least stands for them while the nearest are looked for
CELLS = 4_000_000  # distances held at once
POINTS = 20_000  # points whose repulsion is drawn at once
STEPS = 60  # of the search for the slowest directions
PACKED = "names array<string>, width int, data binary"
PACKED_VALUES = 16_000_000  # coordinates that go to every task, 128 MB


def pack(vectors: DataFrame, unit: bool = False) -> DataFrame:
    """vectors(grp, vec) as one row of PACKED, in the order of grp; what a shorter vector lacks is 0. unit: scaled to length 1."""
    size = vectors.agg(F.count(F.lit(1)) * F.max(F.size("vec"))).first()[0] or 0
    if size > PACKED_VALUES:
        raise ValueError(f"vectors: {size} values, over {PACKED_VALUES}, too many to send to every task")

    def run(t: pa.Table) -> pa.Table:
        book, vec = t["grp"].combine_chunks().dictionary_encode(), t["vec"].combine_chunks()
        order = np.argsort(np.array(book.dictionary.to_pylist(), object), kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        long = np.diff(vec.offsets.to_numpy())
        row = np.repeat(np.arange(len(vec)), long)
        column = np.arange(len(row)) - np.repeat(np.cumsum(long) - long, long)
        x = np.zeros((len(order), long.max(initial=0)))
        np.add.at(x, (place[book.indices.to_numpy()][row], column), vec.flatten().fill_null(0.0).to_numpy(zero_copy_only=False))
        if unit:
            norm = np.sqrt((x * x).sum(1, keepdims=True))
            x = np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)
        names = pa.array([book.dictionary.take(pa.array(order)).to_pylist()], pa.list_(pa.string()))
        return pa.table({"names": names, "width": pa.array([x.shape[1]], pa.int32()), "data": pa.array([(x + 0.0).tobytes()], pa.binary())})  # + 0.0: no -0

    return arrow_groups(vectors.select(F.lit(0).alias("all"), "grp", "vec"), ["all"], run, PACKED)


def _blocks(packed: DataFrame) -> DataFrame:
    """block, blocks and the packed points: each task takes a block of the points and meets it with all of them."""
    spark = packed.sparkSession
    blocks = 2 * spark.sparkContext.defaultParallelism
    return spark.range(0, blocks, 1, blocks).select(F.col("id").cast("int").alias("block"), F.lit(blocks).alias("blocks")).crossJoin(F.broadcast(packed))


def _chunks(x: np.ndarray, block: int, blocks: int) -> Iterator[tuple[int, int]]:
    rows, first, last = max(1, CELLS // max(1, len(x))), block * len(x) // blocks, (block + 1) * len(x) // blocks
    for i in range(first, last, rows):
        yield i, min(last, i + rows)


class Meeting:
    """Points that meet all points, by squared distances less the own square: one product of matrices each time. What the
    product rounds off is bounded by `margin`, which also covers the tenth place, and what lies within it is taken from
    differences: distances count in whole units of the tenth place, ties by number."""

    def __init__(self, x: np.ndarray, kind: type):
        self.x, self.n, n = x, len(x), len(x)
        sq = (x * x).sum(1)
        self.left = np.column_stack([x, np.ones(n)]).astype(kind)
        self.right = np.full((x.shape[1] + 1, -(-n // LANES) * LANES), 0, kind)
        self.right[-1] = np.inf  # columns that fill up the last lanes
        self.right[:-1, :n], self.right[-1, :n] = -2 * x.T, sq
        top = sq.max(initial=0)
        self.margin = 4 * (x.shape[1] + 8) * float(np.finfo(kind).eps) * top + 8e-10 * np.sqrt(top) + 1e-19

    def squares(self, i: int, j: int) -> np.ndarray:
        """Of points i to j to all; infinite to itself."""
        d = self.left[i:j] @ self.right
        d[np.arange(j - i), np.arange(i, j)] = np.inf
        return d

    def exact(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.empty(len(a))
        for k in range(0, len(a), 100_000):
            diff = self.x[a[k : k + 100_000]] - self.x[b[k : k + 100_000]]
            out[k : k + 100_000] = np.rint(np.sqrt((diff * diff).sum(1)) * 1e10)
        return out

    def nearest(self, i: int, j: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """The k nearest of points i to j and their distances. The k-th least of the lanes' least bounds the k-th least."""
        d = self.squares(i, j)
        lanes = np.minimum.reduce(d.reshape(len(d), LANES, -1), 1)
        bound = np.partition(lanes if lanes.shape[1] >= k else d, k - 1, 1)[:, k - 1 : k]
        r, c = np.divmod(np.flatnonzero(d <= bound + 2 * self.margin), d.shape[1])
        r, c = r[c < self.n], c[c < self.n]
        r, c = r[c != r + i], c[c != r + i]
        far = self.exact(r + i, c)
        order = np.lexsort((c, far, r))
        at = order[np.searchsorted(r, np.arange(len(d)))[:, None] + np.arange(k)]  # r is in order already
        return c[at], far[at] / 1e10

    def ranks(self, i: int, j: int, to: np.ndarray) -> np.ndarray:
        """Which neighbour each of `to` (a row a point) is for points i to j; 1 is nearest."""
        d, out, met = self.squares(i, j), np.empty(to.shape, np.int64), np.empty(self.right.shape[1], bool)
        for r, row in enumerate(d):
            for c, t in enumerate(to[r]):
                least, most = row[t] - 2 * self.margin, row[t] + 2 * self.margin
                out[r, c] = 1 + np.count_nonzero(np.less(row, least, out=met))
                if np.count_nonzero(np.less_equal(row, most, out=met)) > out[r, c]:  # not itself only
                    near = np.flatnonzero(met & (row >= least))
                    copies = self.same[near] == self.same[t]
                    near, out[r, c] = near[~copies], out[r, c] + np.count_nonzero(near[copies] < t)
                    if len(near):
                        far = self.exact(np.full(len(near) + 1, i + r), np.append(near, t))
                        out[r, c] += np.count_nonzero((far[:-1] < far[-1]) | (far[:-1] == far[-1]) & (near < t))
        return out

    @cached_property
    def same(self) -> np.ndarray:
        """A number for each point that only equal points have in common."""
        return np.unique(self.x, axis=0, return_inverse=True)[1].reshape(-1)


def _points(b: pa.RecordBatch, i: int) -> tuple[np.ndarray, int, int]:
    width, block, blocks = (b.column(c)[i].as_py() for c in ("width", "block", "blocks"))
    return np.frombuffer(b.column("data")[i].as_buffer(), np.float64).reshape(-1, max(1, width)), block, blocks


def neighbour_edges(packed: DataFrame, n_neighbors: int) -> DataFrame:
    """src, dst, w: each point's nearest others by Euclidean distance, and their directed weights."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(b.num_rows):
                x, block, blocks = _points(b, at)
                names, k = b.column("names")[at].values, min(n_neighbors, len(x) - 1)
                if k < 1:
                    continue
                meeting = Meeting(x, np.float32)
                for i, j in _chunks(x, block, blocks):
                    near, d = meeting.nearest(i, j, k)
                    w = row_weights(d)
                    columns = names.take(pa.array(np.repeat(np.arange(i, j), k))), names.take(pa.array(near.ravel())), pa.array(w.ravel())
                    yield pa.RecordBatch.from_arrays(list(columns), names=["src", "dst", "w"])

    return arrow_map(_blocks(packed), run, "src string, dst string, w double")


def joined(src: np.ndarray, dst: np.ndarray, w: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Edges i < j with the weights of both directions joined, in order."""
    key = np.minimum(src, dst) * n + np.maximum(src, dst)
    order = np.argsort(key, kind="stable")
    key, first = np.unique(key[order], return_index=True)
    return key // n, key % n, 1 - np.multiply.reduceat(1 - w[order], first)


def slow_directions(i: np.ndarray, j: np.ndarray, w: np.ndarray, n: int, rng: np.random.Generator) -> np.ndarray:
    """The two slowest directions of the graph beside the constant one, by Lanczos steps."""
    add = lambda v: np.bincount(i, v[0], n) + np.bincount(j, v[1], n)
    root = np.sqrt(np.maximum(add((w, w)), 1e-12))
    s = w / (root[i] * root[j])
    basis = [root / np.sqrt((root * root).sum())]
    q = rng.normal(size=n)
    alphas, betas = [], []
    for _ in range(min(STEPS, n - 1)):
        for _ in range(2):  # twice: once leaves what was rounded off
            q -= np.array(basis).T @ (np.array(basis) @ q)
        size = np.sqrt(q @ q)
        if size < 1e-10:
            break
        betas.append(size)
        basis.append(q / size)
        q = add((s * basis[-1][j], s * basis[-1][i]))
        alphas.append(basis[-1] @ q)
    off = np.diag(betas[1:], 1) if len(betas) > 1 else 0
    vec = np.linalg.eigh(np.diag(alphas) + off + np.transpose(off))[1][:, ::-1][:, :2]
    y = np.zeros((n, 2))
    y[:, : vec.shape[1]] = np.array(basis[1:]).T @ vec
    return y


def graph_layout(i: np.ndarray, j: np.ndarray, w: np.ndarray, n: int, min_dist: float = 0.1, seed: int = 42, passes: int = PASSES) -> np.ndarray:
    """What `layout` does, from the edges: in each pass an edge is taken by its weight, and a point is pushed by five random
    others for each of its edges taken."""
    rng = np.random.default_rng(seed)
    if n < 3:
        return np.column_stack([np.arange(n, dtype=float), np.zeros(n)])
    a, b = curve(min_dist)
    y = slow_directions(i, j, w, n, rng)
    y *= np.where(y[np.abs(y).argmax(0), [0, 1]] < 0, -1, 1)
    y = 10 * y / max(np.abs(y).max(), 1e-12) + rng.normal(0, 1e-2, (n, 2))
    chance = w / w.max()
    for t in range(passes):
        taken = rng.random(len(w)) < chance
        p, q = i[taken], j[taken]
        diff = y[p] - y[q]
        d2 = (diff * diff).sum(1)
        with np.errstate(divide="ignore"):
            pull = np.where(d2 > 0, -2 * a * b * d2 ** (b - 1) / (1 + a * d2**b), 0.0)
        force = np.clip(pull[:, None] * diff, -4, 4)
        move = np.column_stack([np.bincount(p, force[:, c], n) - np.bincount(q, force[:, c], n) for c in (0, 1)])
        others = rng.binomial(n - 1, np.minimum(1.0, 5 * (np.bincount(p, minlength=n) + np.bincount(q, minlength=n)) / n))
        for first in range(0, n, POINTS):
            own = np.repeat(np.arange(first, min(n, first + POINTS)), others[first : first + POINTS])
            other = rng.integers(0, n - 1, len(own))
            other += other >= own
            diff = y[own] - y[other]
            d2 = (diff * diff).sum(1)
            force = np.clip((2 * b / ((1e-3 + d2) * (1 + a * d2**b)))[:, None] * diff, -4, 4)
            m = min(n, first + POINTS) - first
            move[first : first + m] += np.column_stack([np.bincount(own - first, force[:, c], m) for c in (0, 1)])
        y = y + (1 - t / passes) * move.clip(-4, 4)
    return y


def layout_points(packed: DataFrame, n_neighbors: int = 15, min_dist: float = 0.1, seed: int = 42, passes: int = PASSES) -> DataFrame:
    """LAYOUT (run 0) of many points by Euclidean distance: neighbours by blocks of points, then one task for the passes."""

    def run(t: pa.Table) -> pa.Table:
        names, at = np.unique(np.array(t["src"].to_pylist(), object), return_inverse=True)
        place = {g: k for k, g in enumerate(names)}
        to = np.array([place[g] for g in t["dst"].to_pylist()], np.int64)
        y = graph_layout(*joined(at.astype(np.int64), to, t["w"].to_numpy(), len(names)), len(names), min_dist, seed, passes)
        return pa.table({"run": pa.array(np.zeros(len(names), np.int32)), "grp": pa.array(names, pa.string()), "x": pa.array(y[:, 0].copy()), "y": pa.array(y[:, 1].copy())})

    return arrow_groups(neighbour_edges(packed, n_neighbors).withColumn("run", F.lit(0)), ["run"], run, LAYOUT)


def points_faithful(packed: DataFrame, coords: DataFrame, k: int = 10) -> DataFrame:
    """run, trustworthiness, overlap of LAYOUT rows of all packed points: the same as `trustworthiness` and
    `neighbour_overlap` give. Ranks are counted in a block's distances; no pair leaves its task."""
    low = coords.groupBy("run").agg(F.sort_array(F.collect_list(F.struct("grp", "x", "y"))).alias("placed"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(b.num_rows):
                x, block, blocks = _points(b, at)
                placed = b.column("placed")[at].values
                if not placed.field(0).equals(b.column("names")[at].values):
                    raise ValueError("the layout is not one of these points")
                y = np.column_stack([placed.field(c).to_numpy() for c in (1, 2)])
                over = hits = 0
                near = min(k, len(x) - 1)
                if near < 1:
                    continue
                high, plane = Meeting(x, np.float64), Meeting(y, np.float64)
                for i, j in _chunks(x, block, blocks):
                    ranks = high.ranks(i, j, plane.nearest(i, j, near)[0])
                    over, hits = over + int((ranks - k).clip(0).sum()), hits + int((ranks <= k).sum())
                yield pa.RecordBatch.from_pydict({"run": pa.array([b.column("run")[at].as_py()], pa.int32()), "n": [len(x)], "over": [over], "hits": [hits]})

    counts = arrow_map(_blocks(packed).crossJoin(F.broadcast(low)), run, "run int, n long, over long, hits long")
    n = F.col("n")
    return counts.groupBy("run", "n").agg(F.sum("over").alias("over"), F.sum("hits").alias("hits")).select("run", (1 - 2 * F.col("over") / (n * k * (2 * n - 3 * k - 1))).alias("trustworthiness"), (F.col("hits") / (n * k)).alias("overlap"))


# ---- how faithful a layout is


def layout_distances(coords: DataFrame) -> DataFrame:
    """run, a, b, d of LAYOUT rows."""
    p, q = coords.select("run", F.col("grp").alias("a"), F.col("x").alias("xa"), F.col("y").alias("ya")), coords.select("run", F.col("grp").alias("b"), F.col("x").alias("xb"), F.col("y").alias("yb"))
    dx, dy = F.col("xa") - F.col("xb"), F.col("ya") - F.col("yb")
    return p.join(q, "run").filter("a < b").select("run", "a", "b", F.sqrt(dx * dx + dy * dy).alias("d"))


def _ranks(dist: DataFrame, by: list[str]) -> DataFrame:
    """Neighbour rank of b for a: 1 is nearest; ties at 10 places go by name, the point itself is left out by identity."""
    both = dist.select(*by, "a", "b", "d").unionByName(dist.select(*by, F.col("b").alias("a"), F.col("a").alias("b"), "d"))
    return both.withColumn("rank", F.row_number().over(W.partitionBy(*by, "a").orderBy(F.round("d", 10), "b"))).drop("d")


def trustworthiness(high: DataFrame, low: DataFrame, k: int = 10) -> DataFrame:
    """high(a, b, d), low(run, a, b, d) -> run, trustworthiness: points near in the layout should be near in the original."""
    n = both_ways(high).select("a").distinct().agg(F.count(F.lit(1)).alias("n"))
    near = _ranks(low, ["run"]).filter(F.col("rank") <= k).select("run", "a", "b")
    over = near.join(_ranks(high, []), ["a", "b"]).groupBy("run").agg(F.sum(F.greatest(F.lit(0), F.col("rank") - k)).alias("over")).crossJoin(F.broadcast(n))
    return over.select("run", (1 - 2 * F.col("over") / (F.col("n") * k * (2 * F.col("n") - 3 * k - 1))).alias("trustworthiness"))


def neighbour_overlap(high: DataFrame, low: DataFrame, k: int = 10) -> DataFrame:
    """run, overlap: mean share of the k nearest others that original and layout have in common."""
    near_low = _ranks(low, ["run"]).filter(F.col("rank") <= k).select("run", "a", "b")
    near_high = _ranks(high, []).filter(F.col("rank") <= k).select("a", "b")
    n = near_high.select("a").distinct().agg(F.count(F.lit(1)).alias("n"))
    hits = near_low.join(near_high, ["a", "b"], "left_semi").groupBy("run").agg(F.count(F.lit(1)).alias("hits"))
    runs = low.select("run").distinct()
    return runs.join(hits, "run", "left").crossJoin(F.broadcast(n)).select("run", (F.coalesce("hits", F.lit(0)) / (F.col("n") * k)).alias("overlap"))


def layout_labels(coords: DataFrame, k: int) -> DataFrame:
    """run, grp, u: Ward on the coordinates, for comparison only."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("grp")
        x = pdf[["x", "y"]].to_numpy()
        return pd.DataFrame({"run": pdf["run"].to_numpy(), "grp": pdf["grp"].to_numpy(), "u": labels_at(linkage(x), len(x), min(k, len(x)))})

    return pandas_groups(coords, ["run"], run, "run int, grp string, u int")


def layout_metrics(coords: DataFrame, high: DataFrame, labelled: DataFrame, k: int, near: int = 10) -> DataFrame:
    """All five diagnostics of each run. labelled(grp, cluster): the fixed clusters of the original space."""
    low = layout_distances(coords)
    own, fixed = layout_labels(coords, k), labelled.select("grp", F.col("cluster").alias("v"))
    return (
        trustworthiness(high, low, near).join(neighbour_overlap(high, low, near), "run").join(distance_spearman(low, high, ("run",)), "run")
        .join(ari(own, fixed, ("run",)), "run").join(nmi(own, fixed, ("run",)), "run")
    )


def display_positions(coords: DataFrame, radius: float, passes: int = 60) -> DataFrame:
    """LAYOUT with dx, dy: points that lie closer than two radii are nudged apart for display; x and y stay."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("grp")
        y = pdf[["x", "y"]].to_numpy().copy()
        angle = 2.399963 * np.arange(len(y))
        y += 1e-6 * np.column_stack([np.cos(angle), np.sin(angle)])  # parts points in one place
        for _ in range(passes):
            diff = y[:, None] - y[None]
            d = np.sqrt((diff**2).sum(2)) + np.eye(len(y))
            gap = np.where((d < 2 * radius) & ~np.eye(len(y), dtype=bool), (2 * radius - d) / 2, 0)
            if not gap.any():
                break
            y += (diff / d[..., None] * gap[..., None]).sum(1) * 0.5
        return pd.DataFrame({"run": pdf["run"].to_numpy(), "grp": pdf["grp"].to_numpy(), "x": pdf["x"].to_numpy(), "y": pdf["y"].to_numpy(), "dx": y[:, 0], "dy": y[:, 1]})

    return pandas_groups(coords, ["run"], run, "run int, grp string, x double, y double, dx double, dy double")
