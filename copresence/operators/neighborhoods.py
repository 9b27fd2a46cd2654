"""Which units meet a unit's buffer: joins on tiles, so that no plan pairs all units with all units.

A unit's box is listed under each tile that it covers, a focal unit's under the tiles of its box grown by the distance;
units meet in a tile (an equi-join on group and tile) and an exact test follows. A pair that shares several tiles is
reported only in the one that holds the lower corner of what the grown box and the box have in common. Distances are
closed: exactly d counts. Every unit is its own neighbour at distance 0.

Skew: a dense tile is split by salting the focal side (`salts`), the other side is repeated as often.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from copresence.functions import masks
from copresence.ship import arrow_groups, arrow_map


def _tiles(low: Column, high: Column, side: int) -> Column:
    return F.explode(F.sequence(F.floor(low / side).cast("long"), F.floor(high / side).cast("long")))


def span_pairs(units: DataFrame, d: int, side: int | None = None, keys: tuple[str, ...] = ("grp", "part")) -> DataFrame:
    """units(SPAN) -> grp, focal_id, other_id, focal_bit, other_bit, dist for intervals of the same part within d."""
    side = side or max(2 * d, 16)
    a = units.select(*keys, F.col("unit_id").alias("focal_id"), F.col("bit").alias("focal_bit"), F.col("lo").alias("alo"), F.col("hi").alias("ahi"), _tiles(F.col("lo") - d, F.col("hi") + d, side).alias("tile"))
    b = units.select(*keys, F.col("unit_id").alias("other_id"), F.col("bit").alias("other_bit"), F.col("lo").alias("blo"), F.col("hi").alias("bhi"), _tiles(F.col("lo"), F.col("hi"), side).alias("tile"))
    j = a.join(b, [*keys, "tile"]).filter((F.col("blo") <= F.col("ahi") + d) & (F.col("bhi") >= F.col("alo") - d))
    j = j.filter(F.col("tile") == F.floor(F.greatest(F.col("alo") - d, F.col("blo")) / side))
    return j.select(*keys, "focal_id", "other_id", "focal_bit", "other_bit", F.greatest(F.lit(0), F.col("blo") - F.col("ahi"), F.col("alo") - F.col("bhi")).alias("dist"))


def rect_pairs(units: DataFrame, d: int, side: int | None = None, same_group: bool = True, salts: int = 1, focal: DataFrame | None = None) -> DataFrame:
    """units(RECT), and focal units if only some of them are -> grp, focal_id, other_id, focal_bit, other_bit, dist2 (squared gap, whole numbers)."""
    side = side or max(2 * d, 64)
    keys = ["grp"] if same_group else []
    a = (units if focal is None else focal).select("grp", F.col("unit_id").alias("focal_id"), F.col("bit").alias("focal_bit"), *[F.col(c).alias(f"a{c}") for c in ("x0", "x1", "y0", "y1")])
    a = a.withColumn("tx", _tiles(F.col("ax0") - d, F.col("ax1") + d, side)).withColumn("ty", _tiles(F.col("ay0") - d, F.col("ay1") + d, side)).withColumn("salt", F.pmod(F.xxhash64("focal_id"), F.lit(salts)).cast("int"))
    b = units.select(*(["grp"] if same_group else []), F.col("unit_id").alias("other_id"), F.col("bit").alias("other_bit"), *[F.col(c).alias(f"b{c}") for c in ("x0", "x1", "y0", "y1")])
    b = b.withColumn("tx", _tiles(F.col("bx0"), F.col("bx1"), side)).withColumn("ty", _tiles(F.col("by0"), F.col("by1"), side)).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    gap = lambda p, q: F.greatest(F.lit(0), F.col(f"b{p}") - F.col(f"a{q}"), F.col(f"a{p}") - F.col(f"b{q}"))
    j = a.join(b, [*keys, "tx", "ty", "salt"]).withColumn("dist2", gap("x0", "x1") * gap("x0", "x1") + gap("y0", "y1") * gap("y0", "y1")).filter(F.col("dist2") <= d * d)
    home = (F.col("tx") == F.floor(F.greatest(F.col("ax0") - d, F.col("bx0")) / side)) & (F.col("ty") == F.floor(F.greatest(F.col("ay0") - d, F.col("by0")) / side))
    return j.filter(home).select("grp", "focal_id", "other_id", "focal_bit", "other_bit", "dist2")


def rect_cost(units: DataFrame, d: int, side: int | None = None) -> DataFrame:
    """What `rect_pairs` costs, in one row: units, rows listed on tiles on either side, pairs that meet in a tile before
    the exact test (products of counts a tile: no pair is made), pairs after it."""
    side = side or max(2 * d, 64)
    on = lambda grow: units.select("grp", _tiles(F.col("x0") - grow, F.col("x1") + grow, side).alias("tx"), "y0", "y1").select("grp", "tx", _tiles(F.col("y0") - grow, F.col("y1") + grow, side).alias("ty")).groupBy("grp", "tx", "ty")
    focal, other = on(d).agg(F.count(F.lit(1)).alias("f")), on(0).agg(F.count(F.lit(1)).alias("o"))
    tiles = focal.join(other, ["grp", "tx", "ty"], "full_outer").agg(F.sum("f").alias("focal_rows"), F.sum("o").alias("other_rows"), F.sum(F.col("f") * F.col("o")).alias("candidates"))
    return units.agg(F.count(F.lit(1)).alias("units")).crossJoin(tiles).crossJoin(rect_pairs(units, d, side).agg(F.count(F.lit(1)).alias("pairs")))


# ---- polygons as vertex rings


def parse_rings(wkt: str | Column) -> Column:
    """POLYGON or MULTIPOLYGON text -> array of rings (array<struct<x, y>>), holes and parts alike: what is inside follows
    from all rings by the even-odd rule. Null, EMPTY and texts with an unreadable number have no rings."""
    w = F.col(wkt) if isinstance(wkt, str) else wkt
    number = lambda q, i: F.get(q, i).try_cast("double")
    words = lambda r: F.transform(F.split(r, ","), lambda p: F.split(F.trim(p), r"\s+"))
    ring = lambda r: F.transform(words(r), lambda q: F.struct(number(q, 0).alias("x"), number(q, 1).alias("y")))
    found = F.transform(F.regexp_extract_all(F.coalesce(w, F.lit("")), F.lit(r"\(([^()]*)\)"), F.lit(1)), ring)
    unreadable = lambda rings: F.exists(rings, lambda r: F.exists(r, lambda q: q["x"].isNull() | q["y"].isNull()))
    none = F.array().cast("array<array<struct<x:double,y:double>>>")
    return F.get(F.transform(F.array(found), lambda rings: F.when(unreadable(rings), none).otherwise(rings)), F.lit(0))  # found is worked out once


def box_as_ring(x0: str | Column, x1: str | Column, y0: str | Column, y1: str | Column) -> Column:
    """A rectangle as the text of a closed ring."""
    corner = lambda x, y: F.concat_ws(" ", x if isinstance(x, Column) else F.col(x), y if isinstance(y, Column) else F.col(y))
    return F.concat(F.lit("("), F.concat_ws(", ", corner(x0, y0), corner(x1, y0), corner(x1, y1), corner(x0, y1), corner(x0, y0)), F.lit(")"))


def rect_as_wkt(units: DataFrame) -> DataFrame:
    """RECT units as POLYGON texts."""
    return units.select("grp", "unit_id", "bit", F.concat(F.lit("POLYGON ("), box_as_ring("x0", "x1", "y0", "y1"), F.lit(")")).alias("wkt"))


def frames_as_wkt(units: DataFrame) -> DataFrame:
    """RECT units as rectangles two units thick around them with a hole that holds them: the margin goes by the unit."""
    m = 3 + 2 * F.pmod(F.col("unit_id"), F.lit(20))
    grown = lambda k: box_as_ring(F.col("x0") - k, F.col("x1") + k, F.col("y0") - k, F.col("y1") + k)
    return units.select("grp", "unit_id", "bit", F.concat(F.lit("POLYGON ("), grown(m), F.lit(", "), grown(m - 2), F.lit(")")).alias("wkt"))


Rings = list[np.ndarray]


def _segments(rings: Rings) -> tuple[np.ndarray, np.ndarray]:
    """Ends of all edges of all rings."""
    closed = [r if np.array_equal(r[0], r[-1]) and len(r) > 1 else np.vstack([r, r[:1]]) for r in rings]
    return np.concatenate([r[:-1] for r in closed]), np.concatenate([r[1:] for r in closed])


def _inside(point: np.ndarray, a: np.ndarray, b: np.ndarray) -> bool:
    """Whether a ray from the point meets an odd number of edges."""
    crosses = (a[:, 1] > point[1]) != (b[:, 1] > point[1])
    a, b = a[crosses], b[crosses]
    x = a[:, 0] + (point[1] - a[:, 1]) / (b[:, 1] - a[:, 1]) * (b[:, 0] - a[:, 0])
    return bool(np.count_nonzero(point[0] < x) % 2)


def _point_to_segments(p: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances, points by segments."""
    ab = b - a
    long2 = np.maximum((ab**2).sum(1), 1e-300)
    t = np.clip(((p[:, None, :] - a[None]) * ab[None]).sum(2) / long2, 0, 1)
    return ((p[:, None, :] - (a[None] + t[..., None] * ab[None])) ** 2).sum(2)


def _cross(a: np.ndarray, b: np.ndarray, c: np.ndarray, d: np.ndarray) -> bool:
    """Whether some segment a-b properly crosses some segment c-d."""
    side = lambda p, q, r: (q[..., 0] - p[..., 0]) * (r[..., 1] - p[..., 1]) - (q[..., 1] - p[..., 1]) * (r[..., 0] - p[..., 0])
    a, b, c, d = a[:, None], b[:, None], c[None], d[None]
    return bool(((side(a, b, c) * side(a, b, d) < 0) & (side(c, d, a) * side(c, d, b) < 0)).any())


def ring_distance2(p: Rings, q: Rings) -> float:
    """Squared distance of two polygons given by their rings; 0 where they touch or overlap. Where no edges cross, every
    ring lies wholly inside or outside of the other polygon, so one point of each tells."""
    (a, b), (c, d) = _segments(p), _segments(q)
    if _cross(a, b, c, d) or any(_inside(r[0], c, d) for r in p) or any(_inside(r[0], a, b) for r in q):
        return 0.0
    return float(min(_point_to_segments(a, c, d).min(), _point_to_segments(c, a, b).min()))


def _rings_of(value: pa.Scalar) -> Rings:
    rings = value.values
    flat = rings.flatten()
    points = np.column_stack([flat.field(i).to_numpy(zero_copy_only=False) for i in (0, 1)])
    return np.split(points, np.cumsum(rings.value_lengths().to_numpy())[:-1])


def ring_pairs(units: DataFrame, d: float, side: float | None = None) -> DataFrame:
    """units(grp, unit_id, bit, rings) -> pairs within d: boxes meet on tiles in the JVM, rings of the survivors are
    tested in Arrow batches. A unit without rings has no place and meets itself only."""
    side = side or max(2 * d, 64)
    every = lambda c: F.flatten(F.transform("rings", lambda r: F.transform(r, lambda p: p[c])))
    placed = units.filter(F.size("rings") > 0)
    boxed = placed.withColumns({"x0": F.array_min(every("x")), "x1": F.array_max(every("x")), "y0": F.array_min(every("y")), "y1": F.array_max(every("y"))})
    a = boxed.select("grp", F.col("unit_id").alias("focal_id"), F.col("bit").alias("focal_bit"), F.col("rings").alias("ra"), *[F.col(c).alias(f"a{c}") for c in ("x0", "x1", "y0", "y1")])
    a = a.withColumn("tx", _tiles(F.col("ax0") - d, F.col("ax1") + d, side)).withColumn("ty", _tiles(F.col("ay0") - d, F.col("ay1") + d, side))
    b = boxed.select("grp", F.col("unit_id").alias("other_id"), F.col("bit").alias("other_bit"), F.col("rings").alias("rb"), *[F.col(c).alias(f"b{c}") for c in ("x0", "x1", "y0", "y1")])
    b = b.withColumn("tx", _tiles(F.col("bx0"), F.col("bx1"), side)).withColumn("ty", _tiles(F.col("by0"), F.col("by1"), side))
    gap = lambda p, q: F.greatest(F.lit(0.0), F.col(f"b{p}") - F.col(f"a{q}"), F.col(f"a{p}") - F.col(f"b{q}"))
    j = a.join(b, ["grp", "tx", "ty"]).filter(gap("x0", "x1") * gap("x0", "x1") + gap("y0", "y1") * gap("y0", "y1") <= d * d)
    home = (F.col("tx") == F.floor(F.greatest(F.col("ax0") - d, F.col("bx0")) / side)) & (F.col("ty") == F.floor(F.greatest(F.col("ay0") - d, F.col("by0")) / side))
    j = j.filter(home).select("grp", "focal_id", "other_id", "focal_bit", "other_bit", "ra", "rb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            same = (x.column("focal_id").to_numpy(zero_copy_only=False) == x.column("other_id").to_numpy(zero_copy_only=False)).tolist()
            d2 = np.array([0.0 if own else ring_distance2(_rings_of(p), _rings_of(q)) for own, p, q in zip(same, x.column("ra"), x.column("rb"), strict=True)], float)
            keep = pa.array(d2 <= d * d)
            yield pa.RecordBatch.from_arrays([*[x.column(c).filter(keep) for c in ("grp", "focal_id", "other_id", "focal_bit", "other_bit")], pa.array(d2).filter(keep)], names=["grp", "focal_id", "other_id", "focal_bit", "other_bit", "dist2"])

    found = arrow_map(j, run, "grp string, focal_id long, other_id long, focal_bit int, other_bit int, dist2 double")
    lone = units.filter(F.size("rings") <= 0).select("grp", F.col("unit_id").alias("focal_id"), F.col("unit_id").alias("other_id"), F.col("bit").alias("focal_bit"), F.col("bit").alias("other_bit"), F.lit(0.0).alias("dist2"))
    return found.unionByName(lone)


AT_ONCE = 1 << 18  # pairs of edges that are tested at once
CANDIDATES = 1 << 20  # pairs of boxes that are looked at at once
ROUNDS = 4


class Shapes:
    """Polygons of one tile as arrays: edges one after the other, boxes, first points of rings."""

    def __init__(self, rings: pa.ListArray) -> None:
        inner = rings.flatten()
        x, y = (c.to_numpy(zero_copy_only=False).astype(float) for c in inner.flatten().flatten())
        size, parts = inner.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64), rings.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        end = np.cumsum(size)
        after = np.arange(1, len(x) + 1)
        after[end - 1] = end - size  # the last point goes on to the first
        owner = np.repeat(np.arange(len(parts)), parts)
        point_owner = np.repeat(owner, size)
        first = np.flatnonzero(np.diff(point_owner, prepend=-1))
        self.box = [f.reduceat(c, first) for c in (x, y) for f in (np.minimum, np.maximum)]
        last = np.zeros(len(x), bool)
        last[end - 1] = True
        edge = ~(last & (x == x[after]) & (y == y[after]) & (np.repeat(size, size) > 1))  # a ring that is closed has no edge from its last point
        self.ax, self.ay, self.bx, self.by = x[edge], y[edge], x[after][edge], y[after][edge]
        self.count = np.bincount(point_owner[edge], minlength=len(parts))
        self.start = np.cumsum(self.count) - self.count
        self.padded = -(-self.count // 4) * 4
        self.parts, self.part_start = parts, np.cumsum(parts) - parts
        self.px, self.py = x[end - size], y[end - size]
        # four upright edges that go round their box: the polygon is its box
        four = np.flatnonzero((parts == 1) & (self.count == 4))
        at = self.start[four][:, None] + np.arange(4)
        qx, qy = self.ax[at], self.ay[at]
        steps = ((qx != np.roll(qx, -1, 1)) ^ (qy != np.roll(qy, -1, 1))).all(1)
        across = (qx[:, :2] != qx[:, 2:]).all(1) & (qy[:, :2] != qy[:, 2:]).all(1)
        self.is_box = np.zeros(len(parts), bool)
        self.is_box[four] = steps & across

    def edges(self, i: np.ndarray, width: int) -> tuple[np.ndarray, ...]:
        """Edges of polygons i side by side; shorter lists are filled up with edges of no length at their last point."""
        k = np.arange(width)
        at = self.start[i][:, None] + np.minimum(k, self.count[i][:, None] - 1)
        ax, ay, real = self.ax[at], self.ay[at], k < self.count[i][:, None]
        return ax, ay, np.where(real, self.bx[at], ax), np.where(real, self.by[at], ay)

    def corners(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """A point of each ring of polygons i, with repeats."""
        at = self.part_start[i][:, None] + np.minimum(np.arange(self.parts[i].max()), self.parts[i][:, None] - 1)
        return self.px[at], self.py[at]


def _near_edges(px: np.ndarray, py: np.ndarray, edges: tuple[np.ndarray, ...], d2: float) -> np.ndarray:
    """Whether some point of a row lies within the distance of some edge of the same row."""
    ax, ay, bx, by = (e[:, None] for e in edges)
    abx, aby = bx - ax, by - ay
    t = ((px[..., None] - ax) * abx + (py[..., None] - ay) * aby) / np.maximum(abx * abx + aby * aby, 1e-300)
    np.clip(t, 0, 1, out=t)
    x, y = px[..., None] - (ax + t * abx), py[..., None] - (ay + t * aby)
    return (x * x + y * y <= d2).any((1, 2))


def _crossing(p: tuple[np.ndarray, ...], q: tuple[np.ndarray, ...]) -> np.ndarray:
    ax, ay, bx, by = (e[..., None] for e in p)
    cx, cy, dx, dy = (e[:, None] for e in q)
    side = lambda px, py, qx, qy, rx, ry: (qx - px) * (ry - py) - (qy - py) * (rx - px)
    return ((side(ax, ay, bx, by, cx, cy) * side(ax, ay, bx, by, dx, dy) < 0) & (side(cx, cy, dx, dy, ax, ay) * side(cx, cy, dx, dy, bx, by) < 0)).any((1, 2))


def _holding(px: np.ndarray, py: np.ndarray, edges: tuple[np.ndarray, ...]) -> np.ndarray:
    """Whether some point of a row lies inside the polygon of the same row."""
    ax, ay, bx, by = (e[:, None] for e in edges)
    px, py = px[..., None], py[..., None]
    crosses = (ay > py) != (by > py)
    x = ax + (py - ay) / np.where(crosses, by - ay, 1) * (bx - ax)
    return ((crosses & (px < x)).sum(2) % 2 == 1).any(1)


def _blocks(edges: tuple[np.ndarray, ...], width: int) -> Iterator[tuple[np.ndarray, ...]]:
    for k in range(0, edges[0].shape[1], width):
        yield tuple(e[:, k : k + width] for e in edges)


def shapes_meet(s: Shapes, i: np.ndarray, j: np.ndarray, d: float) -> np.ndarray:
    """What `ring_distance2(i, j) <= d * d` gives for many pairs of polygons at once."""
    out = np.zeros(len(i), bool)
    kind = s.padded[i] << 32 | s.padded[j]
    order = np.argsort(kind, kind="stable")
    for rows in np.split(order, np.flatnonzero(np.diff(kind[order])) + 1):
        wide_p, wide_q = int(s.padded[i[rows[0]]]), int(s.padded[j[rows[0]]])
        step = max(1, AT_ONCE // (wide_p * wide_q))
        for k in range(0, len(rows), step):
            left = rows[k : k + step]
            for test in (_touching, _crossed, _held):
                hit = test(s, i[left], j[left], wide_p, wide_q, d * d)
                out[left[hit]] = True
                left = left[~hit]
                if not len(left):
                    break
    return out


def _touching(s: Shapes, i: np.ndarray, j: np.ndarray, wide_p: int, wide_q: int, d2: float) -> np.ndarray:
    p, q = s.edges(i, wide_p), s.edges(j, wide_q)
    hit = np.zeros(len(i), bool)
    for own, other in ((p, q), (q, p)):  # every edge begins at a point of its ring, and every point begins an edge or closes its ring
        for e in _blocks(other, max(4, AT_ONCE // own[0].shape[1])):
            hit |= _near_edges(own[0], own[1], e, d2)
    return hit


def _crossed(s: Shapes, i: np.ndarray, j: np.ndarray, wide_p: int, wide_q: int, d2: float) -> np.ndarray:
    p, q = s.edges(i, wide_p), s.edges(j, wide_q)
    hit = np.zeros(len(i), bool)
    for e in _blocks(q, max(4, AT_ONCE // wide_p)):
        hit |= _crossing(p, e)
    return hit


def _held(s: Shapes, i: np.ndarray, j: np.ndarray, wide_p: int, wide_q: int, d2: float) -> np.ndarray:
    return _holding(*s.corners(i), s.edges(j, wide_q)) | _holding(*s.corners(j), s.edges(i, wide_p))


def _tile_masks(s: Shapes, classes: np.ndarray, d: float, side: float, tx: int, ty: int) -> np.ndarray:
    """Classes that each polygon listed in a tile meets there. Each pair of boxes is looked at in one tile only; a pair is
    tested only if it may add a class, one pair of a polygon and a set of classes a round."""
    x0, x1, y0, y1 = s.box
    mask = np.zeros(len(classes), np.int64)
    here = np.flatnonzero((np.floor(x0 / side) <= tx) & (np.floor(x1 / side) >= tx) & (np.floor(y0 / side) <= ty) & (np.floor(y1 / side) >= ty))
    if not len(here):
        return mask
    here = here[np.argsort(x0[here], kind="stable")]
    widest = float((x1[here] - x0[here]).max())
    low, high = np.searchsorted(x0[here], x0 - d - widest, "left"), np.searchsorted(x0[here], x1 + d, "right")
    many = np.maximum(high - low, 0)
    upto = np.cumsum(many)
    first = 0
    while first < len(classes):
        last = max(first + 1, int(np.searchsorted(upto, upto[first] - many[first] + CANDIDATES, "right")))
        n = many[first:last]
        i = np.repeat(np.arange(first, last), n)
        j = here[np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + low[i]]
        gx, gy = np.maximum(0, np.maximum(x0[j] - x1[i], x0[i] - x1[j])), np.maximum(0, np.maximum(y0[j] - y1[i], y0[i] - y1[j]))
        close = gx * gx + gy * gy <= d * d
        i, j = i[close], j[close]
        home = (np.floor(np.maximum(x0[i] - d, x0[j]) / side) == tx) & (np.floor(np.maximum(y0[i] - d, y0[j]) / side) == ty)
        i, j = i[home], j[home]
        sure = (i == j) | (s.is_box[i] & s.is_box[j])
        np.bitwise_or.at(mask, i[sure], classes[j[sure]])
        i, j = i[~sure], j[~sure]
        for k in range(ROUNDS + 1):
            more = (classes[j] & ~mask[i]) != 0
            i, j = i[more], j[more]
            if not len(i):
                break
            order = np.lexsort((classes[j], i))
            i, j = i[order], j[order]
            new = (np.diff(i, prepend=-1) != 0) | (np.diff(classes[j], prepend=0) != 0) if k < ROUNDS else np.ones(len(i), bool)
            hit = shapes_meet(s, i[new], j[new], d)
            np.bitwise_or.at(mask, i[new][hit], classes[j[new][hit]])
            i, j = i[~new], j[~new]
        first = last
    return mask


def _once(df: DataFrame, name: str) -> DataFrame:
    """A column that is worked out once a row, however often it is used further on: projections are merged across a plain
    column, not across a generator."""
    return df.select(*[c for c in df.columns if c != name], F.explode(F.array(name)).alias(name))


def ring_masks(places: DataFrame, d: float, side: float | None = None) -> DataFrame:
    """places(grp, place, classes, rings), one row a place -> place, mask: classes of all places of the group within d.
    A tile's polygons are sent once and tested together; places without rings have no row."""
    side = side or max(4 * d, 512)
    every = lambda c: F.flatten(F.transform("rings", lambda r: F.transform(r, lambda p: p[c])))
    read = _once(places.filter("grp IS NOT NULL").select("grp", "place", "classes", "rings"), "rings").filter("size(rings) > 0")
    points = _once(read.withColumn("at", F.struct(every("x").alias("x"), every("y").alias("y"))), "at")
    placed = points.select("grp", "place", "classes", "rings", *[f(f"at.{c}").alias(f"{c}{n}") for c in "xy" for n, f in enumerate((F.array_min, F.array_max))])
    listed = placed.withColumn("tx", _tiles(F.col("x0") - d, F.col("x1") + d, side)).withColumn("ty", _tiles(F.col("y0") - d, F.col("y1") + d, side))

    def run(tile: pa.Table) -> pa.Table:
        tx, ty = tile.column("tx")[0].as_py(), tile.column("ty")[0].as_py()
        rings = tile.column("rings").combine_chunks()
        mask = _tile_masks(Shapes(rings), tile.column("classes").to_numpy(), d, side, tx, ty)
        return pa.table({"place": tile.column("place"), "mask": mask}).filter(pa.array(mask != 0))

    met = arrow_groups(listed.select("grp", "tx", "ty", "place", "classes", "rings"), ["grp", "tx", "ty"], run, "place long, mask long")
    return met.groupBy("place").agg(masks.fold("mask").alias("mask"))


# ---- vectors


def metric_pairs(units: DataFrame, eps: float, blocks: int = 8, block_rows: int = 4096) -> DataFrame:
    """units(VEC) -> pairs within eps (Euclidean), in the group.

    Units are dealt into hash blocks; each block meets each block once, as two packed rows, and the pair of blocks is
    worked in one matrix product. Blocks are raised until one holds about block_rows units, so a task's memory is bounded."""
    n = units.count()
    blocks = max(blocks, -(-n // block_rows))
    u = units.withColumn("blk", F.pmod(F.xxhash64("unit_id"), F.lit(blocks)).cast("int"))
    packed = u.groupBy("grp", "blk").agg(F.sort_array(F.collect_list(F.struct("unit_id", "bit", "vec"))).alias("rows"))
    a, b = packed.select("grp", F.col("blk").alias("i"), F.col("rows").alias("ra")), packed.select("grp", F.col("blk").alias("j"), F.col("rows").alias("rb"))
    both = a.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).repartition("grp", "i", "j").join(b, ["grp", "j"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            for grp, ra, rb in zip(x.column("grp"), x.column("ra"), x.column("rb"), strict=True):
                p, q = ra.as_py(), rb.as_py()
                va, vb = np.array([r["vec"] for r in p], float), np.array([r["vec"] for r in q], float)
                d2 = np.maximum((va**2).sum(1)[:, None] + (vb**2).sum(1)[None] - 2 * va @ vb.T, 0)
                ids_a, ids_b = np.array([r["unit_id"] for r in p]), np.array([r["unit_id"] for r in q])
                d2[ids_a[:, None] == ids_b[None]] = 0
                i, j = np.nonzero(d2 <= eps * eps)
                yield pa.RecordBatch.from_arrays([pa.array([grp.as_py()] * len(i), pa.string()), pa.array(ids_a[i]), pa.array(ids_b[j]), pa.array(np.array([r["bit"] for r in p], np.int32)[i]), pa.array(np.array([r["bit"] for r in q], np.int32)[j]), pa.array(np.sqrt(d2[i, j]))], names=["grp", "focal_id", "other_id", "focal_bit", "other_bit", "dist"])

    return arrow_map(both.select("grp", "ra", "rb"), run, "grp string, focal_id long, other_id long, focal_bit int, other_bit int, dist double")


# ---- listings that other tools give; none of them is a transaction


def adjacent(units: DataFrame) -> DataFrame:
    """Units that touch or overlap: focal_id, other_id (without the unit itself)."""
    return rect_pairs(units, 0).filter("focal_id <> other_id").select("grp", "focal_id", "other_id")


def neighborhood_summary(pairs: DataFrame) -> DataFrame:
    """Per focal unit: neighbours, distinct classes among them, least, greatest and sum of class numbers."""
    p = pairs.filter("focal_id <> other_id")
    return p.groupBy("grp", "focal_id").agg(F.count(F.lit(1)).alias("neighbors"), F.bit_count(masks.fold(masks.bit_mask("other_bit"))).cast("long").alias("classes"), F.min("other_bit").cast("long").alias("low"), F.max("other_bit").cast("long").alias("high"), F.sum("other_bit").alias("total"))


def near_table(pairs: DataFrame, k: int, dist: str = "dist2") -> DataFrame:
    """The k nearest others of each focal unit within the pairs' distance; ties by id."""
    rank = F.row_number().over(W.partitionBy("grp", "focal_id").orderBy(dist, "other_id"))
    return pairs.filter("focal_id <> other_id").withColumn("rank", rank).filter(F.col("rank") <= k).select("grp", "focal_id", "other_id", dist, F.col("rank").cast("long").alias("rank"))
