from __future__ import annotations

import random

import numpy as np
import pytest

from copresence.operators import neighborhoods as near
from copresence.operators import transactions
from copresence.sources import workloads as data


@pytest.fixture(scope="module")
def rects(spark):
    r = random.Random(2)
    rows = []
    for i in range(160):
        x, y = r.randrange(600), r.randrange(600)
        rows.append((f"g{i % 2}", i, x, x + r.randrange(120), y, y + r.randrange(60), r.randrange(20)))
    return rows, spark.createDataFrame(rows, "grp string, unit_id long, x0 long, x1 long, y0 long, y1 long, bit int").persist()


def gap2(p, q):
    dx, dy = max(0, q[2] - p[3], p[2] - q[3]), max(0, q[4] - p[5], p[4] - q[5])
    return dx * dx + dy * dy


@pytest.mark.parametrize("d", [0, 25, 60])
def test_rectangles_against_nested_loops(rects, d):
    rows, units = rects
    want = {p[1]: sum(1 << b for b in {q[6] for q in rows if q[0] == p[0] and gap2(p, q) <= d * d}) for p in rows}
    as_dict = lambda df: {r["unit_id"]: r["mask"] for r in df.collect()}
    assert as_dict(transactions.buffer_rect(units, d)) == want
    assert as_dict(transactions.buffer_rect(units, d, salts=3)) == want
    pairs = near.rect_pairs(units, d, side=17)
    assert pairs.count() == pairs.select("focal_id", "other_id").distinct().count() == sum(q[0] == p[0] and gap2(p, q) <= d * d for p in rows for q in rows)
    if d:
        for dense_above in (0, 7, 10**6):  # all focal units by cells, some, none
            assert as_dict(transactions.buffer_rect_by_tiles(units, d, dense_above=dense_above)) == want
    rings = near.rect_as_wkt(units).select("grp", "unit_id", "bit", near.parse_rings("wkt").alias("rings"))
    assert as_dict(transactions.buffer_ring(rings, d)) == want


def test_distance_of_rings():
    square = lambda x, y, s: np.array([(x, y), (x + s, y), (x + s, y + s), (x, y + s)], float)
    apart = lambda *shapes: near.ring_distance2(*[s if isinstance(s, list) else [s] for s in shapes])
    assert apart(square(0, 0, 10), square(3, 3, 2)) == 0  # one inside the other
    assert apart(square(0, 0, 10), square(10, 0, 5)) == 0  # touching
    assert apart(square(0, 0, 10), square(13, 14, 5)) == 25
    ell = np.array([(0, 0), (10, 0), (10, 2), (2, 2), (2, 10), (0, 10)], float)
    assert apart(ell, square(5, 5, 2)) == 9  # in the notch, outside the shape
    assert apart(np.array([(0, 0), (4, 4), (4, 0)], float), np.array([(0, 4), (1, 4), (4, -1), (3, -1)], float)) == 0  # crossing edges
    holed = [square(0, 0, 100), square(10, 10, 80)]
    assert apart(holed, square(48, 48, 2)) == apart(square(48, 48, 2), holed) == 38**2  # in the hole
    assert apart(holed, square(2, 2, 3)) == 0 and apart(holed, [square(10, 10, 80)]) == 0  # in the rim; filling the hole
    assert apart(holed, [*holed[:1], *holed[1:]]) == 0 and apart(holed, square(-20, -20, 200)) == 0  # itself; around it
    parts = [square(0, 0, 2), square(50, 50, 2)]
    assert apart(parts, square(55, 50, 2)) == 9 and apart(parts, square(51, 51, 9)) == 0
    island = [*holed, square(45, 45, 10)]  # a part in the hole of another
    assert apart(island, square(57, 45, 2)) == 4 and apart(island, square(46, 46, 1)) == 0


def cells_of(rings):
    """The unit cells inside, by the even-odd rule at their middles (rings have whole-number, upright edges)."""
    out = set()
    for x in range(-5, 60):
        for y in range(-5, 60):
            odd = 0
            for r in rings:
                for (x1, y1), (x2, y2) in zip(r, r[1:] + r[:1], strict=True):
                    odd += x1 == x2 and x1 > x + 0.5 and min(y1, y2) < y + 0.5 < max(y1, y2)
            if odd % 2:
                out.add((x, y))
    return out


def test_rings_against_cells(spark):
    r = random.Random(12)
    box = lambda x0, y0, x1, y1: [(x0, y0), (x1, y0), (x1, y1), (x0, y1)]

    def shape():
        x, y, w, h = r.randrange(30), r.randrange(30), r.randrange(3, 25), r.randrange(3, 25)
        rings = [box(x, y, x + w, y + h)]
        if r.random() < 0.6 and min(w, h) > 5:
            rings.append(box(x + 1, y + 1, x + w - 1, y + h - 1))  # a hole
            if r.random() < 0.4 and min(w, h) > 9:
                rings.append(box(x + 3, y + 3, x + 5, y + 5))  # a part in the hole
        if r.random() < 0.3:
            rings.append(box(x + w + 2, y, x + w + 4, y + 3))  # another part
        return rings

    shapes = {i: shape() for i in range(40)}
    text = lambda rings: "MULTIPOLYGON ((" + "), (".join("(" + ", ".join(f"{a} {b}" for a, b in [*g, g[0]]) + ")" for g in rings) + "))"
    rows = [("g", i, text(s), i % 7) for i, s in shapes.items()]
    rows += [("g", 100, "POLYGON EMPTY", 3), ("g", 101, None, 4), ("g", 102, "MULTIPOLYGON EMPTY", 5), ("g", 103, "POLYGON ((0 0, x 1, 2 2))", 6)]
    units = spark.createDataFrame(rows, "grp string, unit_id long, wkt string, bit int").select("grp", "unit_id", "bit", near.parse_rings("wkt").alias("rings"))
    cells = {i: cells_of(s) for i, s in shapes.items()}
    gap = lambda p, q: min(max(0, abs(a - c) - 1) ** 2 + max(0, abs(b - d) - 1) ** 2 for a, b in p for c, d in q)
    edge = {i: {c for c in s if not {(c[0] + 1, c[1]), (c[0] - 1, c[1]), (c[0], c[1] + 1), (c[0], c[1] - 1)} <= s} for i, s in cells.items()}
    for d in (0, 2):
        want = {i: sum(1 << b for b in {j % 7 for j in cells if cells[i] & cells[j] or gap(edge[i], edge[j]) <= d * d}) for i in cells}
        got = {x["unit_id"]: x["mask"] for x in transactions.buffer_ring(units, d).collect()}
        assert got == want | {100: 1 << 3, 101: 1 << 4, 102: 1 << 5, 103: 1 << 6}


def test_wider_buffers_only_add(rects):
    units = rects[1]
    small, large = ({r["unit_id"]: r["mask"] for r in transactions.buffer_rect(units, d).collect()} for d in (10, 50))
    assert small.keys() == large.keys() and all(small[k] & large[k] == small[k] for k in small)


def test_spans_and_instants(spark):
    r = random.Random(4)
    rows = [("g", i % 3, i, t, t, r.randrange(8)) for i in range(150) for t in [r.randrange(1000)]]
    units = spark.createDataFrame(rows, "grp string, part long, unit_id long, lo long, hi long, bit int")
    want = {p[2]: sum(1 << b for b in {q[5] for q in rows if q[1] == p[1] and abs(q[3] - p[3]) <= 20}) for p in rows}
    for f in (transactions.buffer_span, transactions.buffer_instant):
        assert {x["unit_id"]: x["mask"] for x in f(units, 20).collect()} == want


def test_cost_and_audit(rects):
    rows, units = rects
    c = near.rect_cost(units, 25).first()
    pairs = [(p, q) for p in rows for q in rows if p[0] == q[0] and gap2(p, q) <= 625]
    assert c["units"] == 160 and c["pairs"] == len(pairs) and c["pairs"] <= c["candidates"] <= c["focal_rows"] * c["other_rows"]
    got = {r["grp"]: r for r in transactions.set_bag_audit(near.rect_pairs(units, 25)).collect()}
    for g in ("g0", "g1"):
        own = [[q[6] for p2, q in pairs if p2 is p] for p in rows if p[0] == g]
        assert (got[g]["transactions"], got[g]["neighbours"], got[g]["classes"]) == (len(own), sum(len(x) - 1 for x in own), sum(len(set(x)) for x in own))
        assert got[g]["collapsed"] == sum(len(x) - len(set(x)) for x in own) and got[g]["affected"] == sum(len(x) > len(set(x)) for x in own)


def test_no_plan_pairs_everything(spark, rects):
    for df in (transactions.buffer_rect(rects[1], 50), transactions.buffer_rect_by_tiles(rects[1], 50, dense_above=7)):
        plan = df._jdf.queryExecution().toString()
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan


def test_vectors(spark):
    rng = np.random.default_rng(1)
    v = rng.normal(size=(60, 4)).astype(np.float32)
    units = spark.createDataFrame([("a", i, [float(x) for x in v[i]], i % 5) for i in range(60)], "grp string, unit_id long, vec array<float>, bit int")
    d = np.sqrt(((v[:, None].astype(float) - v[None]) ** 2).sum(2))
    assert near.metric_pairs(units, 1.5, blocks=3).count() == int((d <= 1.5).sum())


def test_sinks_round_trip(spark, rects, tmp_path):
    from copresence.operators import sinks

    tx = transactions.buffer_rect(rects[1], 25)
    rows = lambda df: sorted(map(tuple, df.collect()))
    sinks.write_text(tx, data.PARTS, f"{tmp_path}/text")
    assert rows(sinks.read_text(spark, f"{tmp_path}/text", data.PARTS)) == rows(transactions.patterns(tx))
    sinks.write_dichotomous(tx, data.PARTS, f"{tmp_path}/wide")
    assert rows(sinks.read_dichotomous(spark, f"{tmp_path}/wide", data.PARTS)) == rows(tx)
    sinks.write_json(tx, f"{tmp_path}/json")
    assert rows(sinks.read_json(spark, f"{tmp_path}/json", "grp string, unit_id long, mask long")) == rows(tx)
    sinks.write_by_group(tx, f"{tmp_path}/parts")
    assert rows(sinks.read_group(spark, f"{tmp_path}/parts", "g1")) == rows(tx.filter("grp = 'g1'"))


def test_rings_equal_rectangles_at_the_full_distance(spark):
    from copresence.plans.queries import QUERIES

    ring, rect = (sorted(map(tuple, QUERIES[n](spark, "/root/testdata/sf0.001").collect())) for n in ("ring_tx_d150", "rect_tx_d150"))
    assert ring == rect and ring


def test_many_pairs_of_polygons_are_tested_as_one_is(monkeypatch):
    """Slanted edges, holes, parts, single points and mixed numbers of edges, in blocks of any size."""
    import pyarrow as pa

    r = random.Random(31)
    point = lambda x, y, s: (x + r.randrange(s), y + r.randrange(s))

    def shape():
        x, y = r.randrange(60), r.randrange(60)
        rings = [[point(x, y, 20) for _ in range(r.choice((1, 2, 3, 4, 7, 13)))] for _ in range(r.choice((1, 1, 2, 3)))]
        if r.random() < 0.3:  # a box, and one with a hole
            w = r.randrange(0, 15)
            rings = [[(x - k, y - k), (x + w + k, y - k), (x + w + k, y + w + k), (x - k, y + w + k)] for k in r.choice(((0,), (9, 6)))]
        return [[*g, g[0]] if r.random() < 0.5 else g for g in rings]

    shapes = [shape() for _ in range(60)]
    array = pa.array([[[{"x": float(a), "y": float(b)} for a, b in g] for g in s] for s in shapes], pa.list_(pa.list_(pa.struct([("x", pa.float64()), ("y", pa.float64())]))))
    as_rings = [[np.array(g, float) for g in s] for s in shapes]
    i, j = (x.ravel() for x in np.meshgrid(np.arange(60), np.arange(60)))
    packed = near.Shapes(array)
    for d in (0, 3):
        want = np.array([near.ring_distance2(as_rings[a], as_rings[b]) <= d * d for a, b in zip(i, j, strict=True)])
        for at_once in (1, 40, 1 << 18):
            monkeypatch.setattr(near, "AT_ONCE", at_once)
            assert (near.shapes_meet(packed, i, j, d) == want).all()
        classes = 1 << (np.arange(60) % 9)
        for candidates in (1, 50, 1 << 20):
            monkeypatch.setattr(near, "CANDIDATES", candidates)
            got = np.zeros(60, np.int64)
            for tx in range(-2, 6):
                for ty in range(-2, 6):
                    got |= near._tile_masks(packed, classes, d, 16, tx, ty)
            assert (got == [np.bitwise_or.reduce(classes[j[(i == a) & want]]) for a in range(60)]).all()
    box = np.flatnonzero(packed.is_box)
    assert len(box) and all(len(shapes[b]) == 1 and len(set(shapes[b][0])) == 4 for b in box)


def test_units_in_one_place_are_tested_once(spark):
    """Two places of 3,000 units each, which are 18 million pairs, and one that lies in the hole of both."""
    import time

    from pyspark.sql import functions as F

    ring = "CASE WHEN id % 2 = 0 THEN 'POLYGON ((0 0, 40 0, 40 40, 0 40, 0 0), (2 2, 38 2, 38 38, 2 38, 2 2))' ELSE 'POLYGON ((1 1, 39 1, 41 39, 1 39, 1 1), (2 2, 38 2, 38 38, 2 38, 2 2))' END"
    units = spark.range(6000).select(F.lit("g").alias("grp"), F.col("id").alias("unit_id"), (F.col("id") % 5).cast("int").alias("bit"), F.expr(ring).alias("wkt"))
    units = units.unionByName(spark.createDataFrame([("g", 9000, 9, "POLYGON ((10 10, 12 10, 11 12))"), ("g", 9001, 10, None), ("g", 9002, 11, None)], "grp string, unit_id long, bit int, wkt string"))
    begin = time.monotonic()
    got = {x["unit_id"]: x["mask"] for x in transactions.buffer_ring(units, 3).collect()}
    assert got == {i: 31 for i in range(6000)} | {9000: 1 << 9, 9001: 1 << 10, 9002: 1 << 11}
    assert time.monotonic() - begin < 120


def test_equal_rectangles_are_joined_once(spark):
    from pyspark.sql import functions as F

    r = random.Random(41)
    boxes = [(x, x + r.randrange(30), y, y + r.randrange(30)) for x, y in ((r.randrange(200), r.randrange(200)) for _ in range(25))]
    rows = [(f"g{i % 2}", i // 2 if i < 20 else i, *r.choice(boxes), r.randrange(20)) for i in range(400)] + [(None, 900, *boxes[0], 1)]  # some ids twice
    units = spark.createDataFrame(rows, "grp string, unit_id long, x0 long, x1 long, y0 long, y1 long, bit int")
    for d in (0, 25):
        got, want = (sorted(map(tuple, f(units, d).collect())) for f in (transactions.buffer_rect_by_places, transactions.buffer_rect))
        assert got == want and want
    many = spark.range(20_000).select(F.lit("g").alias("grp"), F.col("id").alias("unit_id"), *[F.lit(v).cast("long").alias(c) for c, v in zip(("x0", "x1", "y0", "y1"), boxes[0], strict=True)], (F.col("id") % 7).cast("int").alias("bit"))
    assert transactions.buffer_rect_by_places(many, 50).groupBy("mask").count().collect() == [(127, 20_000)]  # 400 million pairs of units


def test_rings_are_read_once_and_units_join_without_texts(spark):
    """The plan that lists places on tiles reads a text once, and the one that gives units their masks holds no sort of texts."""
    from unittest import mock

    from pyspark.sql import functions as F

    shown, plans = lambda df: df._jdf.queryExecution().executedPlan().toString(), []
    units = spark.range(400).select(F.lit("g").alias("grp"), F.col("id").alias("unit_id"), (F.col("id") % 5).cast("int").alias("bit"), F.expr("concat('POLYGON ((', id % 50, ' 0, ', id % 50 + 3, ' 0, ', id % 50, ' 4))')").alias("wkt"))
    units = units.unionByName(spark.createDataFrame([("g", 900, 9, None), ("g", 901, 10, "POLYGON EMPTY"), (None, 902, 11, None)], "grp string, unit_id long, bit int, wkt string"))
    made = near.arrow_groups
    with mock.patch.object(near, "arrow_groups", lambda df, *a: plans.append(shown(df)) or made(df, *a)), mock.patch.object(transactions, "digests_differ", wraps=transactions.digests_differ) as asked:
        got = transactions.buffer_ring(units, 3)
    assert asked.call_count == 1 and plans[0].count("regexp_extract_all(") == 1
    assert "xxhash64(wkt" in shown(got) and "ShuffledHashJoin" in shown(got)
    as_dict = lambda df: {r["unit_id"]: (r["grp"], r["mask"]) for r in df.collect()}
    with mock.patch.object(transactions, "digests_differ", return_value=False):  # as where two texts have one digest
        assert as_dict(transactions.buffer_ring(units, 3)) == as_dict(got)
    assert as_dict(got) == {i: ("g", 31) for i in range(400)} | {900: ("g", 1 << 9), 901: ("g", 1 << 10), 902: (None, 1 << 11)}
    twice = spark.createDataFrame([("g", "a"), ("g", "a"), ("h", "b")], "grp string, wkt string")
    assert not transactions.digests_differ(twice) and transactions.digests_differ(twice.distinct())
